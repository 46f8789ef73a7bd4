"""Shapes of physical plans, rewrites, relational steps and streams."""

import re
import uuid

from pyspark.sql import functions as F

from tidegraph.functions import relational as R
from tidegraph.graph import PropertyGraph
from tidegraph.plans import layout
from tidegraph.plans.logical import Step, VertexFunction, eliminate_join, improves, push_compute, drop_messages, rewrite
from tidegraph.runtime import scratch_root
from tidegraph.sources import derived as G, files
from tidegraph.streaming.edges import ComponentKeeper, DistanceKeeper, run_available, sessions, timed, tumbling
from tidegraph.vertexprog.api import Components, Ranking, ShortestPath
from tidegraph.vertexprog.runners import register_udtfs, run_program


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def values(df):
    other = [c for c in df.columns if c != "id"][0]
    return {r["id"]: r[other] for r in df.collect()}


def test_selection_is_pushed_and_columns_are_pruned(spark, sf):
    orders = G.table(spark, sf, "orders").where("o_orderpriority = '1-URGENT'").select("o_orderkey")
    text = plan(orders)
    assert "EqualTo(o_orderpriority,1-URGENT)" in text
    assert re.search(r"ReadSchema: struct<o_orderkey:bigint,o_orderpriority:string>", text)


def test_bucketed_copies_join_without_exchange(spark):
    edges = spark.range(2000).select((F.col("id") % 97).alias("src"), (F.col("id") % 89).alias("dst"))
    g = PropertyGraph(spark.range(100), edges)
    name = f"t{uuid.uuid4().hex[:8]}"
    tables = layout.write_bucketed(g, name, 4)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        v, by_dst = spark.table(tables["id"]), spark.table(tables["dst"])
        same = v.join(by_dst, v["id"] == by_dst["dst"]).groupBy("dst").count()
        other = v.join(by_dst, v["id"] == by_dst["dst"]).groupBy("src").count()
        assert "Exchange" not in plan(same)
        assert plan(other).count("Exchange hashpartitioning") == 1
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "10485760")
        for t in tables.values():
            spark.sql(f"DROP TABLE {t}")


def test_one_pass_aggregates_and_settings(spark):
    from tidegraph.plans import physical

    before = spark.conf.get("spark.sql.execution.replaceHashWithSortAgg")
    with physical.settings(spark, spark__sql__autoBroadcastJoinThreshold="-1", spark__sql__adaptive__enabled="false"), physical.one_pass_aggregates(spark):
        e = spark.range(1000).select((F.col("id") % 7).alias("dst"), "id")
        joined = e.join(spark.range(7).withColumnRenamed("id", "dst").hint("merge"), "dst").groupBy("dst").agg(F.min("id"))
        text = plan(joined)
        assert "SortAggregate" in text and "HashAggregate" not in text
    assert spark.conf.get("spark.sql.execution.replaceHashWithSortAgg") == before


def test_stateful_and_joined_streams(spark):
    from tidegraph.streaming.edges import deduplicated, running_degrees, with_vertices

    folder = f"{scratch_root(spark)}/{uuid.uuid4().hex}"
    spark.createDataFrame([(0, 1), (0, 2), (1, 2), (0, 1)], "src long, dst long").repartition(2).write.parquet(f"{folder}/in")
    stream = lambda: spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    names = spark.createDataFrame([(0, "zero"), (1, "one")], "id long, name string")
    got = []
    for k, (df, mode) in enumerate(((running_degrees(stream()), "update"), (with_vertices(stream(), names), "append"))):
        name = f"q{uuid.uuid4().hex[:6]}"
        query = df.writeStream.trigger(availableNow=True).option("checkpointLocation", f"{folder}/c{k}").outputMode(mode).format("memory").queryName(name).start()
        query.awaitTermination()
        got.append(spark.table(name).collect())
    assert max(r.degree for r in got[0] if r.id == 0) == 3 and len(got[1]) == 4 and {r.name for r in got[1]} == {"zero", "one"}
    assert deduplicated(stream().withColumn("ts", F.current_timestamp()).withWatermark("ts", "1 hour"), ["src", "dst"]).isStreaming


def test_user_functions(spark):
    from tidegraph.vertexprog import udf

    v = spark.createDataFrame([(0, 1.0), (1, 3.0)], "id long, value double")
    e = spark.createDataFrame([(0, 2, 2.0), (1, 2, 1.0), (1, 0, 5.0)], "src long, dst long, w double")
    out = udf.gather(v, e, udf.message_udf(lambda a, w: a * w), udf.combine_udaf(lambda m: float(m.max())))
    assert values(out) == {2: 3.0, 0: 15.0}


def test_rules(spark):
    g = PropertyGraph(spark.range(3), spark.createDataFrame([(0, 1)], "src long, dst long"), True, True)
    step = Step(VertexFunction(lambda v, w: v + w, "min", improves))
    assert not drop_messages(push_compute(step)).stored_messages and drop_messages(step).stored_messages
    assert rewrite(step, g).frontier and rewrite(step, g).target_join
    summing = Step(VertexFunction(lambda v, w: v, "sum"), reads_old=False)
    assert not eliminate_join(summing, g).target_join and not rewrite(summing, g).frontier
    g.dst_in_vertices = False
    assert eliminate_join(summing, g).target_join


def test_histogram_keeps_empty_bins(spark):
    df = spark.createDataFrame([(0.0,), (0.1,), (1.0,), (None,)], "x double")
    rows = R.histogram(df, "x", 4).orderBy("bucket").collect()
    assert [r.n for r in rows] == [2, 0, 0, 1]
    assert R.histogram(df.where("x > 5"), "x", 4).count() == 0


def test_range_and_as_of_joins(spark):
    points = spark.createDataFrame([(1, 5.0), (2, 10.0), (3, 25.0)], "p long, x double")
    ranges = spark.createDataFrame([("a", 0.0, 10.0), ("b", 8.0, 26.0)], "r string, lo double, hi double")
    got = {(r.p, r.r) for r in R.range_join(points, ranges, "x", "lo", "hi", 7.0).collect()}
    assert got == {(1, "a"), (2, "b"), (3, "b")}
    left = spark.createDataFrame([("k", 5), ("k", 1), ("z", 9)], "key string, at long")
    right = spark.createDataFrame([("k", 2, 20), ("k", 5, 50)], "key string, at long, v long")
    assert {(r.key, r.at): r.last_v for r in R.as_of(left, right, "key", "at", "v").collect()} == {("k", 5): 50, ("k", 1): None, ("z", 9): None}


def test_edge_files_round_trip(spark):
    folder = f"{scratch_root(spark)}/{uuid.uuid4().hex}"
    edges = spark.createDataFrame([(1, 2), (1, 3), (4, 1)], "src long, dst long")
    files.write_edge_list(edges, f"{folder}/l")
    files.write_adjacency(edges, f"{folder}/a")
    want = {(1, 2), (1, 3), (4, 1)}
    assert {tuple(r) for r in files.read_edge_list(spark, f"{folder}/l").collect()} == want
    assert {tuple(r) for r in files.read_adjacency(spark, f"{folder}/a").collect()} == want
    spark.createDataFrame([("1\t2",), ("x\t2",), ("3",)], "value string").write.text(f"{folder}/bad")
    assert {tuple(r) for r in files.read_edge_list(spark, f"{folder}/bad").collect()} == {(1, 2)}


def test_vertex_programs_agree_over_all_inputs(spark):
    edges = spark.createDataFrame([(0, 1), (1, 2), (0, 2), (2, 3), (3, 0)], "src long, dst long")
    g = PropertyGraph(spark.range(5), edges)
    want = {0: 0.0, 1: 1.0, 2: 1.0, 3: 2.0, 4: None}
    for kind in ("union", "join", "resident", "barrier"):
        out, report = run_program(g, ShortestPath(0), kind, parts=2)
        assert values(out) == want and report.converged
    assert values(run_program(g, ShortestPath(0), "union", batch_vertices=1)[0]) == want
    ranks = values(run_program(g, Ranking(5, 4), "union")[0])
    from tidegraph.operators.pagerank import pagerank

    assert all(abs(v - ranks[k]) < 1e-12 for k, v in values(pagerank(g, rounds=4)).items())
    assert set(values(run_program(g.symmetrised(), Components(), "resident")[0]).values()) == {0.0, 4.0}


def test_superstep_as_a_table_function(spark):
    register_udtfs(spark)
    rows = [(0, 0, 0, None, 0.0), (0, 0, 1, 1, None), (0, 1, 0, None, None), (0, 1, 2, None, 1.0), (0, 1, 1, 2, None)]
    spark.createDataFrame(rows, "part int, id long, kind int, dst long, value double").createOrReplaceTempView("rows_in")
    got = spark.sql("SELECT * FROM vertex_step(TABLE(SELECT * FROM rows_in) PARTITION BY part ORDER BY (id, kind))").collect()
    assert {(r.kind, r.id, r.value) for r in got} == {("v", 0, 0.0), ("v", 1, 1.0), ("m", 2, 2.0)}


def test_streams_keep_results(spark, sf):
    folder = f"{scratch_root(spark)}/{uuid.uuid4().hex}"
    edges = spark.createDataFrame([(0, 1), (1, 2), (5, 6), (2, 3), (3, 5), (8, 9)], "src long, dst long")
    edges.repartition(3).write.parquet(f"{folder}/in")
    stream = spark.readStream.schema("src long, dst long").option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")
    parts = ComponentKeeper()
    run_available(stream, parts.process, f"{folder}/c1")
    assert values(parts.components()) == {0: 0, 1: 0, 2: 0, 3: 0, 5: 0, 6: 0, 8: 8, 9: 8}
    hops = DistanceKeeper(spark.range(10), 0)
    run_available(stream, hops.process, f"{folder}/c2")
    got = values(hops.state.current())
    assert got[6] == 5 and got[3] == 3 and got[9] is None


def test_windows_over_a_stream_match_the_batch(spark, sf):
    folder = f"{scratch_root(spark)}/{uuid.uuid4().hex}"
    events = G.table(spark, sf, "events")
    events.write.parquet(f"{folder}/in")
    stream = timed(spark.readStream.schema(events.schema).parquet(f"{folder}/in"))
    name = f"w{uuid.uuid4().hex[:6]}"
    query = tumbling(stream).writeStream.trigger(availableNow=True).option("checkpointLocation", f"{folder}/c").outputMode("append").format("memory").queryName(name).start()
    query.awaitTermination()
    got = {(r.start, r.event_type): r.n for r in spark.table(name).collect()}
    batch = {(r.start, r.event_type): r.n for r in tumbling(events.withColumn("ts", F.col("ts").cast("timestamp"))).collect()}
    assert got and all(batch[k] == v for k, v in got.items())
    assert sessions(events.withColumn("ts", F.col("ts").cast("timestamp"))).agg(F.sum("n")).first()[0] == events.count()


def test_all_queries_are_registered():
    import __spark_entry__ as entry

    names = set(entry.queries())
    assert {"w_sssp_hops", "w_pagerank_10", "w_cc", "w_strong_overlap", "w_weak_ties"} <= names
    assert set(entry.oracle_sql()) <= names


def test_vector_programs_agree_with_vertex_programs(spark):
    import random

    r = random.Random(3)
    pairs = sorted({(r.randrange(60), r.randrange(60)) for _ in range(150)})
    g = PropertyGraph(spark.range(64), spark.createDataFrame(pairs, "src long, dst long"))
    for program in (ShortestPath(pairs[0][0]), Ranking(64, 6), Components()):
        one, two = values(run_program(g, program, "union")[0]), values(run_program(g, program, "barrier", parts=3)[0])
        assert one.keys() == two.keys() and all(v == two[k] or abs(v - two[k]) < 1e-12 for k, v in one.items())


def test_one_hop_programs_agree_with_joins(spark):
    from tidegraph.operators import motifs as M
    from tidegraph.vertexprog.api import NeighbourOverlap, NeighbourTies

    edges = spark.createDataFrame([(a, b) for a in range(12) for b in range(a + 1, 12) if (a * b + a + b) % 3], "src long, dst long")
    g = PropertyGraph(spark.range(12), edges).symmetrised()
    got = {(x[0], r["id"], x[1]) for r in run_program(g, NeighbourOverlap(2), "union")[0].collect() for x in r["state"]}
    assert got == {tuple(r) for r in M.strong_overlap(g, 2).collect()} and got
    ties = {k: v for k, v in values(run_program(g, NeighbourTies(), "join")[0]).items() if v > 3}
    assert ties == values(M.weak_ties(g, 3)) and ties


def test_settings_come_back_after_a_failing_program(spark):
    class Failing(ShortestPath):
        def compute(self, ctx, vertex, state, messages, edges):
            raise RuntimeError("no")

    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    g = PropertyGraph(spark.range(2), spark.createDataFrame([(0, 1)], "src long, dst long"))
    try:
        run_program(g, Failing(0), "union", batch_vertices=7)
        raise AssertionError("ran")
    except Exception as e:
        assert "no" in str(e)
    assert spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch") == before


def test_a_round_over_bucketed_copies_moves_no_edges(spark):
    from tidegraph.plans.physical import settings

    edges = spark.range(3000).select((F.col("id") % 97).alias("src"), (F.col("id") % 89).alias("dst"))
    name = f"t{uuid.uuid4().hex[:8]}"
    tables = layout.write_bucketed(PropertyGraph(spark.range(100), edges), name, 4)
    try:
        with settings(spark, spark__sql__autoBroadcastJoinThreshold="-1"):
            ranks = spark.table(tables["id"]).select(F.col("id").alias("src"), F.lit(0.1).alias("share"))
            moved = layout.DealtEdges(spark.table(tables["src"]), kept=False).meet(ranks)
            assert "Exchange" not in plan(moved)
            sums = moved.groupBy("dst").agg(F.sum("share"))
            text = plan(sums)
            assert text.count("Exchange hashpartitioning") == 1 and text.index("Exchange hashpartitioning") < text.index("SortMergeJoin")
    finally:
        for t in tables.values():
            spark.sql(f"DROP TABLE {t}")


def test_collaborative_filtering_beats_the_mean(spark):
    from tidegraph.vertexprog.cf import collaborative_filtering

    rows = [(u, i, float(1 + (u % 3) * (i % 2) * 2)) for u in range(24) for i in range(16) if (u * i) % 5]
    ratings = spark.createDataFrame(rows, "user long, item long, rating double")
    few, many = (collaborative_filtering(ratings, 4, k)[1].first() for k in (2, 16))
    assert many["rmse"] < 0.6 * many["rmse_mean"] and many["rmse"] < few["rmse"]
