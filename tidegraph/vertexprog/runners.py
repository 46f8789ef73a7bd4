"""Runners of vertex programs: partitioned table functions over joined or united input, resident state, and a barrier stage."""

from __future__ import annotations

import base64
import pickle
import time
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Observation, functions as F

from tidegraph.graph import PropertyGraph
from tidegraph.plans.iterate import RunReport
from tidegraph.plans.layout import DealtEdges, counted, parts_for
from tidegraph.plans.physical import settings
from tidegraph.runtime import Scratch, materialize, ship
from tidegraph.vertexprog.api import Context, VertexProgram
from tidegraph.vertexprog.peers import Peers

#: Resident state is written once in so many supersteps, which bounds what a lost executor makes others compute again.
CUT_EVERY = 10
#: Vertices and edges a barrier stage may hold, as it cannot retry a part. A larger graph runs a job for each superstep.
BARRIER_ROWS = 5_000_000


def _step(program: VertexProgram, superstep: int, vertex, state, messages: list, edges: list):
    ctx = Context(superstep)
    state = program.compute(ctx, vertex, state, messages, edges)
    return state, ctx.outbox, ctx.halted


def _schema(program: VertexProgram, kind: str) -> str:
    return f"kind string, id {kind}, dst {kind}, state {program.state_type}, message {program.message_type}, halted boolean, active boolean"


def _rows(program, superstep, vertex, state, halted, messages, edges, out: list) -> None:
    """Runs a vertex if it has messages or has not halted; adds its state row and its message rows."""
    active = superstep == 0 or bool(messages) or not halted
    sent = []
    if active:
        state, sent, halted = _step(program, superstep, vertex, state, messages, edges)
    out.append(("v", vertex, None, state, None, halted, active))
    if program.combine is not None and sent:
        merged: dict = {}
        for dst, m in sent:
            merged[dst] = program.combine(merged[dst], m) if dst in merged else m
        sent = list(merged.items())
    out.extend(("m", vertex, dst, None, m, None, None) for dst, m in sent)


_COLUMNS = ["kind", "id", "dst", "state", "message", "halted", "active"]
#: Rows that a vector step takes at once; stands for a null id, which sorts first.
VECTOR_ROWS, NO_ID = 100_000, -(1 << 63)


def _has_vectors(program: VertexProgram, kind: str) -> bool:
    return hasattr(program, "vector_step") and kind == "bigint"


def _vector_rows(program, superstep, ids, state, received, got, at, dst, w) -> pa.RecordBatch:
    """What ``_rows`` gives, of many vertices at once. ``at``: the place of each edge's source in ``ids``; ``got``: who has messages."""
    if not superstep:
        state = np.asarray(program.vector_init(ids), dtype=np.float64)
    active = got | (superstep == 0 or program.vector_awake(superstep - 1))
    state, value, sends = program.vector_step(superstep, ids, state, received, np.bincount(at, minlength=len(ids)))
    used = np.flatnonzero(sends[at])
    at, dst, message = at[used], dst.take(pa.array(used)), np.asarray(program.vector_message(value[at[used]], w[used]), dtype=np.float64)
    to = dst.fill_null(NO_ID).to_numpy()
    if program.combine is not None and len(at):
        order = np.lexsort((to, at))
        heads = np.flatnonzero(np.append(True, (np.diff(at[order]) != 0) | (np.diff(to[order]) != 0)))
        message = (np.add if program.identity == 0.0 else np.minimum).reduceat(message[order], heads)
        at, to = at[order][heads], to[order][heads]
    n, m = len(ids), len(at)
    flags = [np.full(n, not program.vector_awake(superstep)), active]
    out = [
        pa.concat_arrays([pa.repeat("v", n), pa.repeat("m", m)]),
        pa.array(np.concatenate([ids, ids[at]]), mask=np.concatenate([ids, ids[at]]) == NO_ID),
        pa.array(np.concatenate([np.full(n, NO_ID), to]), mask=np.concatenate([np.full(n, NO_ID), to]) == NO_ID),
        pa.concat_arrays([pa.array(state, pa.float64(), mask=~np.isfinite(state)), pa.nulls(m, pa.float64())]),
        pa.concat_arrays([pa.nulls(n, pa.float64()), pa.array(message, pa.float64())]),
        *[pa.concat_arrays([pa.array(x), pa.nulls(m, pa.bool_())]) for x in flags],
    ]
    return pa.RecordBatch.from_arrays(out, _COLUMNS)


def _merged(program, messages: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """The combined message of each of ``n`` vertices, the identity without one."""
    if program.identity == 0.0:
        return np.bincount(at, weights=messages, minlength=n).astype(np.float64)
    out = np.full(n, program.identity)
    np.minimum.at(out, at, messages)
    return out


def _numbers(column: pa.Array, null: float) -> np.ndarray:
    return column.cast(pa.float64()).fill_null(null).to_numpy(zero_copy_only=False)


def _vector_union(program, superstep):
    """A vector step over vertices, edges and messages that come sorted by vertex and kind."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Chunks in which no vertex is cut."""
        held, rows = [], 0
        for batch in batches:
            if not batch.num_rows:
                continue
            held.append(batch)
            rows += batch.num_rows
            if rows >= VECTOR_ROWS and batch["id"][-1] != held[0]["id"][0]:
                chunk = pa.Table.from_batches(held).combine_chunks().to_batches()[0]
                ids = chunk["id"].fill_null(NO_ID).to_numpy()
                cut = int(np.searchsorted(ids, ids[-1]))
                yield chunk.slice(0, cut)
                held, rows = [chunk.slice(cut)], rows - cut
        if held:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for chunk in whole(batches):
            every, kind = chunk["id"].fill_null(NO_ID).to_numpy(), chunk["kind"].to_numpy()
            own = np.flatnonzero(kind == 0)
            ids = every[own]
            last = np.flatnonzero(np.append(ids[1:] != ids[:-1], True)) if len(ids) else own[:0]
            own, ids = own[last], ids[last]
            if not len(ids):
                continue
            place = np.minimum(np.searchsorted(ids, every), len(ids) - 1)
            known = ids[place] == every
            edges, inbox = (np.flatnonzero((kind == k) & known) for k in (1, 2))
            took = lambda c, rows: chunk[c].take(pa.array(rows))
            received = _merged(program, _numbers(took("message", inbox), program.identity), place[inbox], len(ids))
            got = np.bincount(place[inbox], minlength=len(ids)) > 0
            yield _vector_rows(program, superstep, ids, _numbers(took("state", own), np.inf), received, got, place[edges], took("dst", edges), _numbers(took("w", edges), np.nan))

    return run


def _vector_join(program, superstep):
    """A vector step over a row for each vertex, with its edges and messages as lists."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            edges, inbox = batch["edges"], batch["inbox"]
            of = lambda lists: np.repeat(np.arange(n), pc.list_value_length(lists).fill_null(0).to_numpy())
            flat, at, to = edges.flatten(), of(edges), of(inbox)
            received = _merged(program, _numbers(inbox.flatten(), program.identity), to, n)
            yield _vector_rows(program, superstep, batch["id"].fill_null(NO_ID).to_numpy(), _numbers(batch["state"], np.inf), received, np.bincount(to, minlength=n) > 0, at, flat.field("dst"), _numbers(flat.field("w"), np.nan))

    return run


def run_program(
    graph: PropertyGraph, program: VertexProgram, input: str = "union", weight: str | None = None, parts: int | None = None, batch_vertices: int = 10_000, disk: bool = True, max_supersteps: int | None = None
) -> tuple[DataFrame, RunReport]:
    """``(id, state)`` after the program's supersteps, and the report with rounds, messages and phase times.

    ``input``: 'union' sends vertices, edges and messages of a part to the function as one sorted relation and lets it tell
    them apart; 'join' joins them first and calls the function once for each vertex group; 'resident' keeps edges and states
    in executor memory and writes nothing between rounds; 'barrier' runs all supersteps in one barrier stage that holds the
    graph in its workers, on arrays where the program has a vector form and ids are longs; beyond BARRIER_ROWS the vector form
    runs a job for each superstep, and a program without one is refused. The other inputs step through the vector form too where
    there is one, and vertex by vertex where there is none. ``batch_vertices`` sets how many rows a call receives at once. ``disk=False``
    keeps the round's output in memory instead of writing it.
    """
    spark = graph.vertices.sparkSession
    ship(spark)
    if input == "barrier":
        return _run_barrier(graph, program, weight, parts or min(4, spark.sparkContext.defaultParallelism), max_supersteps)
    kind = dict(graph.vertices.dtypes)["id"]
    report = RunReport()
    began = time.time()
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    # Derived once, and in as many parts as their number asks for: a superstep starts a function in each.
    written, rows = counted(graph.edges.select(F.col("src").alias("id"), "dst", w.alias("w")), "edges")
    n = parts or parts_for(rows, int(spark.conf.get("spark.sql.shuffle.partitions")))
    edges = written.df.repartition(n, "id")
    if input == "join":
        # Lists do not change between supersteps.
        edges = edges.groupBy("id").agg(F.collect_list(F.struct("dst", "w")).alias("edges"))
    edges = edges.persist(StorageLevel.MEMORY_AND_DISK)

    @F.udf(program.state_type)
    def first_state(vertex):
        return program.init(vertex)

    schema = _schema(program, kind)
    # A vector form makes its first states itself.
    start = F.lit(None).cast(program.state_type) if _has_vectors(program, kind) else first_state("id")
    vertices = graph.vertices.select("id", start.alias("state"), F.lit(False).alias("halted"))
    keep_on_disk = disk and input != "resident"
    hold = _written if keep_on_disk else _cached
    vertices, release = hold(vertices)
    messages, message_rows = None, 0
    report.phases["load"] = time.time() - began
    limit = max_supersteps or program.max_supersteps
    combine_sql = _combiner(program)
    began = time.time()
    with settings(spark, spark__sql__execution__arrow__maxRecordsPerBatch=batch_vertices):
        for superstep in range(limit):
            t = time.time()
            if input == "join":
                out = _join_step(vertices, edges, messages, program, superstep, schema, _has_vectors(program, kind))
            else:
                out = _union_step(vertices, edges, messages, program, superstep, schema, n, _has_vectors(program, kind))
            if not keep_on_disk and superstep % CUT_EVERY == CUT_EVERY - 1:
                out, release_next = _written(out)
            else:
                out, release_next = hold(out)
            vertices = out.where("kind = 'v'").select("id", "state", "halted")
            messages = out.where("kind = 'm'").select(F.col("dst").alias("id"), "message")
            if combine_sql is not None:
                messages = messages.groupBy("id").agg(combine_sql("message").alias("message"))
            counts = out.agg(F.count_if(F.col("kind") == "m").alias("m"), F.count_if((F.col("kind") == "v") & ~F.col("halted")).alias("awake"), F.count_if("active").alias("ran")).first()
            report.rounds.append({"round": superstep, "seconds": time.time() - t, "updates": counts["ran"], "applied": "write" if keep_on_disk else "keep", "messages": counts["m"]})
            release()
            release = release_next
            if not counts["m"] and not counts["awake"]:
                report.converged = True
                break
    report.phases["analysis"] = time.time() - began
    began = time.time()
    result = materialize(vertices.select("id", "state"), "result").df
    report.phases["store"] = time.time() - began
    release()
    edges.unpersist()
    written.drop()
    return result, report


def _written(df: DataFrame):
    """``df`` as a written table, and what drops it."""
    table = materialize(df, "superstep", free=True)
    return table.df, table.drop


def _cached(df: DataFrame):
    """``df`` kept in memory under a plan of its own, so that plans do not grow by the round, and what lets it go.

    A lost part is computed again, from the last written round at most (see CUT_EVERY).
    """
    kept = df.persist(StorageLevel.MEMORY_AND_DISK)
    rows = kept._jdf.queryExecution().toRdd()
    return DataFrame(kept.sparkSession._jsparkSession.internalCreateDataFrame(rows, kept._jdf.schema(), False), kept.sparkSession), kept.unpersist


def _combiner(program: VertexProgram):
    """The combiner as a Spark aggregate where it is one, so that messages combine before they are shuffled."""
    if program.combine is min:
        return F.min
    if program.combine is not None and program.message_type == "double" and program.combine(2.0, 3.0) == 5.0:
        return F.sum
    return None


def _union_step(vertices, edges, messages, program, superstep, schema, n, vectors=False) -> DataFrame:
    kinds = [
        vertices.select("id", F.lit(0).alias("kind"), "state", "halted"),
        edges.select("id", F.lit(1).alias("kind"), "dst", "w"),
    ]
    united = kinds[0].unionByName(kinds[1], allowMissingColumns=True)
    if messages is not None:
        united = united.unionByName(messages.select("id", F.lit(2).alias("kind"), "message"), allowMissingColumns=True)
    else:
        united = united.withColumn("message", F.lit(None).cast(program.message_type))
    dealt = united.repartition(n, "id").sortWithinPartitions("id", "kind")
    if vectors:
        return dealt.select("id", "kind", "state", "dst", "w", "message").mapInArrow(_vector_union(program, superstep), schema)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        vertex, state, halted, edge_list, inbox, seen = None, None, False, [], [], False
        for frame in frames:
            out: list = []
            plain = frame.astype(object).where(frame.notna(), None) if len(frame) else frame
            for row in zip(plain["id"], plain["kind"], plain["state"], plain["halted"], plain["dst"], plain["w"], plain["message"]):
                if row[0] != vertex:
                    if seen:
                        _rows(program, superstep, vertex, state, halted, inbox, edge_list, out)
                    vertex, state, halted, edge_list, inbox, seen = row[0], None, False, [], [], False
                if row[1] == 0:
                    state, halted, seen = row[2], bool(row[3]), True
                elif row[1] == 1:
                    edge_list.append((row[4], row[5]))
                else:
                    inbox.append(row[6])
            yield pd.DataFrame(out, columns=_COLUMNS, dtype=object)
        if seen:
            out = []
            _rows(program, superstep, vertex, state, halted, inbox, edge_list, out)
            yield pd.DataFrame(out, columns=_COLUMNS, dtype=object)

    return dealt.mapInPandas(run, schema)


def _join_step(vertices, lists, messages, program, superstep, schema, vectors=False) -> DataFrame:
    joined = vertices.join(lists, "id", "left")
    if messages is not None:
        joined = joined.join(messages.groupBy("id").agg(F.collect_list("message").alias("inbox")), "id", "left")
    else:
        joined = joined.withColumn("inbox", F.lit(None).cast(f"array<{program.message_type}>"))
    if vectors:
        return joined.select("id", "state", "edges", "inbox").mapInArrow(_vector_join(program, superstep), schema)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out: list = []
            for vertex, state, halted, own, inbox in zip(frame["id"], frame["state"], frame["halted"], frame["edges"], frame["inbox"]):
                state = None if state is None or (isinstance(state, float) and state != state) else state
                own = [(e["dst"], e["w"]) for e in own] if own is not None else []
                _rows(program, superstep, vertex, state, bool(halted), list(inbox) if inbox is not None else [], own, out)
            yield pd.DataFrame(out, columns=_COLUMNS, dtype=object)

    return joined.select("id", "state", "halted", "edges", "inbox").mapInPandas(run, schema)


def _run_barrier(graph, program, weight, parts, max_supersteps) -> tuple[DataFrame, RunReport]:
    """All supersteps in one barrier stage: workers hold their part and exchange messages at a barrier."""
    spark = graph.vertices.sparkSession
    kind = dict(graph.vertices.dtypes)["id"]
    w = F.col(weight).cast("double") if weight else F.lit(1.0)
    edges, rows = counted(graph.edges.select("src", "dst", w.alias("w")), "edges")
    rows += graph.vertices.count()
    arrays = _has_vectors(program, kind)
    if rows > BARRIER_ROWS:
        if not arrays:
            raise ValueError(f"{rows} rows; a barrier stage may hold {BARRIER_ROWS}")
        return _run_rounds(graph.vertices, edges, program, max_supersteps or program.max_supersteps)
    united = graph.vertices.select("id", F.lit(None).cast(kind).alias("dst"), F.lit(0.0).alias("w")).unionByName(edges.df.select(F.col("src").alias("id"), "dst", "w"))
    if arrays:
        return _run_vectors(united, program, parts, max_supersteps or program.max_supersteps)
    home = F.pmod(F.xxhash64("id"), F.lit(parts)).cast("int")
    table = materialize(united.withColumn("part", home), "resident").df
    places = materialize(graph.vertices.select("id", home.alias("part")), "places").df
    limit = max_supersteps or program.max_supersteps
    dealt = table.join(places.select(F.col("id").alias("dst"), F.col("part").alias("to")), "dst", "left").repartitionByRange(parts, "part")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import BarrierTaskContext

        barrier = BarrierTaskContext.get()
        states, edges, owner = {}, {}, {}
        for frame in frames:
            frame = frame.astype(object).where(frame.notna(), None)
            for vertex, dst, w, to in zip(frame["id"], frame["dst"], frame["w"], frame["to"]):
                if dst is None:
                    states.setdefault(vertex, [program.init(vertex), False])
                else:
                    edges.setdefault(vertex, []).append((dst, w))
                    owner[dst] = to
        inbox: dict = {}
        for superstep in range(limit):
            sent: dict = {}
            awake = False
            for vertex, held in states.items():
                messages = inbox.get(vertex, [])
                if superstep and not messages and held[1]:
                    continue
                held[0], out, held[1] = _step(program, superstep, vertex, held[0], messages, edges.get(vertex, []))
                awake |= not held[1]
                for dst, m in out:
                    if program.combine is not None and dst in sent:
                        sent[dst] = [program.combine(sent[dst][0], m)]
                    else:
                        sent.setdefault(dst, []).append(m)
            packed = base64.b64encode(pickle.dumps((awake, sent))).decode()
            inbox = {}
            anyone = False
            for text in barrier.allGather(packed):
                others, arrived = pickle.loads(base64.b64decode(text))
                anyone |= others or bool(arrived)
                for dst, ms in arrived.items():
                    if dst in states:
                        inbox.setdefault(dst, []).extend(ms)
            if not anyone:
                break
        yield pd.DataFrame({"id": list(states), "state": [s for s, _ in states.values()]}, dtype=object)

    began = time.time()
    report = RunReport(converged=True)
    result = materialize(dealt.select("id", "dst", "w", "to").mapInPandas(run, f"id {kind}, state {program.state_type}", barrier=True), "result").df
    report.phases["analysis"] = time.time() - began
    return result, report


def _run_vectors(united: DataFrame, program: VertexProgram, parts: int, limit: int) -> tuple[DataFrame, RunReport]:
    """A program's vector form in one barrier stage: a worker holds its vertices and their edges as arrays.

    Workers agree once on who owns the targets of each; in a superstep a worker sends each other one combined value for
    each target that the other owns, directly (see ``Peers``).
    """
    began = time.time()
    table = materialize(united, "resident").df.repartition(parts, "id")
    seconds = {"load": time.time() - began}

    def run(batches):
        tables = [pa.Table.from_batches([b]) for b in batches]
        rows = pa.concat_tables(tables) if tables else pa.table({"id": pa.array([], pa.int64()), "dst": pa.array([], pa.int64()), "w": pa.array([], pa.float64())})
        is_edge = rows["dst"].is_valid().to_numpy(zero_copy_only=False) if len(rows) else np.zeros(0, dtype=bool)
        own = rows["id"].to_numpy()
        ids = np.unique(own[~is_edge])
        src, dst, w = own[is_edge], rows["dst"].to_numpy()[is_edge].astype(np.int64), rows["w"].to_numpy()[is_edge]
        known = np.isin(src, ids)
        src, dst, w = np.searchsorted(ids, src[known]), dst[known], w[known]
        targets, at = np.unique(dst, return_inverse=True)
        degree = np.bincount(src, minlength=len(ids))
        with Peers() as peers:
            places, owned = [], []
            for t in peers.exchange([targets] * peers.count):
                place = np.minimum(np.searchsorted(ids, t), max(len(ids) - 1, 0))
                mine = np.flatnonzero(ids[place] == t) if len(ids) else np.zeros(0, dtype=np.int64)
                places.append(place[mine])
                owned.append(mine)
            wanted = peers.exchange(owned)  # of my targets, those that each peer owns
            state, received = program.vector_init(ids), np.full(len(ids), program.identity)
            for superstep in range(limit):
                state, value, sends = program.vector_step(superstep, ids, state, received, degree)
                active = sends[src]
                message = program.vector_message(value[src[active]], w[active])
                if program.identity == 0.0:
                    combined = np.bincount(at[active], weights=message, minlength=len(targets)).astype(np.float64)
                else:
                    combined = np.full(len(targets), program.identity)
                    np.minimum.at(combined, at[active], message)
                awake = np.array([float(active.any())])
                arrived = peers.exchange([np.concatenate([awake, combined[k]]) for k in wanted])
                if not any(x[0] for x in arrived):
                    break
                received = np.full(len(ids), program.identity)
                for place, x in zip(places, arrived):
                    received[place] = received[place] + x[1:] if program.identity == 0.0 else np.minimum(received[place], x[1:])
        final = pa.array(state, pa.float64(), mask=~np.isfinite(state))
        yield pa.RecordBatch.from_arrays([pa.array(ids), final], ["id", "state"])

    began = time.time()
    report = RunReport(converged=True, phases=seconds)
    result = materialize(table.select("id", "dst", "w").mapInArrow(run, "id long, state double", barrier=True), "result").df
    report.phases["analysis"] = time.time() - began
    return result, report


def _run_rounds(vertices: DataFrame, edges: Scratch, program: VertexProgram, limit: int) -> tuple[DataFrame, RunReport]:
    """A program's vector form on a graph that no barrier stage may hold: every superstep is a job over edges that are kept by source.

    States pass through the program as arrays, messages are made and combined by Spark, and a lost task runs again.
    """
    report, began = RunReport(), time.time()
    dealt = DealtEdges(edges.df)
    edges.drop()
    degree = dealt.df.groupBy(F.col("src").alias("id")).agg(F.count(F.lit(1)).alias("degree"))

    def first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            state = np.asarray(program.vector_init(batch["id"].to_numpy()), dtype=np.float64)
            yield pa.RecordBatch.from_arrays([batch["id"], batch["degree"], pa.array(state)], ["id", "degree", "state"])

    at = vertices.select("id").distinct().join(degree, "id", "left").select("id", F.coalesce("degree", F.lit(0)).alias("degree"))
    held = materialize(at.mapInArrow(first, "id long, degree long, state double"), "resident")
    combine = F.sum if program.identity == 0.0 else F.min
    report.phases["load"] = time.time() - began
    began, received = time.time(), None
    for superstep in range(limit):
        t = time.time()

        def step(batches: Iterator[pa.RecordBatch], superstep=superstep) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                ids, state, got, degrees = (batch[c].to_numpy() for c in ("id", "state", "received", "degree"))
                state, value, sends = program.vector_step(superstep, ids, state, got, degrees)
                yield pa.RecordBatch.from_arrays([batch["id"], batch["degree"], pa.array(state), pa.array(value), pa.array(sends)], ["id", "degree", "state", "value", "sends"])

        states = held.df.select("id", "degree", "state")
        states = states.withColumn("received", F.lit(program.identity)) if received is None else states.join(received, "id", "left").withColumn("received", F.coalesce("received", F.lit(program.identity)))
        stepped, seen = states.mapInArrow(step, "id long, degree long, state double, value double, sends boolean"), Observation()
        after = materialize(stepped.observe(seen, F.count_if(F.col("sends") & (F.col("degree") > 0)).alias("n")), "resident")
        held.drop()
        held = after
        report.rounds.append({"round": superstep, "seconds": time.time() - t, "updates": seen.get["n"], "applied": "write"})
        if not seen.get["n"]:
            report.converged = True
            break
        senders = held.df.where("sends").select(F.col("id").alias("src"), "value")
        messages = dealt.meet(senders).select(F.col("dst").alias("id"), program.vector_message(F.col("value"), F.col("w")).alias("message"))
        received = messages.groupBy("id").agg(combine("message").alias("received"))
    dealt.unpersist()
    report.phases["analysis"] = time.time() - began
    finite = F.abs("state") < F.lit(float("inf"))
    return held.df.select("id", F.when(finite, F.col("state")).alias("state")), report


def register_udtfs(spark) -> None:
    """``vertex_step(TABLE(...) PARTITION BY part ORDER BY (id, kind))``: one shortest-path superstep as a table function in SQL."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="kind string, id long, value double")
    class VertexStep:
        def __init__(self):
            self.vertex, self.value, self.best, self.edges = None, None, None, []

        def _flush(self):
            if self.vertex is None:
                return
            improved = self.best is not None and (self.value is None or self.best < self.value)
            value = self.best if improved else self.value
            yield "v", self.vertex, value
            if improved:
                for dst in self.edges:
                    yield "m", dst, value + 1.0

        def eval(self, row):
            if row["id"] != self.vertex:
                yield from self._flush()
                self.vertex, self.value, self.best, self.edges = row["id"], None, None, []
            if row["kind"] == 0:
                self.value = row["value"]
            elif row["kind"] == 1:
                self.edges.append(row["dst"])
            elif self.best is None or row["value"] < self.best:
                self.best = row["value"]

        def terminate(self):
            yield from self._flush()

    spark.udtf.register("vertex_step", VertexStep)
