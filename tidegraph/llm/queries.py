"""The subpackage's registered queries: one for each operation, over its whole table, and the corpus pipeline."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from tidegraph.llm import decontam, htmltext, licenses, mixing, phrases, quality, rollup, simhash, sql, telephony, toxicity


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's toxicity, and its significant passages as JSON. Null and empty texts score as texts without evidence; rows with a null id stay."""
    docs = _table(spark, sf_dir, "documents")
    scored = toxicity.score(docs, toxicity.fit(docs, _table(spark, sf_dir, "labels")))
    return scored.select("doc_id", "held_out", "score", "predicted", "n_words", "n_segments", F.to_json("passages").alias("passages"))


def op2_repeated_phrases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document with an id, and what is left of it without passages of 50 words that start in an earlier one. Null and empty texts have no words."""
    return phrases.remove_repeats(_table(spark, sf_dir, "documents"))


def op3_token_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents as one inserted batch, committed twice, which changes nothing; then the texts with white space at their
    ends are revised to what is between, and documents of which nothing is left are deleted."""
    store = rollup.RollupStore(spark)
    docs = _table(spark, sf_dir, "documents").select("source", "lang", F.coalesce("text", F.lit("")).alias("text"))
    for _ in range(2):
        store.commit("initial", docs.withColumn("sign", F.lit(1)))
    bare = F.regexp_replace("text", r"^\s+|\s+$", "")
    changed = docs.withColumn("bare", bare).where("text <> bare or bare = ''")
    signed = F.array(F.struct("text", F.lit(-1).alias("sign")), F.when(F.col("bare") != "", F.struct(F.col("bare").alias("text"), F.lit(1).alias("sign"))))
    store.commit("trimmed", changed.select("source", "lang", F.explode(F.filter(signed, lambda x: x.isNotNull())).alias("c")).select("source", "lang", "c.*"))
    return store.totals()


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of documents and benchmark items that they hold. Null and empty texts match nothing; rows with a null id are left out."""
    return decontam.matches(_table(spark, sf_dir, "documents"), _table(spark, sf_dir, "benchmark"))


def op5_telephony(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's bytes as mu-law samples, read back and described. A null text is an empty one; rows with a null id stay."""
    return telephony.store_texts(_table(spark, sf_dir, "documents"))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's place in the mix. A null source is the source named by the empty text; rows with a null id stay."""
    mixed = mixing.scheduled(_table(spark, sf_dir, "documents").select("doc_id", "source"))
    return mixed.select("doc_id", "source", "block", "slot", "row_in_block")


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and component of every document with an id. Texts without words have fingerprint zero."""
    return simhash.near_components(_table(spark, sf_dir, "documents"))


def op8_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Main text of every page; null html gives an empty one, repeated rows a row each."""
    return htmltext.extract_pages(_table(spark, sf_dir, "pages"))


def op9_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    """License mentions and notices of every document with an id. Null and empty texts have none."""
    return licenses.scan(_table(spark, sf_dir, "documents"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every document's quality. Null and empty texts score by statistics of zero; rows with a null id stay."""
    docs = _table(spark, sf_dir, "documents")
    return quality.score(docs, quality.fit(docs, _table(spark, sf_dir, "labels")))


QUERIES = {f.__name__: f for f in (op1_toxicity, op2_repeated_phrases, op3_token_rollup, op4_decontamination, op5_telephony, op6_mixing, op7_simhash, op8_html_text, op9_licenses, op10_quality)}

ORACLES: dict[str, str] = {
    "op2_repeated_phrases": sql.repeated_phrases(),
    "op4_decontamination": sql.decontamination(),
    "op9_licenses": sql.license_scan(),
}
