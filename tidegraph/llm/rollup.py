"""Token counts as delta-maintained rollups: signed batches add up to totals by source, language and tokenizer version."""

from __future__ import annotations

import base64
import importlib.util
import os
import re
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

from tidegraph.runtime import scratch_root, ship

#: Folder of the vocabulary files; executors find it under the same path.
VOCABULARIES = "/opt/tokenizers"
#: Tokenizer versions counted unless others are named: a vocabulary file, or ``words`` for runs between white space.
TOKENIZERS = ("words", "byte_bpe_50k.tiktoken")
KEYS = ["source", "lang", "tokenizer"]
MEASURES = ["n_docs", "n_chars", "n_tokens"]
SCHEMA = "source string, lang string, tokenizer string, n_docs long, n_chars long, n_tokens long"

_counters: dict[tuple[str, str], object] = {}


def counter(name: str, folder: str = VOCABULARIES):
    """A function from a list of texts to their token counts; loaded once in each worker."""
    if (folder, name) in _counters:
        return _counters[folder, name]
    path = os.path.join(folder, name)
    if name == "words":
        count = lambda texts: [len(x.encode().split()) for x in texts]
    elif name.endswith(".tiktoken"):
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}
        spec = importlib.util.spec_from_file_location("vocabulary_folder", os.path.join(folder, "__init__.py"))
        module = importlib.util.module_from_spec(spec)
        spec.loader.exec_module(module)
        encoding = tiktoken.Encoding(name, pat_str=module.PATTERN, mergeable_ranks=ranks, special_tokens={})
        count = lambda texts: [len(encoding.encode_ordinary(x)) for x in texts]
    elif name.endswith(".model"):
        import sentencepiece

        pieces = sentencepiece.SentencePieceProcessor(model_file=path)
        count = lambda texts: [len(pieces.encode(x, num_threads=1)) for x in texts]
    else:
        from tokenizers import Tokenizer

        tokenizer = Tokenizer.from_file(path)
        tokenizer.encode_special_tokens = True
        count = lambda texts: [len(tokenizer.encode(x, add_special_tokens=False).ids) for x in texts]
    _counters[folder, name] = count
    return count


def deltas(changes: DataFrame, tokenizers: tuple[str, ...] = TOKENIZERS, folder: str = VOCABULARIES) -> DataFrame:
    """Signed totals of a batch of changes ``(source, lang, text, sign)``: sign 1 inserts, -1 deletes; a revision is both.

    Null text counts as empty, a null sign as 1; null sources and languages are groups of their own. Texts are counted
    whole, and sums are made in each task before they are shuffled.
    """
    ship(changes.sparkSession)
    names = list(tokenizers)

    def run(batches):
        sums: dict[tuple, list[int]] = {}
        for batch in batches:
            sources, langs, texts, signs = (batch.column(i).to_pylist() for i in range(4))
            texts = [x or "" for x in texts]
            counts = [counter(n, folder)(texts) for n in names]
            for i, (source, lang, text, sign) in enumerate(zip(sources, langs, texts, signs)):
                sign = 1 if sign is None else sign
                for name, c in zip(names, counts):
                    row = sums.setdefault((source, lang, name), [0, 0, 0])
                    row[0] += sign
                    row[1] += sign * len(text)
                    row[2] += sign * c[i]
        keys, values = list(sums), list(sums.values())
        columns = [pa.array([k[i] for k in keys], pa.string()) for i in range(3)] + [pa.array([v[i] for v in values], pa.int64()) for i in range(3)]
        yield pa.RecordBatch.from_arrays(columns, KEYS + MEASURES)

    counted = changes.select("source", "lang", "text", F.col("sign").cast("int").alias("sign")).mapInArrow(run, SCHEMA)
    return _sum(counted)


def _sum(rows: DataFrame) -> DataFrame:
    return rows.groupBy(*KEYS).agg(*[F.sum(m).alias(m) for m in MEASURES])


def revisions(old: DataFrame, new: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """The signed changes that turn ``old`` documents into ``new`` ones; documents that did not change make none."""
    columns = [id_col, "source", "lang", "text"]
    signed = old.select(*columns).withColumn("sign", F.lit(-1)).unionByName(new.select(*columns).withColumn("sign", F.lit(1)))
    kept = signed.groupBy(*columns).agg(F.sum("sign").cast("int").alias("sign")).where("sign <> 0")
    return kept.withColumn("sign", F.explode(F.expr("array_repeat(signum(sign), abs(sign))"))).select("source", "lang", "text", F.col("sign").cast("int"))


class RollupStore:
    """Totals as the sum of committed batches in a folder that all executors share.

    A batch is written aside and gets its name in one step once it is complete. Committing it again does nothing, so a job
    that is retried after a failure adds nothing twice, and of two writers of one batch the second has no effect. ``compact`` folds committed batches into a snapshot.
    """

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark = spark
        self.path = path or f"{scratch_root(spark)}/rollups/{uuid.uuid4().hex}"
        self._fs_path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
        self._fs = self._fs_path(self.path).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _exists(self, path: str) -> bool:
        return self._fs.exists(self._fs_path(path))

    def _names(self, folder: str) -> list[str]:
        if not self._exists(f"{self.path}/{folder}"):
            return []
        found = [s.getPath().getName() for s in self._fs.listStatus(self._fs_path(f"{self.path}/{folder}"))]
        return sorted(x for x in found if self._exists(f"{self.path}/{folder}/{x}/_SUCCESS"))

    def _folder(self, batch: str) -> str:
        if not re.fullmatch(r"[A-Za-z0-9_-]+", batch):
            raise ValueError(f"batch names are letters, digits, - and _: {batch!r}")
        return f"{self.path}/batches/{batch}"

    def committed(self) -> set[str]:
        return set(self._names("batches")) | self._folded()[1]

    def _folded(self) -> tuple[str | None, set[str]]:
        """The latest snapshot and the batches in it."""
        snapshots = self._names("snapshots")
        if not snapshots:
            return None, set()
        rows = self.spark.read.parquet(f"{self.path}/snapshots/{snapshots[-1]}").where("batches is not null").select("batches").take(1)
        return snapshots[-1], set(rows[0][0])

    def commit(self, batch: str, changes: DataFrame, tokenizers: tuple[str, ...] = TOKENIZERS, folder: str = VOCABULARIES) -> bool:
        """Count and add a batch; False, and no work, if it was committed before."""
        target = self._folder(batch)
        if batch in self.committed():
            return False
        pending = f"{self.path}/pending/{batch}-{uuid.uuid4().hex}"
        deltas(changes, tokenizers, folder).write.parquet(pending)
        return self._publish(pending, target)

    def _publish(self, pending: str, target: str) -> bool:
        """Move a complete folder to its name in one step; False, and the folder goes, if another writer was first."""
        context = self.spark.sparkContext
        hadoop = context._jvm.org.apache.hadoop.fs
        files = hadoop.FileContext.getFileContext(self._fs.getUri(), context._jsc.hadoopConfiguration())
        files.mkdir(self._fs_path(target).getParent(), hadoop.permission.FsPermission.getDirDefault(), True)
        try:
            files.rename(self._fs_path(pending), self._fs_path(target), context._gateway.new_array(hadoop.Options.Rename, 0))
            return True
        except Exception:
            self._fs.delete(self._fs_path(pending), True)
            if self._exists(f"{target}/_SUCCESS"):
                return False
            raise

    def totals(self) -> DataFrame:
        """``source, lang, tokenizer, n_docs, n_chars, n_tokens``; groups that came to no documents are left out."""
        snapshot, folded = self._folded()
        parts = [self.spark.read.schema(SCHEMA).parquet(self._folder(b)) for b in self._names("batches") if b not in folded]
        if snapshot:
            parts.append(self.spark.read.parquet(f"{self.path}/snapshots/{snapshot}").where("batches is null").drop("batches"))
        if not parts:
            return self.spark.createDataFrame([], SCHEMA)
        out = parts[0]
        for x in parts[1:]:
            out = out.unionByName(x)
        return _sum(out).where("n_docs <> 0 or n_chars <> 0 or n_tokens <> 0")

    def compact(self) -> None:
        """A snapshot of all committed batches; their folders go once it is complete."""
        snapshot, folded = self._folded()
        loose = self._names("batches")
        names = sorted(folded | set(loose))
        if not set(loose) - folded:
            return
        mark = self.spark.createDataFrame([(names,)], "batches array<string>")
        number = int(snapshot[1:]) + 1 if snapshot else 0
        rows = self.totals().withColumn("batches", F.lit(None).cast("array<string>")).unionByName(mark, allowMissingColumns=True)
        rows.write.parquet(f"{self.path}/snapshots/s{number:08d}")
        for b in loose:
            self._fs.delete(self._fs_path(self._folder(b)), True)
