"""Session, scratch tables and code shipping: what every operator needs from the running Spark application."""

from __future__ import annotations

import io
import os
import tempfile
import uuid
import zipfile
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from tidegraph.plans.physical import settings

_BATCH = "spark.sql.execution.arrow.maxRecordsPerBatch"


def session(app: str = "tidegraph", cores: str | int = "*", shuffle_partitions: int = 8, **conf) -> SparkSession:
    """A local session for tests and the bench; on a cluster pass the session that is already there to the operators."""
    builder = (
        SparkSession.builder.appName(app)
        .master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", shuffle_partitions)
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
    )
    for key, value in conf.items():
        builder = builder.config(key.replace("__", "."), value)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def scratch_root(spark: SparkSession) -> str:
    """The shared folder for intermediate tables: the application's checkpoint folder, or a temporary one where none is set."""
    context = spark.sparkContext
    root = context.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        context.setCheckpointDir(f"file://{tempfile.mkdtemp(prefix='tidegraph-')}")
        root = context.getCheckpointDir()
    return root


@dataclass
class Scratch:
    """A written intermediate table. It survives lost executors and cuts lineage; ``drop`` frees its disk."""

    spark: SparkSession
    path: str
    df: DataFrame

    def drop(self) -> None:
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def materialize(df: DataFrame, label: str = "t", codec: str | None = None, free: bool = False) -> Scratch:
    """Write ``df`` to the scratch folder, with ``codec`` or the session's, and read it back under the same schema.

    ``free``: the shuffle files of the write go as soon as it ends, not when the driver's memory is next collected.
    """
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/tables/{label}-{uuid.uuid4().hex}"
    with settings(spark, **({"spark__sql__classic__shuffleDependency__fileCleanup__enabled": "true"} if free else {})):
        df.write.parquet(path, compression=codec)
    return Scratch(spark, path, spark.read.schema(df.schema).parquet(path))


#: Rows that a Python worker gets at once unless the session says otherwise; bounds its memory with long texts.
BATCH_ROWS = 2_000


def ship(spark: SparkSession) -> None:
    """Send this package to the Python workers once per application, so that their functions import it anywhere.

    Also bounds the rows of an Arrow batch where the session has left Spark's default.
    """
    context = spark.sparkContext
    if spark.conf.get(_BATCH) == "10000":
        spark.conf.set(_BATCH, str(BATCH_ROWS))
    if getattr(context, "_tidegraph_shipped", False):
        return
    package = os.path.dirname(os.path.abspath(__file__))
    packed = io.BytesIO()
    with zipfile.ZipFile(packed, "w") as archive:
        for top, _, names in os.walk(package):
            for name in names:
                if name.endswith(".py"):
                    full = os.path.join(top, name)
                    archive.write(full, os.path.relpath(full, os.path.dirname(package)))
    target = f"{scratch_root(spark)}/code/tidegraph_{uuid.uuid4().hex}.zip"
    path = context._jvm.org.apache.hadoop.fs.Path(target)
    stream = path.getFileSystem(context._jsc.hadoopConfiguration()).create(path)
    stream.write(packed.getvalue())
    stream.close()
    context.addPyFile(target)
    context._tidegraph_shipped = True
