"""Written tables in the folder that all executors share."""

from __future__ import annotations

import contextlib
import tempfile
import threading
import uuid
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """spark.checkpoint.dir where the session names it; a temporary folder only where it does not, as in tests."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        root = f"file://{tempfile.mkdtemp(prefix='checkpoints-')}"
        spark.sparkContext.setCheckpointDir(root)
    return root.rstrip("/")


def folder(spark: SparkSession, what: str) -> str:
    return f"{shared_root(spark)}/sparsetri/{what}-{uuid.uuid4().hex}"


def gone_at_end(spark: SparkSession, uri: str) -> None:
    """The folder, which must exist, is deleted when the driver's JVM ends, by Hadoop and so in any store that Spark can write to."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(uri)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(path)


@contextlib.contextmanager
def swept(spark: SparkSession) -> Iterator[None]:
    """What is written inside, also by several threads at once, leaves no shuffle files behind once it is written."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    with _LOCK:
        if not _INSIDE:
            _BEFORE[key] = spark.conf.get(key)
            spark.conf.set(key, "true")
        _INSIDE.append(key)
    try:
        yield
    finally:
        with _LOCK:
            _INSIDE.pop()
            if not _INSIDE:
                spark.conf.set(key, _BEFORE[key])


_LOCK, _INSIDE, _BEFORE = threading.Lock(), [], {}


def stored(df: DataFrame, what: str, level: int = 3, page: int = 1 << 20) -> DataFrame:
    """Lineage ends in Parquet files: later passes scan them, and a lost executor costs a re-read of files, not a re-run of what made them.
    level: zstd's, 3 where time counts more than disk.  page: bytes that are compressed together, Parquet's own by default."""
    spark = df.sparkSession
    uri = folder(spark, what)
    with swept(spark):
        df.write.option("compression", "zstd").option("parquet.compression.codec.zstd.level", level).option("parquet.page.size", page).parquet(uri)
    gone_at_end(spark, uri)
    return spark.read.schema(df.schema).parquet(uri)


def written(df: DataFrame, what: str) -> DataFrame:
    """df where it is no more than the scan of files, else stored: its files hold its rows and no others."""
    return df if df._jdf.queryExecution().optimizedPlan().nodeName() == "LogicalRelation" else stored(df, what)
