"""Shared ground of the operators: tables, files in the folder that all executors see, and row buffers.  Written tables are the engine's."""

from __future__ import annotations

import contextlib
import ctypes
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.store import folder, gone_at_end, stored


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One input table, read by Spark itself, so that any store that Spark can reach will do."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def new_folder(spark: SparkSession, what: str) -> str:
    """A fresh folder under the shared root; it goes when the driver ends."""
    uri = folder(spark, what)
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(uri)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).mkdirs(path)
    gone_at_end(spark, uri)
    return uri


def ease_driver(spark: SparkSession) -> None:
    """For operators that write many tables in a row: broadcasts of finished writes stay in the driver's memory until its JVM collects its
    garbage, and it rather takes a larger heap.  So once the heap has over half of its maximum, it is collected here."""
    runtime = spark.sparkContext._jvm.java.lang.Runtime.getRuntime()
    if runtime.totalMemory() > runtime.maxMemory() // 2:
        runtime.gc()


def parts_for(df: DataFrame, total: str, bytes_each: int) -> int:
    """How many tasks a table's work asks for: its summed `total` (bytes, of a short written table) over bytes_each, but no fewer than cores
    while there are rows for them.  A stated number is not merged by adaptive execution, which sees only the short rows."""
    n, whole = df.agg(F.count(F.lit(1)), F.coalesce(F.sum(total), F.lit(0))).first()
    return max(1, min(n, max(df.sparkSession.sparkContext.defaultParallelism, -(-int(whole) // bytes_each))))


def filesystem(uri: str) -> tuple[pafs.FileSystem, str]:
    """Arrow's view of a folder or file.  It knows file, hdfs, viewfs, s3, gs and abfs addresses; Hadoop's s3a and s3n are its s3, gcs its gs."""
    scheme, mark, rest = uri.partition("://")
    return pafs.FileSystem.from_uri({"s3a": "s3", "s3n": "s3", "gcs": "gs"}.get(scheme, scheme) + mark + rest)


def write_atomically(folder: str, name: str, chunks: Iterator[bytes]) -> str:
    """Writes a file under a scratch name and moves it into place, so that no reader meets half a file.
    Returns its URI.  Names must be unique per task attempt: a re-run then never touches files already listed."""
    fs, path = filesystem(folder)
    fs.create_dir(path, recursive=True)
    with fs.open_output_stream(f"{path}/_{name}.part") as out:
        for chunk in chunks:
            out.write(chunk)
    fs.move(f"{path}/_{name}.part", f"{path}/{name}")
    return f"{folder}/{name}"


def attempt_name(prefix: str, partition: int) -> str:
    return f"{prefix}-{partition:06d}-{uuid.uuid4().hex[:12]}"


def arrow_rows(schema: pa.Schema, flush_rows: int = 2048, flush_bytes: int = 8 << 20) -> tuple[Callable, Callable]:
    """A bounded row buffer for mapInArrow functions: add(row, bytes) gives a batch when full, rest() the remainder."""
    rows: list[tuple] = []
    held = 0

    def make() -> pa.RecordBatch:
        nonlocal held
        columns = list(zip(*rows, strict=True)) if rows else [[] for _ in schema]
        batch = pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip(columns, schema, strict=True)], schema=schema)
        rows.clear()
        held = 0
        return batch

    def add(row: tuple, size: int = 64) -> pa.RecordBatch | None:
        nonlocal held
        rows.append(row)
        held += size
        return make() if len(rows) >= flush_rows or held >= flush_bytes else None

    def rest() -> list[pa.RecordBatch]:
        return [make()] if rows else []

    return add, rest


_caches: dict[str, Callable[[], None]] = {}


def claim_cache(owner: str, clear: Callable[[], None]) -> None:
    """Called by a task that is going to fill a worker-wide memo: memos of other operators in this worker go first, as workers
    live on from stage to stage.  What they leave free goes back to the system, where its allocator can do that."""
    for name, drop in _caches.items():
        if name != owner:
            drop()
    _caches[owner] = clear
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)
