"""The edge relation: u < v, distinct, no loops; and readers and writers of it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def canonical(df: DataFrame, a: Column | str, b: Column | str, distinct: bool = True) -> DataFrame:
    """Edges of two columns: loops and nulls go, the smaller id comes first."""
    a, b = (F.col(c) if isinstance(c, str) else c for c in (a, b))
    out = df.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.least(a, b).cast("long").alias("u"), F.greatest(a, b).cast("long").alias("v"))
    return out.distinct() if distinct else out


def assert_simple(edges: DataFrame) -> DataFrame:
    """Raises on loops, wrong order or repeats: the methods assume a simple graph."""
    bad = edges.groupBy("u", "v").count().where("u >= v or count > 1").limit(1).count()
    if bad:
        raise ValueError("not a simple edge relation: loops, reversed or repeated edges")
    return edges


def half_edges(edges: DataFrame) -> DataFrame:
    """(x, nbr): both directions from one scan."""
    ends = F.array(F.struct(F.col("u").alias("x"), F.col("v").alias("nbr")), F.struct(F.col("v").alias("x"), F.col("u").alias("nbr")))
    return edges.select(F.inline(ends))


def encode_vertices(df: DataFrame, a: str, b: str) -> DataFrame:
    """Edges of ids of any type by a 64-bit hash of the id; two ids meet with odds n^2 / 2^65."""
    return canonical(df, F.xxhash64(a), F.xxhash64(b))


def read_edge_text(spark: SparkSession, path: str, separator: str = "\t") -> DataFrame:
    """One edge a line; lines that start with # are comments."""
    parts = F.split("value", separator)
    lines = spark.read.text(path).where(~F.col("value").startswith("#") & (F.length(F.trim("value")) > 0))
    return canonical(lines.select(F.get(parts, F.lit(0)).cast("long").alias("a"), F.get(parts, F.lit(1)).cast("long").alias("b")), "a", "b")


def read_edge_rows(spark: SparkSession, path: str, kind: str) -> DataFrame:
    """Two ids a row in CSV (no head) or JSON (fields a, b)."""
    return canonical(spark.read.schema("a long, b long").format(kind).load(path), "a", "b")


def write_edges(edges: DataFrame, path: str, partitions: int | None = None) -> None:
    """Sorted by u inside range partitions, so that row groups can be skipped by their least and largest u."""
    ordered = edges.repartitionByRange(partitions, "u") if partitions else edges.repartitionByRange("u")
    ordered.sortWithinPartitions("u", "v").write.parquet(path)


def write_bucketed(edges: DataFrame, name: str, buckets: int) -> None:
    """A table bucketed by u: joins on u then need no shuffle of it."""
    edges.write.bucketBy(buckets, "u").sortBy("u").saveAsTable(name)


class _Lines(DataSourceReader):
    """Byte ranges of the text files of a folder (or of one file) that all executors see; a line belongs to the range in which it begins."""

    def __init__(self, options):
        self.path, self.size = options["path"], int(options.get("splitbytes", 1 << 26))

    def partitions(self):
        import pyarrow.fs as pafs

        fs, path = pafs.FileSystem.from_uri(self.path)
        one = fs.get_file_info(path)
        files = [one] if one.is_file else [f for f in fs.get_file_info(pafs.FileSelector(path)) if f.is_file and not f.base_name.startswith(("_", "."))]
        return [InputPartition((f.path, k, k + self.size)) for f in files for k in range(0, f.size, self.size)] or [InputPartition(("", 0, 0))]

    def read(self, partition):
        import pyarrow.fs as pafs

        name, low, high = partition.value
        if not high:
            return
        fs, _ = pafs.FileSystem.from_uri(self.path)
        with fs.open_input_file(name) as f:
            start, size = max(0, low - 1), f.size()
            raw, at = f.read_at(high - start, start), high
            while not raw.endswith(b"\n") and at < size:  # the last line goes on beyond the range
                more = f.read_at(1 << 12, at)
                cut = more.find(b"\n") + 1
                raw, at = raw + (more[:cut] if cut else more), at + len(more)
        for line in (raw.partition(b"\n")[2] if low else raw).split(b"\n"):
            if line.strip() and not line.startswith(b"#"):
                a, b = line.split()[:2]
                yield int(a), int(b)


class EdgeListSource(DataSource):
    """format("edge_list"): text edge lists as a table of two ids."""

    @classmethod
    def name(cls):
        return "edge_list"

    def schema(self):
        return "a long, b long"

    def reader(self, schema):
        return _Lines(self.options)
