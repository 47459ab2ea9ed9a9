"""Triangles of an edge set whose wedges are too many to be moved.

Edges are laid out once as lists of later neighbours, in buckets by a hash of their first vertex.  A task holds whole lists and goes through the buckets one
after the other: the pairs of its lists whose first vertex lies in the bucket are looked up in it.  Wedges exist in one task's memory only; what crosses the
network is each edge once, packed.  Buckets are read from the shared folder, once for each HELD edges that tasks hold.

The order: vertices of more than twice the mean degree come last, by degree; the others by id.  A list is then no longer than four times the degeneracy
or, of the few large ones, the square root of 2m, so there are at most 2 * m * degeneracy wedges of the first kind.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.packed import PACKS, gathered, moved, opened, packs, place
from ..plans.store import folder, gone_at_end, stored, swept
from .passes import BROADCAST_KEYS
from .whole import VERTICES, Vertices

#: Edges in a bucket, edges that a task holds, wedges that are looked up together.
BUCKET, HELD, TOGETHER = 1_000_000, 4_000_000, 2_000_000
LISTS = "b int, p long, q array<long>"
_P = [np.uint64(x) for x in (0, 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5)]


def readable(uri: str) -> bool:
    """Whether tasks can read files of this folder by themselves."""
    try:
        pafs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}")
        return True
    except Exception:  # no driver for that store here
        return False


def xxhash64(x: np.ndarray) -> np.ndarray:
    """Spark's xxhash64 of one long."""
    turn = lambda h, r: (h << np.uint64(r)) | (h >> np.uint64(64 - r))
    with np.errstate(over="ignore"):
        h = np.uint64(42) + _P[5] + np.uint64(8)
        h = h ^ (turn(x.astype(np.int64).view(np.uint64) * _P[2], 31) * _P[1])
        h = turn(h, 27) * _P[1] + _P[4]
        h = (h ^ (h >> np.uint64(33))) * _P[2]
        h = (h ^ (h >> np.uint64(29))) * _P[3]
        return (h ^ (h >> np.uint64(32))).view(np.int64)


def _lists(b: int, columns: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
    """p, h, q of a bucket -> its lists, each by (h, q)."""
    p, h, q = columns
    order = np.lexsort((q, h, p))
    p, q = p[order], q[order]
    first = np.flatnonzero(np.r_[True, p[1:] != p[:-1]])
    for k in range(0, len(first), 50_000):
        own = first[k : k + 50_000]
        end = first[k + 50_000] if k + 50_000 < len(first) else len(p)
        values = pa.ListArray.from_arrays(pa.array(np.r_[own, end] - own[0], pa.int32()), pa.array(q[own[0] : end]))
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(own), b), pa.int32()), pa.array(p[own]), values], names=["b", "p", "q"])


def _ends(n: int):
    """u, v -> packs of (end, its edges here)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for u, v in gathered(batches):
            x, many = np.unique(np.concatenate([u, v]), return_counts=True)
            yield from packs(place(x, n), [x, many])

    return run


def _added(_, columns: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
    x, at = np.unique(columns[0], return_inverse=True)
    d = np.zeros(len(x), np.int64)
    np.add.at(d, at, columns[1])
    for k in range(0, len(x), 100_000):
        yield pa.RecordBatch.from_arrays([pa.array(x[k : k + 100_000]), pa.array(d[k : k + 100_000])], names=["x", "d"])


def degrees(edges: DataFrame, m: int, bucket: int = BUCKET) -> DataFrame:
    """x, d: ends are counted where they are, and counts cross the network in packs."""
    n = max(1, -(-m // bucket))
    return opened(edges.select("u", "v").mapInArrow(_ends(n), PACKS), n, _added, "x long, d long")


def _directed(degree_files: list[str], n: int, m: int):
    """Edges u, v -> packs of (p, h, q) by bucket of p, the end that comes first; h: the degree of q where it is large."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vertices = None
        for u, v in gathered(batches):
            if vertices is None:
                vertices = Vertices.read(degree_files)
                large = np.where(vertices.d * len(vertices.d) > 4 * m, vertices.d, 0)
            du, dv = large[vertices.number(u)], large[vertices.number(v)]
            up = (du < dv) | ((du == dv) & (u < v))
            p = np.where(up, u, v)
            yield from packs((xxhash64(p) % n).astype(np.int32), [p, np.where(up, dv, du), np.where(up, v, u)])

    return run


def write_lists(edges: DataFrame, m: int, bucket: int = BUCKET, degree: DataFrame | None = None) -> tuple[str, int]:
    """(folder, number of buckets): every edge once, in the list of the end that comes first; degree: a written table of all, where there is one."""
    spark = edges.sparkSession
    n = max(1, -(-m // bucket))
    d = stored(degrees(edges, m, bucket), "closing-degrees") if degree is None else degree
    out = folder(spark, "lists")
    if d.count() <= VERTICES:
        with swept(spark):
            opened(edges.select("u", "v").mapInArrow(_directed(d.inputFiles(), n, m), PACKS), n, _lists, LISTS).write.option("compression", "zstd").partitionBy("b").parquet(out)
        gone_at_end(spark, out)
        return out, n
    large = stored(d.where(F.col("d") * d.count() > 4 * m), "closing-large")
    large = F.broadcast(large) if large.count() <= BROADCAST_KEYS else large
    e = edges.join(large.select(F.col("x").alias("u"), F.col("d").alias("du")), "u", "left").join(large.select(F.col("x").alias("v"), F.col("d").alias("dv")), "v", "left")
    e = e.na.fill(0, ["du", "dv"])
    up = F.struct("du", "u") < F.struct("dv", "v")
    e = e.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("p"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("q"), F.when(up, F.col("dv")).otherwise(F.col("du")).alias("h"))
    e = e.select(F.pmod(F.xxhash64("p"), F.lit(n)).cast("int").alias("b"), "p", "h", "q")
    with swept(spark):
        moved(e, n, _lists, LISTS).write.option("compression", "zstd").partitionBy("b").parquet(out)
    gone_at_end(spark, out)
    return out, n


class _Bucket:
    """Edges of a bucket, to be looked up by (p, q)."""

    def __init__(self, fs: pafs.FileSystem, path: str):
        files = sorted(f.path for f in fs.get_file_info(pafs.FileSelector(path, allow_not_found=True)) if f.is_file and f.path.endswith(".parquet"))
        tables = []
        for f in files:
            with fs.open_input_file(f) as source:
                tables.append(pq.ParquetFile(source).read(columns=["p", "q"], use_threads=False))
        rows = pa.concat_tables(tables).combine_chunks() if tables else None
        self.p = rows["p"].to_numpy() if rows else np.empty(0, np.int64)
        self.keys = np.empty(0, np.int64)
        if not len(self.p):
            return
        lists = rows["q"].chunk(0)
        lengths, w = np.diff(lists.offsets.to_numpy()), lists.flatten().to_numpy()
        self.lists = lengths, self.p, w
        order = np.argsort(self.p, kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        self.p = self.p[order]
        self.low, self.names = int(w.min()), None
        if int(w.max()) - self.low >= 1 << 32:  # ids too far apart for half a key: they get numbers
            self.names = np.unique(w)
        self.laid = (np.repeat(place, lengths) << 32) | self._half(w)
        self.keys = np.sort(self.laid)
        self.bits = max(10, int(len(self.keys) * 12).bit_length())
        self.sieve = np.zeros(1 << self.bits, bool)
        self.sieve[self._hash(self.keys)] = True

    def _half(self, w: np.ndarray) -> np.ndarray:
        return w - self.low if self.names is None else np.searchsorted(self.names, w)

    def _hash(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.view(np.uint64) * _P[1]) >> np.uint64(64 - self.bits)).view(np.int64)

    def known(self, w: np.ndarray) -> np.ndarray:
        """Half keys of any ids, -1 where the bucket has no such end."""
        if self.names is None:
            half = w - self.low
            return np.where((w >= self.low) & (half >= 0) & (half < 1 << 32), half, -1)
        at = np.minimum(np.searchsorted(self.names, w), len(self.names) - 1)
        return np.where(self.names[at] == w, at, -1)

    def found(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions among keys of those that are edges, and the numbers of these edges in the order of keys."""
        hit = np.flatnonzero(self.sieve[self._hash(keys)])
        keys = keys[hit]
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        same = self.keys[at] == keys
        return hit[same], at[same]


def _closed(uri: str, n: int, starts: np.ndarray, p: np.ndarray, q: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, int, np.ndarray, int]]:
    """Lists q[starts[i]:starts[i+1]] of p[i]: positions (i, j) in q of the two later vertices of each triangle, i before j; and the bucket of the edge
    between them, its number there and the bucket's size."""
    fs, path = pafs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}")
    lengths = np.diff(starts)
    left = np.repeat(starts[1:], lengths) - np.arange(len(q)) - 1  # what follows in the same list
    bucket = xxhash64(q) % n
    order = np.argsort(bucket.astype(np.int32), kind="stable")
    order = order[left[order] > 0]
    ends = np.searchsorted(bucket[order], np.arange(n + 1))
    for b in range(n):
        first = order[ends[b] : ends[b + 1]]
        if not len(first):
            continue
        held = _Bucket(fs, f"{path}/b={b}")
        if not len(held.p):
            continue
        at = np.minimum(np.searchsorted(held.p, q[first]), len(held.p) - 1)
        own = held.p[at] == q[first]
        first, at = first[own], at[own]
        upto = np.cumsum(left[first])
        k = 0
        while k < len(first):
            done = upto[k - 1] if k else 0
            stop = max(k + 1, int(np.searchsorted(upto, done + TOGETHER, "right")))
            part, many = first[k:stop], left[first[k:stop]]
            i = np.repeat(part, many)
            j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(many) - many, many)
            half = held.known(q[j])
            keys = (np.repeat(at[k:stop], many) << 32) | half
            hit, number = held.found(keys)
            good = half[hit] >= 0
            hit, number = hit[good], number[good]
            if len(hit):
                yield i[hit], j[hit], b, number, len(held.keys)
            k = stop


def _groups(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(starts, p, q) of lists with HELD edges together, whatever the size of a batch."""
    parts, size = [], 0

    def joined():
        lengths = np.concatenate([x[0] for x in parts])
        return np.r_[0, np.cumsum(lengths)], np.concatenate([x[1] for x in parts]), np.concatenate([x[2] for x in parts])

    for batch in batches:
        lists = batch.column(1)
        q = lists.flatten().to_numpy(zero_copy_only=False)
        parts.append((np.diff(lists.offsets.to_numpy()), batch.column(0).to_numpy(zero_copy_only=False), q))
        size += len(q)
        if size >= HELD:
            yield joined()
            parts, size = [], 0
    if size:
        yield joined()


def _run(uri: str, n: int, count: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for starts, p, q in _groups(batches):
            owner, total = np.repeat(np.arange(len(p)), np.diff(starts)), 0
            for i, j, *_ in _closed(uri, n, starts, p, q):
                total += len(i)
                if not count:
                    t = np.sort(np.stack([p[owner[i]], q[i], q[j]]), axis=0)
                    for k in range(0, len(i), 100_000):
                        yield pa.RecordBatch.from_arrays([pa.array(x[k : k + 100_000]) for x in t], names=["a", "b", "c"])
            if count:
                yield pa.RecordBatch.from_arrays([pa.array([total], pa.int64())], names=["t"])

    return run


def triangles(edges: DataFrame, m: int, bucket: int = BUCKET) -> DataFrame:
    """a < b < c, each once."""
    uri, n = write_lists(edges, m, bucket)
    return edges.sparkSession.read.schema(LISTS).parquet(uri).select("p", "q").mapInArrow(_run(uri, n, False), "a long, b long, c long")


def count_triangles(edges: DataFrame, m: int, bucket: int = BUCKET, degree: DataFrame | None = None) -> DataFrame:
    """t in one row."""
    uri, n = write_lists(edges, m, bucket, degree)
    each = edges.sparkSession.read.schema(LISTS).parquet(uri).select("p", "q").mapInArrow(_run(uri, n, True), "t long")
    return each.agg(F.coalesce(F.sum("t"), F.lit(0)).alias("t"))


#: Counts of a bucket's edges: where they begin, and their increments by edge in the order of keys, packed.
PACKED = "b int, size long, packed binary"


def _pack(b: int, counts: np.ndarray) -> pa.RecordBatch:
    packed = pa.compress(counts.astype("<i4").tobytes(), codec="zstd", asbytes=True)
    return pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([len(counts)], pa.int64()), pa.array([packed], pa.binary())], names=["b", "size", "packed"])


def _counted(uri: str, n: int):
    """Ids of buckets -> triangles of their lists, added up by edge: a row for each bucket that they touch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, path = pafs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}")
        own = [(int(b), x) for batch in batches for b in batch.column(0).to_pylist() if len((x := _Bucket(fs, f"{path}/b={b}")).p)]
        if not own:
            return
        lengths = np.concatenate([x.lists[0] for _, x in own])
        starts, p, q = np.r_[0, np.cumsum(lengths)], np.concatenate([x.lists[1] for _, x in own]), np.concatenate([x.lists[2] for _, x in own])
        orders, sizes = [(b, np.argsort(x.laid, kind="stable")) for b, x in own], [len(x.keys) for _, x in own]
        del own
        mine, at, held = np.zeros(len(q), np.int64), -1, np.empty(0, np.int64)
        for i, j, b, number, size in _closed(uri, n, starts, p, q):
            mine += np.bincount(i, minlength=len(q)) if len(i) > len(q) // 4 else 0
            if len(i) <= len(q) // 4:
                np.add.at(mine, i, 1)
            np.add.at(mine, j, 1)
            if b != at:
                if at >= 0:
                    yield _pack(at, held)
                at, held = b, np.zeros(size, np.int64)
            held += np.bincount(number, minlength=size)
        if at >= 0:
            yield _pack(at, held)
        for (b, order), part in zip(orders, np.split(mine, np.cumsum(sizes)[:-1]), strict=True):
            yield _pack(b, part[order])

    return run


def _unpacked(uri: str, degree_files: list[str] | None = None):
    """Packed counts of one bucket -> its edges with their sums, and their degrees where those of vertices are given."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fs, path = pafs.FileSystem.from_uri(uri if "://" in uri else f"file://{uri}")
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for b, size, packed in zip(*(batch.column(k) for k in range(3)), strict=True):
                counts = np.frombuffer(pa.decompress(packed.as_buffer(), 4 * size.as_py(), codec="zstd"), "<i4")
                sums[b.as_py()] = sums[b.as_py()] + counts if b.as_py() in sums else counts.astype(np.int64)
        vertices = Vertices.read(degree_files) if degree_files is not None and sums else None
        for b, counts in sums.items():
            x = _Bucket(fs, f"{path}/b={b}")
            order = np.argsort(x.laid, kind="stable")
            p, q = np.repeat(x.lists[1], x.lists[0])[order], x.lists[2][order]
            u, v = np.minimum(p, q), np.maximum(p, q)
            for k in range(0, len(u), 100_000):
                part = [c[k : k + 100_000] for c in (u, v, counts)]
                part[2:2] = [vertices.least(*part[:2])] if vertices else []
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in part], names=["u", "v", "d_e", "t_inc"] if vertices else ["u", "v", "t_inc"])

    return run


def edge_counts(edges: DataFrame, m: int, bucket: int = BUCKET, degree: DataFrame | None = None) -> DataFrame:
    """u, v, t_inc of every edge, and d_e where degree, a written table that a task can hold, is given: what crosses the network is a packed count for
    each edge and task."""
    spark = edges.sparkSession
    uri, n = write_lists(edges, m, bucket, degree)
    counted = spark.range(0, n, 1, min(n, max(1, n * bucket // HELD))).mapInArrow(_counted(uri, n), PACKED)
    files, also = (None, "") if degree is None else (degree.inputFiles(), "d_e long, ")
    return counted.repartitionById(n, F.col("b")).mapInArrow(_unpacked(uri, files), f"u long, v long, {also}t_inc long")
