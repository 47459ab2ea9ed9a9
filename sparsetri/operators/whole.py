"""Graphs whose vertices fit into one task's memory: arrays by vertex number instead of joins.

Vertices have the number of their id in order.  Tasks read the table of degrees, and edges where they need all, from the shared folder by themselves.
A graph that has no more than 64 pairs of vertices for each edge is kept as rows of bits, which take no more than its lists would.
"""

from __future__ import annotations

from collections.abc import Iterator
from urllib.parse import unquote

import numpy as np
import pyarrow as pa
import pyarrow.fs as pafs
import pyarrow.parquet as pq

#: Vertices of a graph kept as bits at most (128 MB), vertices whose degrees a task holds, wedges that are looked up together.
BITS, VERTICES, TOGETHER = 1 << 15, 4_000_000, 1_000_000
SUMMARY = "n long, m long, t long, sum_de long"
Pairs = Iterator[tuple[np.ndarray, np.ndarray]]


def columns(files: list[str], a: str, b: str) -> Pairs:
    """Two columns of files in the shared folder, a row group at a time."""
    for f in files:
        fs, path = pafs.FileSystem.from_uri(f) if "://" in f else pafs.FileSystem.from_uri("file://" + unquote(f.removeprefix("file:")))
        with fs.open_input_file(path) as source:
            for batch in pq.ParquetFile(source).iter_batches(1 << 20, columns=[a, b], use_threads=False):
                yield batch.column(0).to_numpy(zero_copy_only=False), batch.column(1).to_numpy(zero_copy_only=False)


def incoming(batches: Iterator[pa.RecordBatch]) -> Pairs:
    for b in batches:
        if b.num_rows:
            yield b.column(0).to_numpy(zero_copy_only=False), b.column(1).to_numpy(zero_copy_only=False)


class Vertices:
    """ids in order and their degrees."""

    def __init__(self, ids: np.ndarray, d: np.ndarray):
        order = np.argsort(ids, kind="stable")
        self.ids, self.d = ids[order], d[order].astype(np.int64)
        self.table, span = None, int(ids.max()) - int(ids.min()) + 1 if len(ids) else 0
        if span <= max(1 << 16, 8 * len(ids)):
            self.table = np.zeros(span, np.int32)
            self.table[self.ids - self.ids[:1]] = np.arange(len(ids), dtype=np.int32)

    @classmethod
    def read(cls, files: list[str]) -> Vertices:
        parts = [(np.empty(0, np.int64), np.empty(0, np.int64)), *columns(files, "x", "d")]
        return cls(*(np.concatenate(c) for c in zip(*parts, strict=True)))

    def number(self, x: np.ndarray) -> np.ndarray:
        return self.table[x - self.ids[0]] if self.table is not None else np.searchsorted(self.ids, x).astype(np.int32)

    def least(self, u: np.ndarray, v: np.ndarray) -> np.ndarray:
        """Degrees of edges."""
        return np.minimum(self.d[self.number(u)], self.d[self.number(v)])


def dense(n: int, m: int) -> bool:
    return n <= BITS and n * n <= 64 * m


def bits(vertices: Vertices, edges: Pairs, both: bool) -> np.ndarray:
    """Rows of bits: neighbours of a vertex, all or only later ones."""
    n = len(vertices.ids)
    words = (n + 63) // 64
    out = np.zeros(n * words * 8, np.uint8)
    for u, v in edges:
        p, q = vertices.number(u).astype(np.int64), vertices.number(v).astype(np.int64)
        p, q = np.minimum(p, q), np.maximum(p, q)
        for a, b in ((p, q), (q, p))[: 2 if both else 1]:
            np.bitwise_or.at(out, a * (words * 8) + (b >> 3), np.left_shift(1, b & 7).astype(np.uint8))
    return out.view(np.uint64).reshape(n, words)


def later(row: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.unpackbits(row.view(np.uint8), bitorder="little"))


def closed_bits(rows: np.ndarray, own: range) -> int:
    """Triangles whose first vertex is among own; rows: later neighbours."""
    t = 0
    for p in own:
        q, first = later(rows[p]), p // 64
        t += sum(int(np.bitwise_count(rows[near, first:] & rows[p, first:]).sum(dtype=np.int64)) for near in np.array_split(q, 1 + len(q) // 4096))
    return t


def peeled_bits(vertices: Vertices, rows: np.ndarray) -> np.ndarray:
    n, d = len(rows), vertices.d.copy()
    core, alive, k = np.zeros(n, np.int64), np.arange(n), 0
    there = np.ones(n, bool)
    while len(alive):
        k = max(k, int(d[alive].min()))
        while len(go := alive[there[alive] & (d[alive] <= k)]):
            core[go], there[go] = k, False
            for part in np.array_split(go, 1 + len(go) // 64):
                d -= np.unpackbits(rows[part].view(np.uint8), axis=1, bitorder="little")[:, :n].sum(axis=0, dtype=np.int64)
        alive = alive[there[alive]]
    return core


def lists(vertices: Vertices, edges: Pairs) -> tuple[np.ndarray, np.ndarray]:
    """(starts, neighbours' numbers): neighbours of vertex i at starts[i]:starts[i + 1]; 24 bytes an edge at most at once."""
    starts = np.r_[0, np.cumsum(vertices.d)]
    keys, at = np.empty(int(starts[-1]), np.int64), 0
    for u, v in edges:
        p, q = vertices.number(u).astype(np.int64), vertices.number(v).astype(np.int64)
        keys[at : at + len(p)] = (p << 32) | q
        keys[at + len(p) : at + 2 * len(p)] = (q << 32) | p
        at += 2 * len(p)
    keys.sort()
    return starts, (keys & 0xFFFFFFFF).astype(np.int32)


def peeled(vertices: Vertices, starts: np.ndarray, near_all: np.ndarray) -> np.ndarray:
    """Core numbers by rounds over arrays; a round costs what it removes."""
    n, d = len(vertices.ids), vertices.d.copy()
    core, alive, k = np.zeros(n, np.int64), np.arange(n), 0
    there = np.ones(n, bool)
    while len(alive):
        k = max(k, int(d[alive].min()))
        go = alive[d[alive] <= k]
        while len(go):
            core[go], there[go] = k, False
            found = []
            for part in np.array_split(go, 1 + int(vertices.d[go].sum()) // 4_000_000):
                many = vertices.d[part]
                near = near_all[np.repeat(starts[part] - np.cumsum(many) + many, many) + np.arange(many.sum())]
                near = near[there[near]]
                if 8 * len(near) > n:
                    less = np.bincount(near, minlength=n)
                    near = np.flatnonzero(less)
                    d[near] -= less[near]
                else:
                    near, less = np.unique(near, return_counts=True)
                    d[near] -= less
                found.append(near)
            near = found[0] if len(found) == 1 else np.unique(np.concatenate(found))
            go = near[d[near] <= k]
        alive = alive[there[alive]]
    return core


def cores(files: list[str], as_bits: bool):
    """All edges u, v -> core numbers; files: of the degrees."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vertices = Vertices.read(files)
        if not len(vertices.ids):
            return
        if as_bits:
            core = peeled_bits(vertices, bits(vertices, incoming(batches), True))
        else:
            core = peeled(vertices, *lists(vertices, incoming(batches)))
        for k in range(0, len(core), 100_000):
            yield pa.RecordBatch.from_arrays([pa.array(vertices.ids[k : k + 100_000]), pa.array(core[k : k + 100_000])], names=["v", "core"])

    return run


def edge_degrees(files: list[str]):
    """Edges u, v -> their number and the sum of their degrees (the less of both ends') in each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vertices, m, total = None, 0, 0
        for u, v in incoming(batches):
            vertices = vertices or Vertices.read(files)
            m, total = m + len(u), total + int(vertices.least(u, v).sum())
        yield pa.RecordBatch.from_arrays([pa.array([m], pa.int64()), pa.array([total], pa.int64())], names=["m", "sum_de"])

    return run


def count_bits(degree_files: list[str], edge_files: list[str], tasks: int):
    """Numbers of tasks -> triangles of each one's share of the vertices."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = [k for batch in batches for k in batch.column(0).to_pylist()]
        if own:
            vertices = Vertices.read(degree_files)
            rows = bits(vertices, columns(edge_files, "u", "v"), False)
            yield pa.RecordBatch.from_arrays([pa.array([sum(closed_bits(rows, range(k, len(rows), tasks)) for k in own)], pa.int64())], names=["t"])

    return run


def one_summary(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All edges of a small graph -> SUMMARY in one row."""
    parts = [(np.empty(0, np.int64), np.empty(0, np.int64)), *incoming(batches)]
    u, v = (np.concatenate(c) for c in zip(*parts, strict=True))
    vertices = Vertices(*np.unique(np.concatenate([u, v]), return_counts=True))
    n, m, t, total = len(vertices.ids), len(u), 0, 0
    if m:
        p, q = vertices.number(u).astype(np.int64), vertices.number(v).astype(np.int64)
        total = int(vertices.least(u, v).sum())
        if dense(n, m):
            t = closed_bits(bits(vertices, iter([(u, v)]), False), range(n))
        else:
            t = closed_lists(vertices, p, q)
    yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()) for x in (n, m, t, total)], names=["n", "m", "t", "sum_de"])


def closed_lists(vertices: Vertices, p: np.ndarray, q: np.ndarray) -> int:
    """Triangles of edges between numbers p, q: pairs in lists of neighbours that come later by (degree, number), looked up among the edges."""
    place = np.empty(len(vertices.ids), np.int64)
    place[np.argsort(vertices.d, kind="stable")] = np.arange(len(place))
    p, q = place[p], place[q]
    keys = np.sort((np.minimum(p, q) << 32) | np.maximum(p, q))
    a, b = keys >> 32, keys & 0xFFFFFFFF
    left = np.searchsorted(a, a, "right") - np.arange(len(a)) - 1
    upto, t, k = np.cumsum(left), 0, 0
    while k < len(a):
        stop = max(k + 1, int(np.searchsorted(upto, (upto[k - 1] if k else 0) + TOGETHER, "right")))
        many = left[k:stop]
        i = np.repeat(np.arange(k, stop), many)
        j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(many) - many, many)
        wanted = (b[i] << 32) | b[j]
        at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
        t += int((keys[at] == wanted).sum())
        k = stop
    return t


def above(degree_files: list[str], cut: float):
    """Edges u, v -> those whose ends are both of more than `cut`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vertices = None
        for u, v in incoming(batches):
            vertices = vertices or Vertices.read(degree_files)
            keep = vertices.least(u, v) > cut
            yield pa.RecordBatch.from_arrays([pa.array(u[keep]), pa.array(v[keep])], names=["u", "v"])

    return run


class Marked:
    """Edges to be looked up."""

    def __init__(self, files: list[str]):
        parts = [(np.empty(0, np.int64), np.empty(0, np.int64)), *columns(files, "u", "v")]
        u, v = (np.concatenate(c) for c in zip(*parts, strict=True))
        self.ids = np.unique(np.concatenate([u, v]))
        self.keys = np.unique((np.searchsorted(self.ids, u) << 32) | np.searchsorted(self.ids, v))

    def number(self, x: np.ndarray) -> np.ndarray:
        at = np.minimum(np.searchsorted(self.ids, x), len(self.ids) - 1)
        return np.where(self.ids[at] == x, at, -1)

    def holds(self, p: np.ndarray, q: np.ndarray) -> np.ndarray:
        """Of numbers p, q, -1 where an id is none of an edge's."""
        out = np.zeros(len(p), bool)
        some = np.flatnonzero((p >= 0) & (q >= 0))
        keys = (p[some] << 32) | q[some]
        out[some] = self.keys[np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)] == keys
        return out


def with_marked(files: list[str]):
    """Triangles a < b < c -> those with an edge among the marked ones."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        marked = None
        for batch in batches:
            marked = marked or Marked(files)
            if batch.num_rows and len(marked.keys):
                a, b, c = (marked.number(x.to_numpy(zero_copy_only=False)) for x in batch.columns)
                yield batch.filter(pa.array(marked.holds(a, b) | marked.holds(a, c) | marked.holds(b, c)))

    return run
