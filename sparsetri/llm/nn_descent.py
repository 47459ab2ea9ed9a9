"""Embedding near-duplicates by NN-descent.

A neighbour graph inside each label starts from random-hyperplane leaves and is refined by joins of neighbours of neighbours: around
every vector its nearest and reverse neighbours are compared with each other, and what improves a list enters it.  Lists hold `K`
entries; one that is full of links is saturated and may hide others, so it is enlarged: it takes twice as many, found around its neighbours,
until it holds something that is no link or has `MOST` entries.  Inside a component all links are found and counted, in tiles.  A
link between components is in the list of its end that is not saturated; where both ends still are, it is found by comparing all vectors
that stay saturated in a label with one another, in tiles too.  So the only thing that can be missed is what the descent did not come upon.  New
leaves and another descent follow until a round joins no more components and an audit meets the recall: sampled vectors are compared with
all others, and the sample grows until enough of it have a link.  Rounds grow with the largest label.  Where links are too rare to be
audited, or rounds run out, all vectors of a label are compared in tiles: exact, and quadratic in a label.

Equal vectors are one node with a multiplicity, so copies are never compared with one another.  Leaves are split by hash when a
cluster falls into one, tiles are small blocks of a component, and lists are bounded, so that no task holds an unbounded group.

Defined results: a row whose label or vector is null, or whose vector is empty, zero or has null or non-finite components, links
with nothing and is its own component.  Vectors of different lengths never link.  Rows that share a vec_id are one vertex: the least (label,
vector) stands for it.  A null vec_id is its own, with a null component.  Only vec_id, label and embedding are read.
"""

from __future__ import annotations

import math
from collections import defaultdict
from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stored
from .components import connected_components

K, MOST, TREES, LEAF, EMIT, AUDIT, SEEN, MOST_AUDIT = 8, 64, 6, 64, 4, 256, 100, 16384


def units(rows: DataFrame) -> DataFrame:
    """(vec_id, label, dim, unit) of the rows that can link: double precision, unit length."""
    x = F.transform(F.col("embedding"), lambda v: v.cast("double"))
    biggest = F.array_max(F.transform(x, F.abs))
    ok = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & (F.size("embedding") > 0) & ~F.exists("embedding", lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    scaled = rows.where(ok).select(F.col("vec_id").cast("long").alias("vec_id"), F.col("label").cast("string").alias("label"), F.size("embedding").alias("dim"), x.alias("x"), biggest.alias("biggest"))
    scaled = scaled.where("biggest > 0").withColumn("x", F.transform("x", lambda v: v / F.col("biggest")))
    length = F.sqrt(F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v))
    return scaled.withColumn("length", length).select("vec_id", "label", "dim", F.transform("x", lambda v: v / F.col("length")).alias("unit"))


def grouped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Runs of rows with an equal first column, across batch ends."""
    held, key = [], None
    for b in batches:
        if not b.num_rows:
            continue
        keys = b.column(0).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(keys[1:] != keys[:-1]) + 1).tolist(), len(keys)]
        for low, high in zip(cuts, cuts[1:], strict=False):
            if held and keys[low] != key:
                yield pa.Table.from_batches(held)
                held = []
            key = keys[low]
            held.append(b.slice(low, high - low))
    if held:
        yield pa.Table.from_batches(held)


def matrix(t: pa.Table, name: str = "unit") -> np.ndarray:
    c = t.column(name).combine_chunks()
    return c.flatten().to_numpy(zero_copy_only=False).reshape(len(c), -1)


def column(t: pa.Table, name: str) -> np.ndarray:
    return t.column(name).to_numpy()


FOUND = pa.schema([("v", pa.int64()), ("u", pa.int64()), ("cos", pa.float64())])


def _emit(parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), f.type) for x, f in zip(zip(*parts, strict=True), FOUND, strict=True)], schema=FOUND)


def _batched(found: Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
    parts, n = [], 0
    for p in found:
        parts.append(p)
        n += len(p[0])
        if n > 50_000:
            yield _emit(parts)
            parts, n = [], 0
    if n:
        yield _emit(parts)


def _best(ids: np.ndarray, x: np.ndarray, top: int, above: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of every row its `top` most similar others, if more similar than `above`."""
    cos = x @ x.T
    np.fill_diagonal(cos, -2)
    top = min(top, len(ids) - 1)
    at = np.argpartition(-cos, top - 1, axis=1)[:, :top] if top < len(ids) - 1 else np.argsort(-cos, axis=1)[:, :top]
    got = np.take_along_axis(cos, at, axis=1)
    ok = (got > above[:, None]) & (got > -2)
    return np.repeat(ids, ok.sum(axis=1)), ids[at[ok]], got[ok]


def _leaf_join(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    def run():
        for t in grouped(batches):
            if t.num_rows > 1:
                yield _best(column(t, "node"), matrix(t), K, np.full(t.num_rows, -2.0))

    yield from _batched(run())


def _local_join(emit: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Around one vector: its neighbours, each with the similarity that its own list asks for."""

    def run():
        for t in grouped(batches):
            if t.num_rows > 1:
                yield _best(column(t, "u"), matrix(t), emit, column(t, "worst"))

    yield from _batched(run())


def _signs(seed: int, trees: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Leaf names: label, length, tree and as many sign bits as the label's size asks for."""
    planes: dict[int, np.ndarray] = {}
    for b in batches:
        t = pa.Table.from_batches([b])
        bits, dims, labels, nodes = column(t, "bits"), column(t, "dim"), t.column("label").to_pylist(), t.column("node")
        units_ = t.column("unit").combine_chunks()
        out = []
        for dim in np.unique(dims):
            where = np.flatnonzero(dims == dim)
            if dim not in planes:
                planes[dim] = np.random.default_rng([seed, int(dim)]).standard_normal((int(dim), trees * 24))
            x = units_.take(pa.array(where)).flatten().to_numpy(zero_copy_only=False).reshape(len(where), -1)
            marks = (x @ planes[dim] > 0).reshape(len(where), trees, 24)
            for tree in range(trees):
                code = np.where(np.arange(24) < bits[where][:, None], marks[:, tree], False) @ (1 << np.arange(24))
                out.append((where, tree, code))
        for where, tree, code in out:
            names = [f"{tree}|{dims[i]}|{c}|{labels[i]}" for i, c in zip(where.tolist(), code.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(names), nodes.combine_chunks().take(pa.array(where)), units_.take(pa.array(where))], names=["leaf", "node", "unit"])


def _dealt(df: DataFrame, key: str) -> DataFrame:
    """Groups of `key` together and in runs; no group is larger than what its maker bounds it by.  The number of tasks is the session's: merged
    by their bytes, tasks whose work is the square of a group would be too few."""
    return df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), key).sortWithinPartitions(key)


def leaf_lists(nodes: DataFrame, seed: int) -> DataFrame:
    """(v, u, cos): the nearest of each node inside its leaves."""
    sizes = nodes.groupBy("label", "dim").agg(F.count(F.lit(1)).alias("size"))
    sizes = sizes.select("label", "dim", F.greatest(F.lit(0), F.least(F.lit(24), F.ceil(F.log2(F.col("size") / LEAF)))).cast("int").alias("bits"))
    leaves = stored(nodes.join(sizes, ["label", "dim"]).select("node", "label", "dim", "bits", "unit").mapInArrow(partial(_signs, seed, TREES), "leaf string, node long, unit array<double>"), "leaves")
    counts = leaves.groupBy("leaf").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") > 2 * LEAF)
    # a leaf that a cluster fills is split by hash: any part of a cluster is as good a start
    split = leaves.join(counts.withColumn("parts", F.ceil(F.col("size") / LEAF)).select("leaf", "parts"), "leaf", "left")
    named = F.concat_ws("|", "leaf", F.coalesce(F.pmod(F.xxhash64("node", F.lit(seed)), F.col("parts")), F.lit(0)).cast("string"))
    return _dealt(split.select(named.alias("leaf"), "node", "unit"), "leaf").mapInArrow(_leaf_join, "v long, u long, cos double")


def shortened(lists: DataFrame, size: int) -> DataFrame:
    order = Window.partitionBy("v").orderBy(F.desc("cos"), "u")
    return lists.groupBy("v", "u").agg(F.max("cos").alias("cos")).withColumn("place", F.row_number().over(order)).where(F.col("place") <= size)


def descend(nodes: DataFrame, lists: DataFrame) -> DataFrame:
    """One round: neighbours of neighbours are joined, and lists take what is nearer."""
    worst = lists.where(F.col("place") == K).select(F.col("v").alias("u"), F.col("cos").alias("worst"))
    around = lists.select("v", "u", "cos").unionByName(lists.select(F.col("u").alias("v"), F.col("v").alias("u"), "cos"))
    around = shortened(around, 2 * K).select("v", "u")
    placed = around.join(nodes.select(F.col("node").alias("u"), "unit").join(worst, "u", "left").select("u", "unit", F.coalesce("worst", F.lit(-2.0)).alias("worst")), "u")
    found = _dealt(placed.select("v", "u", "worst", "unit"), "v").mapInArrow(partial(_local_join, EMIT), "v long, u long, cos double")
    return shortened(lists.select("v", "u", "cos").unionByName(found), K)


def enlarged(nodes: DataFrame, lists: DataFrame, threshold: float) -> DataFrame:
    """lists, of which those that are full of links have been doubled, up to MOST entries, with links found around their neighbours."""
    size = K
    while size < MOST:
        full = stored(lists.where((F.col("place") == size) & (F.col("cos") >= threshold)).select("v"), "full")
        if full.isEmpty():
            break
        around = lists.select("v", "u", "cos").unionByName(lists.select(F.col("u").alias("v"), F.col("v").alias("u"), "cos"))
        around = shortened(around, 2 * size).select("v", "u")
        # neighbourhoods with a full list in them; only full lists take what is found, and only links
        asked = around.join(full.select(F.col("v").alias("u"), F.lit(threshold - 1e-9).alias("worst")), "u", "left")
        centres = asked.where(F.col("worst").isNotNull()).select("v").distinct()
        placed = asked.join(centres, "v", "left_semi").join(nodes.select(F.col("node").alias("u"), "unit"), "u")
        found = _dealt(placed.select("v", "u", F.coalesce("worst", F.lit(2.0)).alias("worst"), "unit"), "v").mapInArrow(partial(_local_join, 2 * size), "v long, u long, cos double")
        size *= 2
        lists = stored(shortened(lists.select("v", "u", "cos").unionByName(found), size), "lists")
    return lists


TILE, MOST_BLOCKS, MOST_ROWS, ACROSS = 32, 64, 8192, 2048


def _tile(threshold: float, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links between the two blocks of a tile, counted for the rows of both; a tile of one block with itself counts once."""
    for t in grouped(batches):
        node, weight, side, x = column(t, "node"), column(t, "copies"), column(t, "side"), matrix(t)
        if (side == 2).all():
            link = x @ x.T >= threshold
            np.fill_diagonal(link, False)
            n = link @ weight
        else:
            a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
            link = x[a] @ x[b].T >= threshold
            n = np.zeros(len(node), np.int64)
            n[a], n[b] = link @ weight[b], weight[a] @ link
        yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(n.astype(np.int64))], names=["node", "links"])


def tiled(members: DataFrame, key: list[str], block: Column) -> DataFrame:
    """Each pair of blocks of the nodes of one key is a tile; `block` is the rows of a block, by `size`."""
    sizes = members.groupBy(*key).agg(F.count(F.lit(1)).alias("size")).where("size > 1")
    cut = members.join(sizes.select(*key, F.ceil(F.col("size") / block).cast("long").alias("blocks")), key)
    cut = cut.withColumn("own", F.pmod(F.xxhash64("node"), F.col("blocks")))
    tiles = cut.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    side = F.when(F.col("own") == F.col("other"), 2).when(F.col("own") < F.col("other"), 0).otherwise(1)
    named = F.concat_ws("|", *key, F.least("own", "other"), F.greatest("own", "other"))
    return tiles.withColumn("tile", named).withColumn("side", side)


def links_inside(members: DataFrame, threshold: float) -> DataFrame:
    """members: component, node, copies, unit.  (node, links): copies of other nodes of the component that link with it."""
    block = F.greatest(F.lit(TILE), F.least(F.lit(MOST_ROWS), F.ceil(F.col("size") / MOST_BLOCKS)))
    tiles = tiled(members, ["component"], block).select("tile", "node", "copies", "side", "unit")
    return _dealt(tiles, "tile").mapInArrow(partial(_tile, threshold), "node long, links long").groupBy("node").agg(F.sum("links").alias("links"))


def _across(threshold: float, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The pairs of components that links between the two blocks of a tile join."""
    for t in grouped(batches):
        component, side, x = column(t, "component"), column(t, "side"), matrix(t)
        if (component == component[0]).all():
            continue
        a, b = (np.flatnonzero(side != 1), np.flatnonzero(side != 0))
        i, j = np.nonzero((x[a] @ x[b].T >= threshold) & (component[a][:, None] != component[b]))
        pairs = np.unique(np.sort(np.stack([component[a[i]], component[b[j]]], axis=1), axis=1), axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(pairs[:, 0]), pa.array(pairs[:, 1])], names=["a", "b"])


def links_across(members: DataFrame, threshold: float) -> DataFrame:
    """members: label, dim, component, node, unit.  (a, b): components that a link between any two of the members joins."""
    tiles = tiled(members, ["label", "dim"], F.lit(ACROSS)).select("tile", "component", "side", "unit")
    return _dealt(tiles, "tile").mapInArrow(partial(_across, threshold), "a long, b long").distinct()


def audit(members: DataFrame, threshold: float, sample: int = AUDIT) -> tuple[int, int, int, float]:
    """Of a bounded sample of nodes against all nodes: links found, all links, nodes that have one, and the sum of their found shares;
    members: node, label, dim, component, unit."""
    queries = members.orderBy(F.xxhash64(F.lit("audit"), "node")).limit(sample).select("node", "label", "component", "unit").toArrow()
    if not queries.num_rows:
        return 0, 0, 0, 0.0
    own_ids, own_components, vectors = column(queries, "node"), column(queries, "component"), queries.column("unit").combine_chunks()
    alike = defaultdict(list)
    for i, (label, n) in enumerate(zip(queries.column("label").to_pylist(), vectors.value_lengths().to_pylist(), strict=True)):
        alike[n, label].append(i)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found, whole = np.zeros(len(own_ids), np.int64), np.zeros(len(own_ids), np.int64)
        for b in batches:
            t = pa.Table.from_batches([b])
            ids, components, units_ = column(t, "node"), column(t, "component"), t.column("unit").combine_chunks()
            here = defaultdict(list)
            for i, key in enumerate(zip(column(t, "dim").tolist(), t.column("label").to_pylist(), strict=True)):
                here[key].append(i)
            for key, rows in here.items():
                where = np.array(rows)
                x = units_.take(pa.array(where)).flatten().to_numpy(zero_copy_only=False).reshape(len(where), -1)
                for low in range(0, len(alike.get(key, ())), AUDIT):
                    mine = np.array(alike[key][low : low + AUDIT])
                    q = vectors.take(pa.array(mine)).flatten().to_numpy(zero_copy_only=False).reshape(len(mine), -1)
                    link = (q @ x.T >= threshold) & (own_ids[mine][:, None] != ids[where])
                    whole[mine] += link.sum(axis=1)
                    found[mine] += (link & (own_components[mine][:, None] == components[where])).sum(axis=1)
        has = np.flatnonzero(whole)
        yield pa.RecordBatch.from_arrays([pa.array(own_ids[has]), pa.array(found[has]), pa.array(whole[has])], names=["q", "found", "whole"])

    each = members.select("node", "label", "dim", "component", "unit").mapInArrow(run, "q long, found long, whole long").groupBy("q").agg(F.sum("found").alias("found"), F.sum("whole").alias("whole"))
    got = each.agg(F.sum("found"), F.sum("whole"), F.count(F.lit(1)), F.sum(F.col("found") / F.col("whole"))).first()
    return int(got[0] or 0), int(got[1] or 0), int(got[2]), float(got[3] or 0)


def recall_met(members: DataFrame, n: int, threshold: float, recall: float) -> bool | None:
    """Whether the links of a sample, and its nodes on average, are found.  The sample grows until SEEN of its nodes have a link or it is the
    whole table; None if MOST_AUDIT nodes are too few for that."""
    sample = AUDIT
    while True:
        got, whole, linked, shares = audit(members, threshold, sample)
        if got < recall * whole or shares < recall * linked:
            return False
        if linked >= SEEN or sample >= n:
            return True
        if sample >= MOST_AUDIT:
            return None
        sample *= 4


def joined(nodes: DataFrame, links: DataFrame) -> DataFrame:
    """The nodes with their components."""
    found = connected_components(links)
    return stored(nodes.join(found.withColumnRenamed("id", "node"), "node", "left").withColumn("component", F.coalesce("component", "node")), "placed")


def near_vectors(rows: DataFrame, threshold: float = 0.93, recall: float = 0.999, most_rounds: int = 5, descents: int = 2) -> DataFrame:
    """(vec_id, n_links, component_id, kept): a row for each row of `rows`."""
    rows = rows.select("vec_id", "label", "embedding")
    able = units(rows).withColumn("h", F.xxhash64("unit")).withColumn("h2", F.xxhash64(F.lit(1), F.col("unit")))
    able = stored(able, "units")
    if not able.groupBy("vec_id").count().where("count > 1").isEmpty():
        able = stored(able.groupBy("vec_id").agg(F.min(F.struct("label", "dim", "unit", "h", "h2")).alias("s")).select("vec_id", "s.*"), "units")
    nodes = able.groupBy("label", "dim", "h", "h2").agg(F.min(F.struct("vec_id", "unit")).alias("s"), F.count(F.lit(1)).alias("copies"))
    nodes = stored(nodes.select(F.col("s.vec_id").alias("node"), "label", "dim", "h", "h2", "copies", F.col("s.unit").alias("unit")), "nodes")
    n, largest = nodes.count(), nodes.groupBy("label", "dim").count().agg(F.max("count")).first()[0] or 1
    links, placed, apart, settled = None, None, n, False
    for turn in range(most_rounds + max(0, math.ceil(math.log2(largest / LEAF)))):
        lists = stored(shortened(leaf_lists(nodes, turn), K), "lists")
        for _ in range(descents):
            lists = stored(descend(nodes, lists), "lists")
        lists = enlarged(nodes, lists, threshold)
        new = lists.where(F.col("cos") >= threshold).select(F.col("v").alias("a"), F.col("u").alias("b"))
        links = stored(new if links is None else links.unionByName(new).distinct(), "links")
        placed = joined(nodes, links)
        saturated = lists.where((F.col("place") == MOST) & (F.col("cos") >= threshold)).select(F.col("v").alias("node"))
        bridges = stored(links_across(placed.join(saturated, "node"), threshold), "bridges")
        if not bridges.isEmpty():
            placed = joined(nodes, links.unionByName(bridges))
        before, apart = apart, placed.where("node = component").count()
        met = recall_met(placed, n, threshold, recall) if turn == 0 or before == apart else False
        settled = bool(met) and before == apart
        if settled or met is None:
            break
    if not settled:
        # links too rare to be audited, or rounds that ran out: all nodes of a label are compared
        rest = stored(links_across(placed, threshold), "bridges")
        if not rest.isEmpty():
            placed = joined(nodes, placed.where("node <> component").select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(rest))
    counted = links_inside(placed.select("component", "node", "copies", "unit"), threshold)
    named = placed.join(counted, "node", "left").select("label", "dim", "h", "h2", "component", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("links"))
    each = able.select("vec_id", "label", "dim", "h", "h2").join(named, ["label", "dim", "h", "h2"]).select(F.col("vec_id").alias("id"), "links", "component")
    out = rows.select(F.col("vec_id").cast("long").alias("vec_id")).join(each, F.col("vec_id") == F.col("id"), "left")
    out = out.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))
