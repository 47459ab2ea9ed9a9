"""Degeneracy and its relatives.

Peeling removes all vertices of degree at most k at once, so a round costs one aggregation of what is left; lineage is cut by written tables.
The last edges, up to a stated number, are peeled on the driver.
Bounds come cheaper: an order gives an upper bound, a subgraph a lower one, and batch peeling a factor 2(1+eta) in log n rounds.
"""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ledger import file_reads
from ..plans.store import folder, gone_at_end, shared_root, stored, written
from ..sources.edges import half_edges
from . import closing, whole
from .exact import degrees, written_degrees
from .passes import BROADCAST_KEYS

CORES = "v long, core long"
TASK_EDGES = 16_000_000  # some 400 MB in one task


def _rest(edges: list[tuple[int, int]], k: int) -> tuple[int, dict[int, int]]:
    """Core numbers of what is left, one vertex of least degree after the other, k so far."""
    near: dict[int, set[int]] = {}
    for a, b in edges:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    heap, cores = [(len(x), v) for v, x in near.items()], {}
    heapq.heapify(heap)
    while heap:
        d, v = heapq.heappop(heap)
        if v in cores or d != len(near[v]):
            continue
        k = max(k, d)
        cores[v] = k
        for w in near[v]:
            near[w].discard(v)
            heapq.heappush(heap, (len(near[w]), w))
    return k, cores


def peel(edges: DataFrame, driver_edges: int = 50_000) -> tuple[int, DataFrame]:
    """(kappa, core numbers: v, core).  Each round adds its vertices to one folder, so the plan of the answer is one scan, however deep the graph.
    Rounds go on until driver_edges are left at most (0: none); so many, a bounded list, are peeled in one place, as a chain's rounds are its length."""
    spark = edges.sparkSession
    left, k, out = stored(edges, "peel"), 0, folder(spark, "cores")
    spark.createDataFrame([], CORES).write.parquet(out)
    gone_at_end(spark, out)
    while left_edges := left.count():
        if left_edges <= driver_edges:
            k, cores = _rest([tuple(r) for r in left.select("u", "v").collect()], k)
            spark.createDataFrame(list(cores.items()), CORES).write.mode("append").parquet(out)
            break
        d = stored(degrees(left), "peel-degrees")
        k = max(k, int(d.agg(F.min("d")).first()[0]))
        gone = d.where(F.col("d") <= k).select(F.col("x").alias("v"), F.lit(k).alias("core"))
        u, v = gone.select(F.col("v").alias("u")), gone.select("v")
        smaller = stored(left.join(u, "u", "left_anti").join(v, "v", "left_anti").select("u", "v"), "peel")
        # a vertex whose last neighbours go with this batch has no edge left: it goes at this k too
        rest = d.where(F.col("d") > k).select(F.col("x").alias("v")).join(half_edges(smaller).select(F.col("x").alias("v")).distinct(), "v", "left_anti")
        gone.unionByName(rest.select("v", F.lit(k).alias("core"))).select("v", F.col("core").cast("long").alias("core")).write.mode("append").parquet(out)
        left = smaller
    return k, spark.read.schema(CORES).parquet(out)


def cores(edges: DataFrame) -> DataFrame:
    """Core numbers (v, core): in one task up to TASK_EDGES, and as bits where vertices are few, else by peeling rounds."""
    left = written(edges, "cores-edges")
    m = left.count()
    d = stored(written_degrees(left), "cores-degrees")
    as_bits = whole.dense(d.count(), m)
    if (m <= TASK_EDGES or as_bits) and closing.readable(shared_root(edges.sparkSession)):
        return left.select("u", "v").coalesce(1).mapInArrow(whole.cores(d.inputFiles(), as_bits), CORES)
    return peel(left)[1]


def peel_batch(edges: DataFrame, eta: float = 0.5) -> int:
    """An upper bound of at most 2(1+eta) times the degeneracy: all vertices of degree up to (1+eta) times the mean go."""
    left, bound = edges if len(file_reads(edges)) == 1 else stored(edges, "batch"), 0
    while not left.isEmpty():
        d = stored(written_degrees(left), "batch-degrees")
        mean = d.agg(F.avg("d")).first()[0]
        gone = d.where(F.col("d") <= (1 + eta) * mean)
        most, n_gone, n = *gone.agg(F.max("d"), F.count(F.lit(1))).first(), d.count()
        bound = max(bound, int(most))
        if n <= whole.VERTICES and closing.readable(shared_root(edges.sparkSession)):
            left = stored(left.select("u", "v").mapInArrow(whole.above(d.inputFiles(), (1 + eta) * mean), "u long, v long"), "batch")
            continue
        # every end has a degree here, so what stays may be named by either side; the shorter list goes to all tasks where it is short
        stays = n - n_gone < n_gone
        side = (d.where(F.col("d") > (1 + eta) * mean) if stays else gone).select("x")
        side = F.broadcast(side) if min(n_gone, n - n_gone) <= BROADCAST_KEYS else side
        how = "left_semi" if stays else "left_anti"
        left = stored(left.join(side.withColumnRenamed("x", "u"), "u", how).join(side.withColumnRenamed("x", "v"), "v", how).select("u", "v"), "batch")
    return bound


def cores_by_hindex(edges: DataFrame, most_rounds: int = 100) -> DataFrame:
    """Core numbers (v, core): every vertex takes the h-index of its neighbours' values until nothing moves; after most_rounds, peeling gives them."""
    half = stored(half_edges(edges), "hindex-edges")
    value = stored(half.groupBy("x").agg(F.count(F.lit(1)).alias("h")), "hindex")
    for _ in range(most_rounds):
        seen = half.join(value.select(F.col("x").alias("nbr"), F.col("h").alias("hn")), "nbr").join(value, "x")
        # neighbours at or above a level, by counts of values: a hub's list never meets in one place unsummed
        counts = seen.groupBy("x", "h", F.least("hn", "h").alias("level")).agg(F.count(F.lit(1)).alias("n"))
        lists = counts.groupBy("x", "h").agg(F.sort_array(F.collect_list(F.struct("level", "n")), asc=False).alias("levels"))
        step = F.aggregate("levels", F.struct(F.lit(0).cast("long").alias("n"), F.lit(0).cast("long").alias("best")), lambda s, x: F.struct((s["n"] + x["n"]).alias("n"), F.greatest(s["best"], F.least(x["level"], s["n"] + x["n"])).alias("best")))
        new = stored(lists.select("x", "h", step["best"].alias("next")), "hindex")
        moved = not new.where("h != next").isEmpty()
        value = new.select("x", F.col("next").alias("h"))
        if not moved:
            return value.select(F.col("x").alias("v"), F.col("h").alias("core"))
    return peel(edges)[1]  # also where a chain is longer than the rounds reach


def forward_degree_bound(edges: DataFrame, order: DataFrame) -> DataFrame:
    """order (x, rank): the most later neighbours of any vertex bounds the degeneracy from above."""
    later = half_edges(edges).join(order.select("x", "rank"), "x").join(order.select(F.col("x").alias("nbr"), F.col("rank").alias("rank2")), "nbr").where("rank < rank2")
    return later.groupBy("x").agg(F.count(F.lit(1)).alias("f")).agg(F.coalesce(F.max("f"), F.lit(0)).alias("upper"))


def min_degree_of_subgraph(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """The least degree inside a vertex set (x) bounds the degeneracy from below."""
    inside = edges.join(vertices.select(F.col("x").alias("u")), "u", "left_semi").join(vertices.select(F.col("x").alias("v")), "v", "left_semi")
    return degrees(inside).agg(F.coalesce(F.min("d"), F.lit(0)).alias("lower"))


def density_bound(edges: DataFrame) -> DataFrame:
    """A forest on n vertices has at most n - 1 edges: ceil(m / (n - 1)) forests are needed."""
    n = degrees(edges).agg(F.count(F.lit(1)).alias("n"))
    return n.join(edges.agg(F.count(F.lit(1)).alias("m"))).select(F.when(F.col("n") > 1, F.ceil(F.col("m") / (F.col("n") - 1))).otherwise(0).cast("long").alias("lower"))


def arboricity_bounds(kappa: int) -> tuple[int, int]:
    return -(-(kappa + 1) // 2) if kappa else 0, kappa
