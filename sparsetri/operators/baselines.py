"""Runnable stand-ins for rival bounds, and the bounds themselves.  Each takes coins as the estimators do."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import COIN_RANGE, coin52
from ..sources.edges import canonical, half_edges
from .exact import count_triangles, edge_degrees, edge_triangle_counts, triangle_edges
from .sampling import uniform_multiset


def _closed(edges: DataFrame, wedges: DataFrame) -> DataFrame:
    """wedges with y, w -> those whose ends are joined."""
    ends = wedges.where("w != y").withColumns({"p": F.least("y", "w"), "q": F.greatest("y", "w")})
    return ends.join(edges.select(F.col("u").alias("p"), F.col("v").alias("q")), ["p", "q"], "left_semi")


def incident_sample(edges: DataFrame, r: int, m: int, seed: int) -> DataFrame:
    """(m / 3r) times the triangles on r uniform edges: what fails where one edge is in all triangles."""
    counts = edge_triangle_counts(edges)
    s = uniform_multiset(edges, r, m, seed).join(counts, ["u", "v"]).agg(F.coalesce(F.sum("t_inc"), F.lit(0)).alias("hits"))
    return s.select("hits", F.round(F.lit(float(m)) / (3.0 * r) * F.col("hits"), 6).alias("x_est"))


def uniform_wedges(edges: DataFrame, r: int, m: int, seed: int) -> DataFrame:
    """r uniform edges, ceil(d_e / sqrt(2m)) neighbours of the low end each; a closing neighbour counts if the edge owns its
    triangle by the least-degree rule.  Hits are weighed by d_e over the number of neighbours."""
    e = edge_degrees(edges)
    s = uniform_multiset(edges, r, m, seed).join(e, ["u", "v"])
    tries = s.withColumn("tries", F.ceil(F.col("d_e") / math.sqrt(2 * m)).cast("long"))
    drawn = tries.withColumn("j", F.explode(F.sequence(F.lit(1).cast("long"), F.col("tries"))))
    chosen = half_edges(edges).join(drawn.select("slot", "j", "x"), "x").withColumn("coin", coin52(seed, F.lit("wedge"), "slot", "j", "nbr"))
    chosen = chosen.groupBy("slot", "j").agg(F.min(F.struct("coin", "nbr"))["nbr"].alias("w"))
    closed = _closed(edges, drawn.join(chosen, ["slot", "j"]))
    t = F.array_sort(F.array("u", "v", "w"))
    tri = closed.select("slot", "j", "tries", F.col("d_e").alias("own"), F.col("u").alias("eu"), F.col("v").alias("ev"), *(F.get(t, F.lit(i)).alias(c) for i, c in enumerate("abc")))
    least = triangle_edges(tri, "slot", "j").join(e.select("u", "v", "d_e"), ["u", "v"]).groupBy("slot", "j").agg(F.min(F.struct("d_e", "u", "v")).alias("o"))
    owned = tri.join(least, ["slot", "j"]).where("o.u = eu and o.v = ev")
    return owned.agg(F.count(F.lit(1)).alias("hits"), F.round(F.coalesce(F.sum(F.col("own") / F.col("tries")), F.lit(0.0)) * m / r, 6).alias("x_est"))


def oriented_wedges(edges: DataFrame, r: int, m: int, seed: int) -> DataFrame:
    """With free degrees: a uniform edge u -> v in degree order, a uniform later neighbour w of u, accepted with probability
    d+(u) / sqrt(2m).  A triangle is reached from two edges."""
    e = edge_degrees(edges)
    up = F.col("d_u") <= F.col("d_v")
    o = e.select("u", "v", F.when(up, F.col("u")).otherwise(F.col("v")).alias("p"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("y"))
    out = o.groupBy("p").agg(F.count(F.lit(1)).alias("out"))
    s = uniform_multiset(edges, r, m, seed).join(o, ["u", "v"]).join(out, "p")
    s = s.where(coin52(seed, F.lit("accept"), "slot") < F.col("out") / math.sqrt(2 * m) * COIN_RANGE)
    chosen = o.select("p", F.col("y").alias("nbr")).join(s.select("slot", "p"), "p").withColumn("coin", coin52(seed, F.lit("later"), "slot", "nbr"))
    chosen = chosen.groupBy("slot").agg(F.min(F.struct("coin", "nbr"))["nbr"].alias("w"))
    return _closed(edges, s.join(chosen, "slot")).agg(F.count(F.lit(1)).alias("hits")).withColumn("x_est", F.round(F.col("hits") * (m * math.sqrt(2 * m) / 2 / r), 6))


def sparsified_by_edges(edges: DataFrame, p: float, seed: int) -> DataFrame:
    kept = edges.where(coin52(seed, F.lit("sparsify"), "u", "v") < int(p * COIN_RANGE))
    return count_triangles(kept).select(F.col("t").alias("hits"), F.round(F.col("t") / p**3, 6).alias("x_est"))


def sparsified_by_colours(edges: DataFrame, colours: int, seed: int) -> DataFrame:
    """Edges whose ends have one colour; a triangle survives with probability 1 / colours^2."""
    colour = lambda c: coin52(seed, F.lit("colour"), c) % colours
    return count_triangles(edges.where(colour("u") == colour("v"))).select(F.col("t").alias("hits"), F.round(F.col("t") * float(colours**2), 6).alias("x_est"))


def compare_bounds(facts: DataFrame) -> DataFrame:
    """facts: view, m, t, kappa -> the three space bounds without logarithms, and the least."""
    m, t, k = F.col("m").cast("double"), F.col("t"), F.col("kappa")
    out = facts.where("t > 0").withColumns({"mk_over_t": F.round(m * k / t, 6), "m15_over_t": F.round(m * F.sqrt(m) / t, 6), "m_over_sqrt_t": F.round(m / F.sqrt(t), 6)})
    least = F.least("mk_over_t", "m15_over_t", "m_over_sqrt_t")
    names = F.when(F.col("mk_over_t") == least, "degeneracy").when(F.col("m15_over_t") == least, "m15").otherwise("sqrt")
    return out.select("view", "mk_over_t", "m15_over_t", "m_over_sqrt_t", names.alias("winner"), (t >= k * k).alias("past_crossover"))


def disjointness_bits(spark: SparkSession, n: int, shared: bool) -> DataFrame:
    """(i, x, y): n/3 ones in each string; with `shared` they have index 0 in common, else nothing."""
    if n % 3:
        raise ValueError("n must be divisible by 3")
    i = F.col("id")
    y = (((i % 3 == 1) & (i != 1)) | (i == 0)) if shared else i % 3 == 1
    return spark.range(n).select(i.alias("i"), (i % 3 == 0).alias("x"), y.alias("y"))


def hard_graph(bits: DataFrame, p: int, q: int) -> DataFrame:
    """Sides A (0..p-1) and B (p..2p-1), complete between; block i of q vertices joined to all of A if x, to all of B if y."""
    spark = bits.sparkSession
    a, b = spark.range(p).select(F.col("id").alias("a")), spark.range(p, 2 * p).select(F.col("id").alias("a"))
    block = bits.join(spark.range(q).select(F.col("id").alias("j"))).withColumn("w", F.col("i") * q + F.col("j") + 2 * p)
    return canonical(a.join(b.withColumnRenamed("a", "w")).unionByName(a.join(block.where("x").select("w"))).unionByName(b.join(block.where("y").select("w"))), "a", "w", distinct=False)


def hard_graph_for(spark: SparkSession, kappa: int, t: int, n: int, shared: bool) -> DataFrame:
    """The family member with degeneracy about kappa and, if shared, kappa^t triangles."""
    return hard_graph(disjointness_bits(spark, n, shared), kappa, kappa ** (t - 2))


def protocol_bits(passes: int, state_bits: int) -> int:
    """What a replay by two parties can cost at most: the state crosses once in each direction for each pass but the last half."""
    return (2 * passes - 1) * state_bits


def clique_bound(m: int, kappa: int, k: int, count: int) -> float:
    """Conjectured space for k-cliques."""
    return math.inf if not count else m * kappa ** (k - 2) / count


