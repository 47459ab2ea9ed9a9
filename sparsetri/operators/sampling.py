"""Uniform, degree-proportional and neighbour samples, exact in distribution and independent of partitioning.

Sampling with repetition in one scan rests on a bijection: slots draw positions below the population size, the k-th distinct position
stands for the k-th element in coin order, and coin order is a uniformly random order.  So a bottom-r list is enough.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import COIN_RANGE, coin52
from .passes import watched


def slots(spark, reps: int, size: int) -> DataFrame:
    """(rep, slot)."""
    return spark.range(reps).select(F.col("id").cast("int").alias("rep")).join(spark.range(size).select(F.col("id").alias("slot")))


def bottom_edges(edges: DataFrame, r: int, m: int, seed: int, reps: int = 1, coin: str = "md5") -> DataFrame:
    """(rep, rank, u, v): the r edges of least coin for each replica.  Edges whose coin is far too large leave in the scan
    itself, so only about r rows a replica are ever ordered."""
    slack = 1 + 10 / math.sqrt(max(r, 1)) + 50 / max(r, 1)
    tossed = edges.select("u", "v", F.explode(F.sequence(F.lit(0), F.lit(reps - 1))).alias("rep")).withColumn("coin", coin52(seed, F.lit("edge"), "rep", "u", "v", mode=coin))
    if m and slack * r < m:
        tossed = tossed.where(F.col("coin") < int(COIN_RANGE * slack * r / m))
    order = Window.partitionBy("rep").orderBy("coin", "u", "v")
    return tossed.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= r).select("rep", "rank", "u", "v")


def uniform_multiset(edges: DataFrame, r: int, m: int, seed: int, reps: int = 1, coin: str = "md5") -> DataFrame:
    """(rep, slot, u, v): r independent uniform edges a replica, repeats and all."""
    spark = edges.sparkSession
    if not m:
        return bottom_edges(edges, 0, 0, seed, reps, coin).select("rep", F.col("rank").cast("long").alias("slot"), "u", "v")
    drawn = slots(spark, reps, r).withColumn("position", coin52(seed, F.lit("slot"), "rep", "slot", mode=coin) % m)
    drawn = drawn.withColumn("rank", F.dense_rank().over(Window.partitionBy("rep").orderBy("position")))
    return drawn.join(bottom_edges(edges, r, m, seed, reps, coin), ["rep", "rank"]).select("rep", "slot", "u", "v")


def bernoulli_edges(edges: DataFrame, p: float, seed: int, coin: str = "md5") -> DataFrame:
    """Each edge with probability p: a filter in the scan, no shuffle."""
    return edges.where(coin52(seed, F.lit("bernoulli"), "u", "v", mode=coin) < int(p * COIN_RANGE))


def proportional_picks(weighted: DataFrame, weight: str, order: list[str], picks: DataFrame, seed: int, label: str, coin: str = "md5", groups: int = 1) -> DataFrame:
    """picks (rep, i) each get one row of `weighted` (with rep) with probability proportional to its integer weight.

    A pick is an integer below the replica's total, and falls into one row's stretch of the running sum.  The sum is two-level: rows
    are dealt to `groups` by a coin on `order`, groups are summed and laid end to end, and only rows of a group are ordered, so no task
    orders the whole.  Stretches and picks meet on the number of a cell as wide as a mean weight, which makes the range condition an
    equi-join of few rows."""
    rows = weighted.where(F.col(weight) > 0).withColumn("grp", coin52(seed, F.lit("grp"), *order, mode=coin) % groups)
    sums = rows.groupBy("rep", "grp").agg(F.sum(weight).alias("held"), F.count(F.lit(1)).alias("size"))
    whole = Window.partitionBy("rep")
    before = whole.orderBy("grp").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select("rep", "grp", F.coalesce(F.sum("held").over(before), F.lit(0)).alias("base"), F.sum("held").over(whole).alias("total"), F.ceil(F.sum("held").over(whole) / F.sum("size").over(whole)).alias("width"))
    running = Window.partitionBy("rep", "grp").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0)
    laid = rows.withColumn("upto", F.sum(weight).over(running)).join(sums.drop("total"), ["rep", "grp"]).withColumn("upto", F.col("upto") + F.col("base"))
    laid = laid.withColumn("low", F.col("upto") - F.col(weight))
    cells = F.sequence(F.floor(F.col("low") / F.col("width")), F.floor((F.col("upto") - 1) / F.col("width")))
    aimed = picks.join(sums.select("rep", "total", "width").distinct(), "rep").withColumn("aim", coin52(seed, F.lit(label), "rep", "i", mode=coin) % F.col("total"))
    aimed = aimed.select("rep", "i", "aim", F.floor(F.col("aim") / F.col("width")).alias("cell"))
    met = laid.withColumn("cell", F.explode(cells)).drop("width", "base", "grp").join(aimed, ["rep", "cell"])
    return met.where((F.col("low") <= F.col("aim")) & (F.col("aim") < F.col("upto"))).drop("cell", "low", "upto", "aim")


def race_picks(weighted: DataFrame, weight: str, k: int, seed: int) -> DataFrame:
    """k weighted draws in a single pass: in every slot the row of least -ln(U)/weight wins.  k coins a row, combined map-side."""
    each = weighted.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(k - 1))))
    race = -F.log((coin52(seed, F.lit("race"), "i", "u", "v", mode="xx") + 1) / float(COIN_RANGE)) / F.col(weight)
    return each.groupBy("i").agg(F.min(F.struct(race.alias("t"), "u", "v")).alias("w")).select("i", "w.u", "w.v")


def sample_neighbor(half: DataFrame, picks: DataFrame, seed: int, coin: str = "md5", n: int | None = None) -> DataFrame:
    """picks (rep, i, x) -> (rep, i, w): of all neighbours of x the one of least coin.  Minima combine map-side, so a hub
    costs one row a task.  n: a bound of the number of picks."""
    tossed = watched(half, picks.select("rep", "i", "x"), ["x"], n).withColumn("coin", coin52(seed, F.lit("neighbor"), "rep", "i", "nbr", mode=coin))
    return tossed.groupBy("rep", "i").agg(F.min(F.struct("coin", "nbr")).alias("best")).select("rep", "i", F.col("best.nbr").alias("w"))


def ranked_neighbor(half: DataFrame, picks: DataFrame, seed: int, coin: str = "md5", n: int | None = None) -> DataFrame:
    """picks (rep, i, x, d_e) -> (rep, i, w): the neighbour at a drawn place among those of x, in order of ids.  A pick tosses one coin, not one for each
    neighbour; neighbours are numbered once for each distinct x."""
    listed = watched(half, picks.select("x").distinct(), ["x"], n).withColumn("place", F.row_number().over(Window.partitionBy("x").orderBy("nbr")) - 1)
    aimed = picks.select("rep", "i", "x", (coin52(seed, F.lit("place"), "rep", "i", mode=coin) % F.col("d_e")).cast("int").alias("place"))
    return aimed.join(listed, ["x", "place"]).select("rep", "i", F.col("nbr").alias("w"))


def bottom_neighbors(half: DataFrame, targets: DataFrame, s: int, seed: int, coin: str = "md5", n: int | None = None) -> DataFrame:
    """targets (u, v, x, y, d_e) -> targets with nbr, coin and rank: the s neighbours of x of least coin.  Lists of parts of the edges merge by another cut."""
    tossed = watched(half, targets, ["x"], n).withColumn("coin", coin52(seed, F.lit("owner"), "u", "v", "nbr", mode=coin))
    order = Window.partitionBy("u", "v").orderBy("coin", "nbr")
    return tossed.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= s)


def drawn_neighbors(ranked: DataFrame, targets: DataFrame, s: int, seed: int, coin: str = "md5", exhaustive: bool = False) -> DataFrame:
    """(u, v, y, w, d_e, times): s draws from N(x) with repetition out of bottom lists, equal draws added up.

    With exhaustive, targets of at most s neighbours get each of them s times over d_e: times = s for each and the caller
    divides by d_e less."""
    spark = ranked.sparkSession
    drawn = targets.join(spark.range(s).select(F.col("id").alias("j")))
    drawn = drawn.withColumn("position", coin52(seed, F.lit("draw"), "u", "v", "j", mode=coin) % F.col("d_e"))
    drawn = drawn.withColumn("rank", F.dense_rank().over(Window.partitionBy("u", "v").orderBy("position")))
    times = drawn.groupBy("u", "v", "rank").agg(F.count(F.lit(1)).alias("times"))
    sampled = ranked.join(times, ["u", "v", "rank"]).select("u", "v", "y", F.col("nbr").alias("w"), "d_e", F.col("times"))
    if not exhaustive:
        return sampled
    everyone = ranked.where(F.col("d_e") <= s).select("u", "v", "y", F.col("nbr").alias("w"), "d_e", F.lit(s).cast("long").alias("times"))
    return sampled.where(F.col("d_e") > s).unionByName(everyone)
