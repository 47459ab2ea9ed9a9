"""The six passes as streams over one directory of edge files.

Each pass is one AvailableNow query.  A micro-batch writes its own mergeable summary under its batch id (a bottom list, counters, minima,
hits); summaries of all batches are merged at the end of the pass, and none is larger than what the plan samples.  All merges are minima, sums by batch and unions, so neither the
order of edges, nor batching, nor replays change a result, and results equal the batch engine's.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import assign as owners
from ..operators import passes as probes
from ..operators.sampling import bottom_edges, bottom_neighbors, drawn_neighbors, proportional_picks, slots
from ..functions import coin52
from ..plans.params import SamplePlan
from ..plans.store import folder, stored
from ..sources.edges import half_edges
from .windows import run_by_batches


class EdgeStream:
    """A replayable stream of edges: a directory of Parquet files."""

    def __init__(self, spark: SparkSession, path: str, files_per_batch: int = 2):
        self.spark, self.path, self.files, self.passes = spark, path, files_per_batch, 0

    def one_pass(self, what: str, summarize: Callable[[DataFrame], DataFrame]) -> DataFrame:
        """All batches' summaries, with their batch ids."""
        self.passes += 1
        out, schema = folder(self.spark, f"stream-{what}"), []

        def write(batch: DataFrame, batch_id: int) -> None:
            s = summarize(batch)
            schema[:] = [s.schema]
            s.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")

        stream = self.spark.readStream.schema("u long, v long").option("maxFilesPerTrigger", self.files).parquet(self.path)
        run_by_batches(stream, write, what)
        return self.spark.read.parquet(out).drop("batch") if schema else self.spark.createDataFrame([], "u long")


class Halves(EdgeStream):
    """Two parties, each with a half of the edges, in place of the stream: a pass is the first party's summary, sent over, and the second's,
    and what both make of it, sent back.  `crossed` has the rows of every message."""

    def __init__(self, first: DataFrame, second: DataFrame):
        self.spark, self.halves, self.passes, self.crossed = first.sparkSession, (first, second), 0, []

    def one_pass(self, what: str, summarize: Callable[[DataFrame], DataFrame]) -> DataFrame:
        self.passes += 1
        own = [stored(summarize(h), f"party-{what}") for h in self.halves]
        self.crossed += [s.count() for s in own]
        return own[0].unionByName(own[1])


def least_edges(batch: DataFrame, r: int, seed: int) -> DataFrame:
    """The r edges of least coin: a top-r of each task, merged, so that no batch is ordered whole."""
    tossed = batch.select("u", "v", coin52(seed, F.lit("edge"), F.lit(0), "u", "v").alias("coin"))
    return tossed.orderBy("coin", "u", "v").limit(r).select("u", "v")


def first_pass(stream: EdgeStream, r: int, seed: int) -> tuple[DataFrame, int]:
    """(sample: rep, slot, u, v; m).  The batch summary is its own bottom list and, in one row without an edge, its number of edges."""

    def summary(batch: DataFrame) -> DataFrame:
        none = F.lit(None).cast("long")
        counted = batch.agg(F.count(F.lit(1)).alias("edges")).select(none.alias("u"), none.alias("v"), "edges")
        return least_edges(batch, r, seed).select("u", "v", none.alias("edges")).unionByName(counted)

    seen = stored(stream.one_pass("bottom", summary), "stream-bottom")
    m = int(seen.agg(F.coalesce(F.sum("edges"), F.lit(0))).first()[0])
    return stored(_multiset(stored(least_edges(seen.where("u is not null"), r, seed), "stream-least"), r, m, seed), "stream-sample"), m


def _multiset(candidates: DataFrame, r: int, m: int, seed: int) -> DataFrame:
    drawn = slots(candidates.sparkSession, 1, r if m else 0).withColumn("position", coin52(seed, F.lit("slot"), "rep", "slot") % max(m, 1))
    drawn = drawn.withColumn("rank", F.dense_rank().over(Window.partitionBy("rep").orderBy("position")))
    return drawn.join(bottom_edges(candidates, r, 0, seed), ["rep", "rank"]).select("rep", "slot", "u", "v")


def live_sample(stream: EdgeStream, r: int, seed: int) -> DataFrame:
    """(m, u, v) in a single live pass: after every batch the state is m and the bottom list of what has come; the last state is returned.  A sample of
    the whole is exact; whatever else a single pass could watch of an edge counts from its arrival on, and carries no guarantee."""
    states: list[DataFrame] = []

    def write(batch: DataFrame, _: int) -> None:
        new = batch.agg(F.count(F.lit(1)).alias("m"))
        if states:
            new = new.join(states[-1].agg(F.max("m").alias("before"))).select((F.col("m") + F.coalesce("before", F.lit(0))).alias("m"))
            batch = batch.unionByName(states[-1].select("u", "v"))
        states[:] = [stored(least_edges(batch, r, seed).join(new), "live")]

    run_by_batches(stream.spark.readStream.schema("u long, v long").option("maxFilesPerTrigger", stream.files).parquet(stream.path), write, "live")
    return states[-1].select("m", "u", "v") if states else stream.spark.createDataFrame([], "m long, u long, v long")


def _summed(rows: DataFrame) -> DataFrame:
    return rows.groupBy("kind", "a", "b").agg(F.sum("n").alias("n"))


def streamed_six_pass(stream: EdgeStream, plan: SamplePlan) -> DataFrame:
    """rep, m, r, ell, sum_dr, hits, x_est for one replica, as the batch engine gives."""
    spark = stream.spark
    sample, m = first_pass(stream, plan.r, plan.seed)
    plan = replace(plan, m=m)
    ends = sample.select(F.explode(F.array("u", "v")).alias("x")).distinct()
    known = probes.degrees_of(stored(_summed(stream.one_pass("degrees", lambda b: probes.probe_pass(b, ends, n=2 * plan.r))), "stream-degrees"))
    sample = stored(probes.with_edge_degree(sample, known).select("rep", "slot", "u", "v", "x", "y", "d_e"), "stream-edges")
    picks = stored(proportional_picks(sample, "d_e", ["slot"], slots(spark, 1, plan.ell).withColumnRenamed("slot", "i"), plan.seed, "pick").drop("slot"), "stream-picks")

    def least(batch: DataFrame) -> DataFrame:
        tossed = probes.watched(half_edges(batch), picks.select("rep", "i", "x"), ["x"], plan.ell).withColumn("coin", coin52(plan.seed, F.lit("neighbor"), "rep", "i", "nbr"))
        return tossed.groupBy("rep", "i").agg(F.min(F.struct("coin", "nbr")).alias("best"))

    best = stream.one_pass("neighbors", least).groupBy("rep", "i").agg(F.min("best").alias("best")).select("rep", "i", F.col("best.nbr").alias("w"))
    chosen = stored(picks.join(best, ["rep", "i"]), "stream-neighbors").withColumns({"p": F.least("y", "w"), "q": F.greatest("y", "w")})
    third, pairs = chosen.select(F.col("w").alias("x")).distinct(), chosen.where("w != y").select("p", "q").distinct()
    probed = stored(_summed(stream.one_pass("closures", lambda b: probes.probe_pass(b, third, pairs, 2 * plan.ell))), "stream-closures")
    t = F.array_sort(F.array("u", "v", "w"))
    closed = chosen.join(probes.pairs_of(probed), ["p", "q"]).where("w != y").select("rep", "i", "u", "v", *(F.get(t, F.lit(k)).alias(c) for k, c in enumerate("abc")))
    closed = stored(closed, "stream-closed")
    everyone = probes.degrees_of(probed).unionByName(known).distinct()
    # the last two passes keep a bottom list of s neighbours for each edge that may own, and the hits among drawn pairs
    rows, targets = owners.asked(owners.remember(None, closed), everyone, plan.degree_cut)
    rows, targets = stored(rows, "stream-triangles"), stored(targets, "stream-targets")
    lists = stored(stream.one_pass("owner-neighbors", lambda b: bottom_neighbors(half_edges(b), targets, plan.s, plan.seed, n=3 * plan.ell).drop("rank")), "stream-lists")
    merged = lists.withColumn("rank", F.row_number().over(Window.partitionBy("u", "v").orderBy("coin", "nbr"))).where(F.col("rank") <= plan.s)
    drawn = stored(owners.closing_pairs(drawn_neighbors(merged, targets, plan.s, plan.seed)), "stream-draws")
    nobody, asked = targets.where("false").select("x"), drawn.select("p", "q").distinct()
    hit = stored(probes.pairs_of(_summed(stream.one_pass("owner-closures", lambda b: probes.probe_pass(b, nobody, asked, 3 * plan.ell * plan.s)))), "stream-hits")
    memo = owners.decided(rows, owners.estimated(targets, drawn, hit, plan), plan)
    hits = closed.join(memo, owners.ABC).where("owner_u = u and owner_v = v").agg(F.count(F.lit(1)).alias("hits"))
    out = sample.agg(F.coalesce(F.sum("d_e"), F.lit(0)).alias("sum_dr")).join(hits)
    x = F.lit(float(m)) / plan.r * F.col("sum_dr") * F.col("hits") / plan.ell
    return out.select(F.lit(m).cast("long").alias("m"), F.lit(plan.r).cast("long").alias("r"), F.lit(plan.ell).cast("long").alias("ell"), "sum_dr", "hits", F.round(x, 6).alias("x_est"))
