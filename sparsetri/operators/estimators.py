"""Estimators of the number of triangles.

six_pass: a uniform multiset of edges, their degrees, picks of it in proportion to degree, a neighbour of each pick, its closure, and
(two more passes) the owners of the triangles found.  oracle: the three-pass form with free degrees.  Replicas are a column.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ledger import PassLedger, SpaceGuard
from ..plans.params import SamplePlan
from ..plans.store import stored
from ..sources.edges import half_edges
from . import assign as owners
from .exact import degrees, edge_degrees, edge_triangle_counts
from .passes import degrees_of, pairs_of, probe_pass, with_edge_degree
from .sampling import proportional_picks, ranked_neighbor, sample_neighbor, slots, uniform_multiset

ASSIGN = ("sampled", "min_degree", "min_triangles", "exact", None)


@dataclass
class EstimateResult:
    per_rep: DataFrame  # rep, m, r, ell, sum_dr, hits, x_est
    ledger: PassLedger
    plan: SamplePlan
    stages: dict[str, DataFrame]

    def calls(self) -> tuple[int, int]:
        """How often the owner of a triangle was asked for, and distinct triangles among these calls, for which it was decided."""
        closed = self.stages["closed"]
        return closed.count(), closed.select("a", "b", "c").distinct().count()

    def median_of_means(self, groups: int = 1) -> DataFrame:
        return median_of_means(self.per_rep, groups)


def median_of_means(per_rep: DataFrame, groups: int) -> DataFrame:
    """One number: replicas are averaged in groups, and the middle average is taken."""
    means = per_rep.groupBy((F.col("rep") % groups).alias("g")).agg(F.avg("x_est").alias("mean"))
    return means.agg(F.round(F.percentile("mean", F.lit(0.5)), 6).alias("x_est"))


def _triangle(u: str, v: str, w: str) -> list:
    t = F.array_sort(F.array(u, v, w))
    return [F.get(t, F.lit(i)).alias(c) for i, c in enumerate("abc")]


def _six(edges: DataFrame, plan: SamplePlan, assign: str | None, degree_oracle: DataFrame | None, guard: SpaceGuard | None, neighbor: str, guesses: list[float] | None):
    """The passes; (per replica and guess: hits; the plan; the ledger; the kept tables)."""
    spark, ledger, stages = edges.sparkSession, PassLedger(edges, plan.n, guard), {}

    def keep(name: str, df: DataFrame) -> DataFrame:
        stages[name] = ledger.keep(name, df)
        return stages[name]

    sample = keep("sample", uniform_multiset(ledger.scan("sample"), plan.r, plan.m, plan.seed, plan.reps, plan.coin))
    ends = sample.select(F.explode(F.array("u", "v")).alias("x")).distinct()
    if degree_oracle is None:
        known = keep("degrees", degrees_of(probe_pass(ledger.scan("degrees"), ends, n=2 * ledger.kept["sample"])))
    else:
        known = degree_oracle.join(ends, "x", "left_semi")
        ledger.oracle_queries += ends.count()
    sample = keep("edges", with_edge_degree(sample, known).select("rep", "slot", "u", "v", "x", "y", "d_e"))
    sums = stored(sample.groupBy("rep").agg(F.sum("d_e").alias("sum_dr")), "sums")
    if plan.ell is None:
        plan = plan.with_degrees(int(sums.agg(F.coalesce(F.max("sum_dr"), F.lit(0))).first()[0]))
    picks = keep("picks", proportional_picks(sample, "d_e", ["slot"], slots(spark, plan.reps, plan.ell).withColumnRenamed("slot", "i"), plan.seed, "pick", plan.coin).drop("slot"))
    near = sample_neighbor if neighbor == "argmin" else ranked_neighbor
    chosen = keep("neighbors", picks.join(near(half_edges(ledger.scan("neighbors")), picks, plan.seed, plan.coin, ledger.kept["picks"]), ["rep", "i"]))
    pairs = chosen.where("w != y").select(F.least("y", "w").alias("p"), F.greatest("y", "w").alias("q")).distinct()
    third = chosen.select(F.col("w").alias("x")).distinct()
    probed = keep("closures", probe_pass(ledger.scan("closures"), third, pairs, 2 * ledger.kept["neighbors"]))
    hit = pairs_of(probed)
    closed = chosen.withColumns({"p": F.least("y", "w"), "q": F.greatest("y", "w")}).join(hit, ["p", "q"]).where("w != y").select("rep", "i", "u", "v", *_triangle("u", "v", "w"))
    closed = keep("closed", closed)
    if assign is not None:
        tri = keep("triangles", owners.remember(None, closed))
        everyone = degrees_of(probed).unionByName(known.select("x", "d")).distinct()
        if guesses is not None:
            memo = owners.assign_for_guesses(ledger, tri, everyone, plan, guesses)
        elif assign == "sampled":
            memo = owners.assign_sampled(ledger, tri, everyone, plan)
        elif assign == "min_degree":
            memo = owners.assign_by_degree(tri, everyone)
        elif assign == "min_triangles":
            memo = owners.assign_by_count(tri, edge_triangle_counts(ledger.scan("exact counts")))
        else:
            memo = owners.assign_exact(ledger.scan("exact counts"), plan.kappa, plan.eps, plan.t_guess, plan.m)
        memo = keep("memo", memo)
        closed = closed.join(memo, ["a", "b", "c"]).where("owner_u = u and owner_v = v")
    by = ["rep"] if guesses is None else ["guess", "rep"]
    return closed.groupBy(*by).agg(F.count(F.lit(1)).alias("hits")), sums, plan, ledger, stages


def six_pass(edges: DataFrame, plan: SamplePlan, assign: str | None = "sampled", degree_oracle: DataFrame | None = None, guard: SpaceGuard | None = None, neighbor: str = "argmin") -> EstimateResult:
    """With a degree oracle the second pass goes.  Between passes only written tables of sample size are kept.  neighbor: argmin draws by the
    least of coins tossed for all neighbours, rank by a drawn place.  The ablations min_triangles and exact count triangles of all edges beside the passes."""
    if assign not in ASSIGN or neighbor not in ("argmin", "rank"):
        raise ValueError(f"assign is one of {ASSIGN}, neighbor argmin or rank")
    hits, sums, plan, ledger, stages = _six(edges, plan, assign, degree_oracle, guard, neighbor, None)
    per = slots(edges.sparkSession, plan.reps, 1).select("rep").join(sums, "rep", "left").join(hits, "rep", "left").na.fill(0, ["sum_dr", "hits"])
    return EstimateResult(_estimates(per, plan, 1.0 if assign is not None else 3.0, ["rep"]), ledger, plan, stages)


def _estimates(per: DataFrame, plan: SamplePlan, share: float, by: list[str]) -> DataFrame:
    per = per.select(*by, F.lit(plan.m).cast("long").alias("m"), F.lit(plan.r).cast("long").alias("r"), F.lit(plan.ell).cast("long").alias("ell"), "sum_dr", "hits")
    return per.withColumn("x_est", F.round(F.col("m") / F.col("r") * F.col("sum_dr") * F.col("hits") / F.col("ell") / share, 6))


def without_guess(edges: DataFrame, plan: SamplePlan, guesses: list[float]) -> tuple[DataFrame, PassLedger]:
    """(guess, est, accepted) and the ledger: one set of six passes serves all guesses of the number of triangles, as a guess enters only through
    the degree cut of the owners.  The largest guess that its estimate supports is accepted."""
    spark = edges.sparkSession
    hits, sums, plan, ledger, _ = _six(edges, plan, "sampled", None, None, "argmin", guesses)
    grid = slots(spark, plan.reps, 1).select("rep").join(F.broadcast(spark.createDataFrame([(float(g),) for g in guesses], "guess double")))
    per = grid.join(sums, "rep", "left").join(hits, ["guess", "rep"], "left").na.fill(0, ["sum_dr", "hits"])
    means = _estimates(per, plan, 1.0, ["guess", "rep"]).groupBy("guess").agg(F.round(F.avg("x_est"), 6).alias("est"))
    best = means.where("est >= guess").agg(F.max("guess").alias("best"))
    return means.join(F.broadcast(best)).select("guess", "est", F.coalesce(F.col("guess") == F.col("best"), F.lit(False)).alias("accepted")), ledger


def oracle_estimate(edges: DataFrame, k: int, seed: int, assign: str | None = "min_degree", degree: DataFrame | None = None, coin: str = "md5", n: int = 2) -> EstimateResult:
    """k copies: an edge in proportion to its degree, a uniform neighbour of its low-degree end, 1 if they close a triangle that
    the edge owns; the degree sum times that.  The degree oracle is a table, made beside the passes where none is given; looking up both ends of
    every edge is 2m queries."""
    spark, ledger = edges.sparkSession, PassLedger(edges, n)
    degree = stored(degrees(edges), "oracle-degrees") if degree is None else degree
    e = stored(edge_degrees(ledger.scan("edges"), degree), "oracle-edges")
    m = e.count()
    ledger.oracle_queries = 2 * m
    sum_de = int(e.agg(F.coalesce(F.sum(F.col("d_e").cast("decimal(38,0)")), F.lit(0))).first()[0])
    wanted = slots(spark, 1, k).withColumnRenamed("slot", "i")
    picks = ledger.keep("picks", proportional_picks(e.withColumn("rep", F.lit(0)), "d_e", ["u", "v"], wanted, seed, "oracle", coin, groups=64))
    ledger.read["picks"] = 1  # the edges with their degrees stand for the first pass
    chosen = ledger.keep("neighbors", picks.join(sample_neighbor(half_edges(ledger.scan("neighbors")), picks, seed, coin, ledger.kept["picks"]), ["rep", "i"]))
    chosen = chosen.where("w != y").withColumns({"p": F.least("y", "w"), "q": F.greatest("y", "w")})
    hit = pairs_of(probe_pass(ledger.scan("closures"), chosen.select(F.col("w").alias("x")).limit(0), chosen.select("p", "q").distinct(), ledger.kept["neighbors"]))
    closed = ledger.keep("closed", chosen.join(hit, ["p", "q"]).select("rep", "i", "u", "v", *_triangle("u", "v", "w")))
    stages = {"closed": closed}
    if assign is not None:
        tri = owners.remember(None, closed)
        memo = owners.assign_by_degree(tri, degree) if assign == "min_degree" else owners.assign_by_count(tri, edge_triangle_counts(edges))
        closed = closed.join(memo, ["a", "b", "c"]).where("owner_u = u and owner_v = v")
    per = wanted.select("rep", "i").join(closed.select("rep", "i", F.lit(1).alias("hit")), ["rep", "i"], "left")
    share = 1.0 if assign is not None else 3.0
    per = per.select(F.col("i").cast("int").alias("rep"), F.coalesce("hit", F.lit(0)).cast("long").alias("hits"), F.lit(k).cast("long").alias("k"), F.lit(sum_de).cast("long").alias("sum_de"))
    return EstimateResult(per.withColumn("x_est", F.col("hits") * F.col("sum_de") / share), ledger, SamplePlan(m, n, 0, 0, 0.1, m, k, 0, seed), stages)


def good_sample(edges: DataFrame, sample: DataFrame, assigned: DataFrame, r: int, m: int, n: int, eps: float) -> DataFrame:
    """Whether a sample's degree sum is at most its mean times ln(n)/eps, and its assigned triangles are within (1 +- eps) of
    their mean."""
    import math

    e = edge_degrees(edges)
    per = assigned.where("owner_u is not null").groupBy(F.col("owner_u").alias("u"), F.col("owner_v").alias("v")).agg(F.count(F.lit(1)).alias("t"))
    rows = e.join(per, ["u", "v"], "left").na.fill(0, ["t"])
    whole = rows.agg(F.sum("d_e").alias("d_all"), F.sum("t").alias("t_all"))
    mine = sample.join(rows.select("u", "v", "d_e", "t"), ["u", "v"]).agg(F.sum("d_e").alias("d_r"), F.sum("t").alias("t_r"))
    fair = F.col("t_all") * r / m
    return mine.join(whole).select("d_r", "t_r", (F.col("d_r") <= F.col("d_all") * r / m * math.log(n) / eps).alias("good_dr"), ((F.col("t_r") >= fair * (1 - eps)) & (F.col("t_r") <= fair * (1 + eps))).alias("good_tr"))
