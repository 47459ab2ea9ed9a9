"""Which of its edges owns a triangle.

The sampled rule estimates for each edge of a triangle how many triangles hold it, from s sampled neighbours of its low-degree end; the
edge with the least estimate owns the triangle, unless even that is too large.  Estimates are compared as integers, count times d_e over
the common s.  Coins are keyed by edge, so an edge has one estimate in a run and an owner never depends on who asks; decisions are made
once for each distinct triangle.
"""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.ledger import PassLedger
from ..plans.params import SamplePlan
from ..plans.store import stored, written
from ..sources.edges import half_edges
from . import whole
from .exact import edge_triangle_counts, joined, triangle_edges, triangles
from .passes import pairs_of, probe_pass, watched, with_edge_degree
from .sampling import bottom_neighbors, drawn_neighbors

ABC = ["a", "b", "c"]


def _owner(rows: DataFrame, count: Column, most: Column | float, by: tuple[str, ...] = ()) -> DataFrame:
    """rows a, b, c, u, v: the owner is the edge of least (count, u, v); null counts are infinite."""
    best = rows.withColumn("t", count).groupBy(*by, *ABC).agg(F.min(F.when(F.col("t").isNotNull(), F.struct("t", "u", "v"))).alias("o"))
    own = F.when(F.col("o.t") <= most, F.col("o"))
    return best.select(*by, *ABC, own["u"].alias("owner_u"), own["v"].alias("owner_v"))


def asked(tri: DataFrame, degree: DataFrame, cut: float) -> tuple[DataFrame, DataFrame]:
    """tri (distinct a, b, c) -> (rows: a, b, c and each edge with its degree; targets: the edges that may own, u, v, x, y, d_e)."""
    rows = with_edge_degree(triangle_edges(tri, *ABC), degree)
    return rows, rows.where(F.col("d_e") <= cut).select("u", "v", "x", "y", "d_e").distinct()


def closing_pairs(drawn: DataFrame) -> DataFrame:
    """Drawn neighbours with the pair (p, q) that would close a triangle."""
    return drawn.where("w != y").withColumns({"p": F.least("y", "w"), "q": F.greatest("y", "w")})


def estimated(targets: DataFrame, drawn: DataFrame, hit: DataFrame, plan: SamplePlan) -> DataFrame:
    """(u, v, scaled): s times the estimate of how many triangles hold each target, an integer."""
    # a whole neighbourhood counts each neighbour s times, a sample counts draws times d_e: both are estimates times s
    weight = F.when(F.lit(plan.exhaustive) & (F.col("d_e") <= plan.s), F.col("times")).otherwise(F.col("times") * F.col("d_e"))
    counted = drawn.join(hit, ["p", "q"]).groupBy("u", "v").agg(F.sum(weight).alias("scaled"))
    return targets.select("u", "v").join(counted, ["u", "v"], "left").select("u", "v", F.coalesce("scaled", F.lit(0)).alias("scaled"))


def _two_passes(ledger: PassLedger, targets: DataFrame, degree: DataFrame, plan: SamplePlan) -> DataFrame:
    ranked = bottom_neighbors(half_edges(ledger.scan("owner neighbours")), targets, plan.s, plan.seed, plan.coin, ledger.kept["owner targets"])
    drawn = ledger.keep("owner draws", closing_pairs(drawn_neighbors(ranked, targets, plan.s, plan.seed, plan.coin, plan.exhaustive)))
    hit = ledger.keep("owner hits", pairs_of(probe_pass(ledger.scan("owner closures"), degree.where("false").select("x"), drawn.select("p", "q"), ledger.kept["owner draws"])))
    return estimated(targets, drawn, hit, plan)


def assign_sampled(ledger: PassLedger, tri: DataFrame, degree: DataFrame, plan: SamplePlan) -> DataFrame:
    """tri (distinct a, b, c) -> (a, b, c, owner_u, owner_v); two passes for all triangles together.  degree: of all their vertices."""
    rows, targets = asked(tri, degree, plan.degree_cut)
    targets = ledger.keep("owner targets", targets)
    return decided(rows, _two_passes(ledger, targets, degree, plan), plan)


def decided(rows: DataFrame, known: DataFrame, plan: SamplePlan) -> DataFrame:
    return _owner(rows.select(*ABC, "u", "v").join(known, ["u", "v"], "left"), F.col("scaled"), plan.owner_threshold * plan.s)


def assign_for_guesses(ledger: PassLedger, tri: DataFrame, degree: DataFrame, plan: SamplePlan, guesses: list[float]) -> DataFrame:
    """(guess, a, b, c, owner_u, owner_v): the same two passes for several guesses of the number of triangles, which differ in their degree cut only."""
    cuts = [(g, replace(plan, t_guess=g).degree_cut) for g in guesses]
    rows, targets = asked(tri, degree, max(c for _, c in cuts))
    targets = ledger.keep("owner targets", targets)
    known = _two_passes(ledger, targets, degree, plan)
    each = rows.join(known, ["u", "v"], "left").join(F.broadcast(rows.sparkSession.createDataFrame(cuts, "guess double, cut double")))
    return _owner(each, F.when(F.col("d_e") <= F.col("cut"), F.col("scaled")), plan.owner_threshold * plan.s, ("guess",))


def assign_by_degree(tri: DataFrame, degree: DataFrame) -> DataFrame:
    """The edge of least degree owns; ties go to the lesser edge."""
    return _owner(with_edge_degree(triangle_edges(tri, *ABC), degree), F.col("d_e"), float("inf"))


def assign_by_count(tri: DataFrame, counts: DataFrame) -> DataFrame:
    """The edge in fewest triangles owns (exact)."""
    return _owner(triangle_edges(tri, *ABC).join(counts.select("u", "v", "t_inc"), ["u", "v"]), F.col("t_inc"), float("inf"))


def assign_exact(edges: DataFrame, kappa: int, eps: float, t: float, m: int) -> DataFrame:
    """The sampled rule with true counts: same degree cut, same bound on the owner's count, for all triangles."""
    counts = edge_triangle_counts(edges)
    allowed = F.when(F.col("d_e") <= m * kappa**2 / (eps**2 * t) if t else F.lit(True), F.col("t_inc"))
    return _owner(triangle_edges(triangles(edges), *ABC).join(counts, ["u", "v"]), allowed, kappa / (2 * eps))


def exact_quality(edges: DataFrame, kappa: int, epss: list[float], t: float, m: int) -> DataFrame:
    """eps and quality() of assign_exact() for several eps: they differ in the degree cut and the bound only, so triangles and counts are found once."""
    counts = stored(edge_triangle_counts(edges), "counts")
    rows = triangle_edges(triangles(edges), *ABC).join(counts, ["u", "v"])
    each = edges.sparkSession.createDataFrame([(float(x), float(m * kappa**2 / (x**2 * t)) if t else math.inf, kappa / (2 * x)) for x in epss], "eps double, cut double, most double")
    best = rows.join(F.broadcast(each)).groupBy("eps", "most", *ABC).agg(F.min(F.when(F.col("d_e") <= F.col("cut"), F.struct("t_inc", "u", "v"))).alias("o"))
    own = F.when(F.col("o.t_inc") <= F.col("most"), F.col("o"))
    per = best.select("eps", own["u"].alias("owner_u"), own["v"].alias("owner_v")).groupBy("eps", "owner_u", "owner_v").agg(F.count(F.lit(1)).alias("n"))
    owned = F.when(F.col("owner_u").isNotNull(), F.col("n"))
    per = per.groupBy("eps").agg(F.sum("n").alias("triangles"), F.sum(owned).alias("assigned"), F.max(owned).alias("max_assigned"), F.sum(owned * owned).alias("sum_squares"))
    out = each.select("eps").join(per, "eps", "left").na.fill(0, ["triangles", "assigned", "max_assigned", "sum_squares"])
    return stored(out, "quality")


def quality(assigned: DataFrame) -> DataFrame:
    """triangles, assigned, max_assigned, sum of squares over owners."""
    per = assigned.where("owner_u is not null").groupBy("owner_u", "owner_v").agg(F.count(F.lit(1)).alias("t"))
    per = per.agg(F.coalesce(F.sum("t"), F.lit(0)).alias("assigned"), F.coalesce(F.max("t"), F.lit(0)).alias("max_assigned"), F.coalesce(F.sum(F.col("t") * F.col("t")), F.lit(0)).alias("sum_squares"))
    return assigned.agg(F.count(F.lit(1)).alias("triangles")).join(per)


def is_owner(assigned: DataFrame, asked: DataFrame) -> DataFrame:
    """asked: a, b, c, u, v -> and owned."""
    own = assigned.select(*ABC, "owner_u", "owner_v")
    return asked.join(own, ABC, "left").select(*ABC, "u", "v", F.coalesce((F.col("owner_u") == F.col("u")) & (F.col("owner_v") == F.col("v")), F.lit(False)).alias("owned"))


def remember(memo: DataFrame | None, tri: DataFrame) -> DataFrame:
    """The triangles that have no decision yet."""
    fresh = tri.select(*ABC).distinct()
    return fresh if memo is None else fresh.join(memo.select(*ABC), ABC, "left_anti")


def heavy_edges(counts: DataFrame, kappa: int, eps: float) -> DataFrame:
    return counts.where(F.col("t_inc") > kappa / eps).select("u", "v", "t_inc")


def costly_edges(counts: DataFrame, kappa: int, eps: float, m: int, t: float) -> DataFrame:
    """d_e / t_inc above m * kappa / (eps * t), multiplied out since t_inc may be 0."""
    return counts.where(F.col("d_e") * (eps * t) > F.col("t_inc") * float(m * kappa)).select("u", "v", "d_e", "t_inc")


def triangles_by_edges(edges: DataFrame, marked: DataFrame, every: bool) -> DataFrame:
    """Triangles of which every edge (or at least one) is marked."""
    if not every and joined(edges) is not None and marked.count() <= whole.VERTICES:  # tasks hold the marked edges
        files = written(marked.select("u", "v"), "marked").inputFiles()
        return triangles(edges).mapInArrow(whole.with_marked(files), "a long, b long, c long")
    if not every:  # only edges that may be marked leave the scan of triangles
        return watched(triangle_edges(triangles(edges), *ABC), marked.select("u", "v"), ["u", "v"]).select(*ABC).distinct()
    rows = triangle_edges(triangles(edges), *ABC).join(marked.select("u", "v", F.lit(True).alias("mark")), ["u", "v"], "left").withColumn("mark", F.coalesce("mark", F.lit(False)))
    return rows.groupBy(*ABC).agg((F.bool_and if every else F.bool_or)("mark").alias("mark")).where("mark").select(*ABC)


