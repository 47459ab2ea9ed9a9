"""Exact triangle work.

Everything is joins on the edge relation.  The edge-wise search walks the neighbourhood of an edge's low-degree end, so the number of
wedge rows is the sum of edge degrees, at most 2 * m * degeneracy; enumeration orients edges from low to high degree.  Above JOIN_EDGES
triangles are found without moving wedges (closing).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.store import shared_root, stored, written
from ..sources.edges import half_edges
from . import closing, whole
from .classes import ROWS, Classes
from .passes import BROADCAST_KEYS

#: Up to so many edges wedges are rows of a join.
JOIN_EDGES = 300_000


def joined(edges: DataFrame) -> int | None:
    """None where wedges are joined, else the number of edges, too many for that (a count of a written table comes from its footers)."""
    m = edges.count()
    return m if m > JOIN_EDGES and closing.readable(shared_root(edges.sparkSession)) else None


def degrees(edges: DataFrame) -> DataFrame:
    return half_edges(edges).groupBy("x").agg(F.count(F.lit(1)).alias("d"))


def written_degrees(edges: DataFrame) -> DataFrame:
    """degrees() of a written table, whose count is at hand; above JOIN_EDGES in packs."""
    m = edges.count()
    return closing.degrees(edges, m) if m > JOIN_EDGES else degrees(edges)


def edge_degrees(edges: DataFrame, degree: DataFrame | None = None) -> DataFrame:
    """u, v, d_u, d_v, d_e, x (low-degree end; the second end on a tie), y."""
    degree = degrees(edges) if degree is None else degree
    out = edges.join(degree.select(F.col("x").alias("u"), F.col("d").alias("d_u")), "u").join(degree.select(F.col("x").alias("v"), F.col("d").alias("d_v")), "v")
    first = F.col("d_u") < F.col("d_v")
    return out.select("u", "v", "d_u", "d_v", F.least("d_u", "d_v").alias("d_e"), F.when(first, F.col("u")).otherwise(F.col("v")).alias("x"), F.when(first, F.col("v")).otherwise(F.col("u")).alias("y"))


def oriented(edges: DataFrame) -> DataFrame:
    """(p, q): from the end of lower (degree, id) to the other."""
    e = edge_degrees(edges)
    up = F.col("d_u") <= F.col("d_v")
    return e.select(F.when(up, F.col("u")).otherwise(F.col("v")).alias("p"), F.when(up, F.col("v")).otherwise(F.col("u")).alias("q"))


def triangles(edges: DataFrame) -> DataFrame:
    """a < b < c, each once."""
    if (m := joined(edges)) is not None:
        return closing.triangles(edges, m)
    o = oriented(edges)
    wedge = o.join(o.select("p", F.col("q").alias("w")), "p").where("q < w")
    closed = wedge.join(edges.select(F.col("u").alias("q"), F.col("v").alias("w")), ["q", "w"], "left_semi")
    t = F.array_sort(F.array("p", "q", "w"))
    return closed.select(*(F.get(t, F.lit(i)).alias(c) for i, c in enumerate("abc")))


def triangle_edges(t: DataFrame, *keep: str) -> DataFrame:
    """Rows (u, v) of each triangle's edges."""
    pairs = F.array(*(F.struct(F.col(p).alias("u"), F.col(q).alias("v")) for p, q in (("a", "b"), ("a", "c"), ("b", "c"))))
    return t.select(*keep, F.inline(pairs))


def edge_triangle_counts(edges: DataFrame) -> DataFrame:
    """u, v, d_e, t_inc: walk the smaller neighbourhood, look each vertex up in the larger."""
    if (m := joined(edges)) is not None:
        d = stored(written_degrees(edges), "degrees")
        if d.count() <= whole.VERTICES:
            return closing.edge_counts(edges, m, degree=d).select("u", "v", "d_e", "t_inc")
        counts = closing.edge_counts(edges, m).join(d.select(F.col("x").alias("u"), F.col("d").alias("d_u")), "u").join(d.select(F.col("x").alias("v"), F.col("d").alias("d_v")), "v")
        return counts.select("u", "v", F.least("d_u", "d_v").alias("d_e"), "t_inc")
    e = edge_degrees(edges)
    wedge = e.select("u", "v", "x", "y").join(half_edges(edges).select("x", F.col("nbr").alias("w")), "x").where("w != y")
    wedge = wedge.select("u", "v", F.least("y", "w").alias("p"), F.greatest("y", "w").alias("q"))
    hits = wedge.join(edges.select(F.col("u").alias("p"), F.col("v").alias("q")), ["p", "q"], "left_semi").groupBy("u", "v").agg(F.count(F.lit(1)).alias("t"))
    return e.select("u", "v", "d_e").join(hits, ["u", "v"], "left").select("u", "v", "d_e", F.coalesce("t", F.lit(0)).cast("long").alias("t_inc"))


def edge_triangles(edges: DataFrame) -> DataFrame:
    """u, v, t_inc: as edge_triangle_counts, without degrees."""
    m = joined(edges)
    return edge_triangle_counts(edges).select("u", "v", "t_inc") if m is None else closing.edge_counts(edges, m)


def count_triangles(edges: DataFrame, degree: DataFrame | None = None) -> DataFrame:
    """t in one row; degree: of all vertices, where it is at hand."""
    if (m := joined(edges)) is not None:
        degree = written(written_degrees(edges) if degree is None else degree, "degrees")
        if not whole.dense(n := degree.count(), m):
            return closing.count_triangles(edges, m, degree=degree)
        tasks = min(n, 2 * edges.sparkSession.sparkContext.defaultParallelism)
        files = written(edges, "dense").inputFiles()
        each = edges.sparkSession.range(0, tasks, 1, tasks).mapInArrow(whole.count_bits(degree.inputFiles(), files, tasks), "t long")
        return each.agg(F.coalesce(F.sum("t"), F.lit(0)).alias("t"))
    return triangles(edges).agg(F.count(F.lit(1)).alias("t"))


def count_by_intersection(edges: DataFrame) -> DataFrame:
    """Adjacency arrays of forward neighbours; for graphs of low degeneracy, where no array is long."""
    o = oriented(edges)
    forward = o.groupBy("p").agg(F.collect_set("q").alias("out"))
    pairs = o.join(forward, "p").join(forward.select(F.col("p").alias("q"), F.col("out").alias("out2")), "q")
    return pairs.agg(F.coalesce(F.sum(F.size(F.array_intersect("out", "out2")).cast("long")), F.lit(0)).alias("t"))


def count_bruteforce(edges: DataFrame) -> DataFrame:
    """Three-way self-join in id order, for fixtures."""
    ab = edges.select(F.col("u").alias("a"), F.col("v").alias("b"))
    bc = edges.select(F.col("u").alias("b"), F.col("v").alias("c"))
    ac = edges.select(F.col("u").alias("a"), F.col("v").alias("c"))
    return ab.join(bc, "b").join(ac, ["a", "c"]).agg(F.count(F.lit(1)).alias("t"))


def count_by_matrix(edges: DataFrame) -> DataFrame:
    """The sum of U^2 over the entries of U, a sixth of trace(A^3): U has an edge once, from its end of lower (degree, id), so a hub's row is short and
    its square is never made.  For fixtures."""
    o = stored(oriented(edges), "matrix")
    square = o.join(o.select(F.col("p").alias("q"), F.col("q").alias("w")), "q").groupBy("p", "w").agg(F.count(F.lit(1)).alias("ways"))
    closed = square.join(o.select("p", F.col("q").alias("w")), ["p", "w"])
    return closed.agg(F.coalesce(F.sum("ways"), F.lit(0)).alias("t"))


def vertex_triangles(edges: DataFrame) -> DataFrame:
    """v, t_v, d_v, cc: triangles, degree and clustering coefficient of every vertex."""
    t = triangles(edges).select(F.explode(F.array("a", "b", "c")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("t_v"))
    d = degrees(edges).select(F.col("x").alias("v"), F.col("d").alias("d_v"))
    out = d.join(t, "v", "left").select("v", F.coalesce("t_v", F.lit(0)).cast("long").alias("t_v"), "d_v")
    return out.withColumn("cc", F.when(F.col("d_v") > 1, F.round(F.col("t_v") * 2 / (F.col("d_v") * (F.col("d_v") - 1)), 9)).otherwise(0.0))


def summary(edges: DataFrame) -> DataFrame:
    """n, m, t, sum_de in one row: of a small graph in one task, of one whose degrees a task can hold without a join."""
    m = edges.count()
    if m <= JOIN_EDGES:
        return edges.select("u", "v").repartition(1).mapInArrow(whole.one_summary, whole.SUMMARY)
    if joined(edges) is not None:
        d = stored(written_degrees(edges), "degrees")
        if d.count() <= whole.VERTICES:
            e = edges.select("u", "v").mapInArrow(whole.edge_degrees(d.inputFiles()), "m long, sum_de long")
            e = e.agg(F.sum("m").alias("m"), F.sum(F.col("sum_de").cast("decimal(38,0)")).cast("long").alias("sum_de"))
            return d.agg(F.count(F.lit(1)).alias("n")).join(e).join(count_triangles(edges, d)).select("n", "m", "t", "sum_de")
    e = edge_degrees(edges).agg(F.count(F.lit(1)).alias("m"), F.coalesce(F.sum(F.col("d_e").cast("decimal(38,0)")), F.lit(0)).cast("long").alias("sum_de"))
    n = degrees(edges).agg(F.count(F.lit(1)).alias("n"))
    return n.join(e).join(count_triangles(edges)).select("n", "m", "t", "sum_de")


def cliques(edges: DataFrame, k: int) -> DataFrame:
    """Number of k-cliques, k >= 3: cliques among later neighbours of their first vertex, grown by one vertex a step; each new vertex is
    joined to the first by orientation and to the others by semi-joins."""
    o = stored(oriented(edges), "oriented")
    rows = o.withColumnRenamed("q", "q0")
    for i in range(1, k - 1):
        rows = rows.join(o.select("p", F.col("q").alias(f"q{i}")), "p").where(f"q{i - 1} < q{i}")
        for j in range(i):
            rows = rows.join(edges.select(F.col("u").alias(f"q{j}"), F.col("v").alias(f"q{i}")), [f"q{j}", f"q{i}"], "left_semi")
    return rows.agg(F.count(F.lit(1)).alias("cliques"))


def transitivity(edges: DataFrame) -> DataFrame:
    """t, wedges and 3t / wedges."""
    d = degrees(edges).agg(F.coalesce(F.sum((F.col("d") * (F.col("d") - 1) / 2).cast("decimal(38,0)")), F.lit(0)).cast("long").alias("wedges"))
    return d.join(count_triangles(edges)).select("t", "wedges", F.when(F.col("wedges") > 0, F.round(3 * F.col("t") / F.col("wedges"), 9)).otherwise(0.0).alias("transitivity"))


def group_summary(held: DataFrame, low: int = 64, most_classes: int = 4000) -> DataFrame:
    """n, m, t, sum_de of the graph that joins members of a common group, however large groups are; held: member, token.

    Members of the very same groups are neighbours of the same vertices, so they fold into one vertex with a weight.  Pairs of a group of up to `low` folded
    members are edges; those of larger groups are never made, but counted by classes.  low doubles until there are at most most_classes, so what it is
    changes the work and not the counts.  Edges are thus of three kinds, each pair of one: inside a vertex, by a large group (h), by small groups only (l)."""
    spark = held.sparkSession
    own = held.where("member is not null and token is not null").select("member", "token").distinct()
    shared = stored(own.groupBy("token").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("token"), "shared-groups")
    inside = stored(own.join(shared, "token").select("member", "token"), "group-members")
    kinds = inside.groupBy("member").agg(F.sha2(F.array_join(F.array_sort(F.collect_list(F.sha2(F.col("token").cast("string"), 256))), ""), 256).alias("kind"))
    folded = stored(kinds.groupBy("kind").agg(F.count(F.lit(1)).alias("w"), F.min("member").alias("id")).select("id", "w"), "folded")
    n_folded = folded.count()
    short = F.broadcast if n_folded <= BROADCAST_KEYS else (lambda x: x)
    rows = inside.withColumnRenamed("member", "id").join(short(folded.select("id")), "id", "left_semi")
    sizes = rows.groupBy("token").agg(F.count(F.lit(1)).alias("n")).where("n > 1").withColumn("g", F.monotonically_increasing_id())
    rows = stored(rows.join(stored(sizes, "group-sizes"), "token").select("g", "n", "id"), "folded-members")
    while True:
        signed = stored(rows.where(F.col("n") > low).groupBy("id").agg(F.array_sort(F.collect_list("g")).alias("signs")).join(folded, "id"), "signs")
        if signed.select("signs").distinct().count() <= most_classes:
            break
        low *= 2
    known = sorted((list(r.signs), r.n) for r in signed.groupBy("signs").agg(F.sum("w").alias("n")).collect())
    own_class = Classes([s for s, _ in known], [n for _, n in known])
    around = own_class.around()
    table = spark.createDataFrame([(s, c, a) for c, ((s, _), a) in enumerate(zip(known, around, strict=True))], "signs array<long>, c long, around_h long")
    classed = signed.join(F.broadcast(table), "signs").select("id", "c", "around_h")
    vertices = stored(folded.join(short(classed), "id", "left").select("id", "w", F.coalesce("c", F.lit(-1)).alias("c"), (F.coalesce("around_h", "w") - 1).alias("base")), "folded-classes")

    small = rows.where(F.col("n") <= low).select("g", "id")
    pairs = small.withColumnRenamed("id", "u").join(small.withColumnRenamed("id", "v"), "g").where("u < v").select("u", "v").distinct()
    named = lambda x: short(vertices.select(F.col("id").alias(x), F.col("w").alias(f"w{x}"), F.col("c").alias(f"c{x}")))
    light = pairs.join(named("u"), "u").join(named("v"), "v").select("u", "v", "wu", "wv", "cu", "cv")
    light = stored(light.mapInArrow(own_class.apart(), light.schema), "light-edges")
    half = light.select(F.inline(F.array(*(F.struct(F.col(x).alias("z"), F.col(f"w{x}").alias("wz"), F.col(f"w{y}").alias("w"), F.col(f"c{y}").alias("c")) for x, y in ("uv", "vu")))))
    degree = half.groupBy(F.col("z").alias("id")).agg(F.sum("w").alias("more"))
    degree = stored(vertices.join(degree, "id", "left").select("id", "w", "c", (F.col("base") + F.coalesce("more", F.lit(0))).alias("d")), "folded-degrees")

    big = lambda c: F.coalesce(F.sum(c.cast("decimal(38,0)")), F.lit(0)).cast("decimal(38,0)")
    total = lambda df, *of: [int(x) for x in df.agg(*(big(c) for c in of)).first()]
    w, two = F.col("w"), F.col("w") * (F.col("w") - 1) / 2
    (n,) = total(degree, w)
    m, t, s = total(degree.where("c < 0"), two, two * (F.col("w") - 2) / 3, two * F.col("d"))
    (across,) = total(light, F.col("wu") * F.col("wv"))
    ends = light.join(short(degree.select(F.col("id").alias("u"), F.col("d").alias("du"))), "u").join(short(degree.select(F.col("id").alias("v"), F.col("d").alias("dv"))), "v")
    m, s = m + across, s + total(ends, F.col("wu") * F.col("wv") * F.least("du", "dv"))[0]
    thrice = triangles(light.select("u", "v"))
    for c in "abc":
        thrice = thrice.join(short(folded.select(F.col("id").alias(c), F.col("w").alias(f"w{c}"))), c)
    t += total(thrice, F.col("wa") * F.col("wb") * F.col("wc"))[0] + total(half.where("c < 0"), F.col("wz") * two)[0]
    if known:
        once, twice = sum(n for _, n in known), sum(n * a for (_, n), a in zip(known, around, strict=True))
        m += (twice - once) // 2
        lined = light.where("cu >= 0 and cv >= 0").groupBy(F.least("cu", "cv").alias("c"), F.greatest("cu", "cv").alias("c2")).agg(F.sum(F.col("wu") * F.col("wv")).alias("s"))
        lined = lined.unionByName(spark.range(len(known)).select(F.col("id").alias("c"), F.lit(-1).cast("long").alias("c2"), F.lit(0).cast("long").alias("s")))
        blocks = -(-len(known) // ROWS)
        triples, wedges = total(lined.repartition(blocks, F.expr(f"c div {ROWS}")).mapInArrow(own_class.squared(), "hhh string, hhl string"), F.col("hhh"), F.col("hhl"))
        mixed = half.where("c >= 0").groupBy("z", "wz", "c").agg(F.sum("w").alias("h")).repartition("z")
        t += (triples - 3 * twice + 2 * once) // 6 + wedges + total(mixed.mapInArrow(own_class.between(), "hll string"), F.col("hll"))[0]
        alike = degree.where("c >= 0").groupBy("c", "d").agg(F.sum("w").alias("n")).repartition(1)
        s += total(alike.mapInArrow(own_class.least(), "s string"), F.col("s"))[0]
    return spark.range(1).select(*(F.lit(x).cast("long").alias(k) for k, x in (("n", n), ("m", m), ("t", t), ("sum_de", s))))
