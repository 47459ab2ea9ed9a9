"""Graph views of the tables.  Ids of different kinds are kept apart by their remainder."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..plans.packed import PACKS, TOGETHER, moved, opened, packs, place
from .edges import canonical


def _t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def co_members(df: DataFrame, group: list[str], member: str) -> DataFrame:
    """Pairs of members of one group; groups are small (an order, an hour), so the self-join stays near its input."""
    a = df.select(*group, F.col(member).alias("a")).distinct()
    b = a.withColumnRenamed("a", "b")
    return canonical(a.join(b, group).where("a < b"), "a", "b")


#: Rows of a table for each place that groups, and then pairs, are dealt to.
DEALT = 250_000


def _pairs(n: int, most: int = TOGETHER):
    """Rows (a group's numbers, member) of a place -> packs of its pairs, each for the place of its first end."""

    def then(_, columns: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        order = np.lexsort(columns[::-1])
        *g, a = (c[order] for c in columns)
        other = np.r_[True, np.any([x[1:] != x[:-1] for x in g], axis=0)]
        once = other | np.r_[True, a[1:] != a[:-1]]
        a, starts = a[once], np.flatnonzero(other[once])
        sizes = np.diff(np.r_[starts, len(a)])
        later = np.repeat(starts + sizes, sizes) - np.arange(len(a)) - 1
        upto, k = np.cumsum(later), 0
        while k < len(a):
            stop = max(k + 1, int(np.searchsorted(upto, (upto[k - 1] if k else 0) + most, "right")))
            many = later[k:stop]
            i = np.repeat(np.arange(k, stop), many)
            j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(many) - many, many)
            yield from packs(place(a[i], n), [a[i], a[j]])
            k = stop

    return then


def _edges(_, columns: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
    """Pairs of a place, each once, in order."""
    u, v = columns
    order = np.lexsort((v, u))
    u, v = u[order], v[order]
    once = np.r_[True, (u[1:] != u[:-1]) | (v[1:] != v[:-1])]
    u, v = u[once], v[once]
    for k in range(0, len(u), 100_000):
        yield pa.RecordBatch.from_arrays([pa.array(u[k : k + 100_000]), pa.array(v[k : k + 100_000])], names=["u", "v"])


def co_members_packed(df: DataFrame, group: str | list[str], member: str, pairs: int = 0) -> DataFrame:
    """co_members() by whole numbers: rows cross the network once and pairs, some `pairs` where groups are large, once, both in packs; edges leave in order."""
    group = [group] if isinstance(group, str) else group
    n = 1 + max(df.count() // DEALT, pairs // TOGETHER)
    rows = df.where(" and ".join(f"{c} is not null" for c in (*group, member)))
    rows = rows.select(F.pmod(F.xxhash64(*group), F.lit(n)).cast("int").alias("b"), *(F.col(c).cast("long").alias(f"g{k}") for k, c in enumerate(group)), F.col(member).cast("long").alias("a"))
    return opened(moved(rows, n, _pairs(n), PACKS), n, _edges, "u long, v long")


def canonical_packed(df: DataFrame, a: Column, b: Column, rows: int) -> DataFrame:
    """canonical() of about so many rows: pairs cross the network in packs, and edges leave in order."""
    n = 1 + rows // DEALT
    pairs = canonical(df, a, b, distinct=False)
    return moved(pairs.select(F.pmod(F.xxhash64("u"), F.lit(n)).cast("int").alias("b"), "u", "v"), n, _edges, "u long, v long")


def capped_groups(df: DataFrame, member: str, token: str, low: int, high: int) -> DataFrame:
    """Pairs of members that share a token held by low..high members."""
    held = df.select(F.col(member).alias("member"), F.col(token).alias("token")).where("token is not null").distinct()
    fit = held.groupBy("token").count().where(F.col("count").between(low, high)).select("token")
    return co_members(held.join(fit, "token"), ["token"], "member")


def corners(df: DataFrame, a: str, b: str, c: str, rows: int = 0) -> DataFrame:
    """The three edges of each of some `rows` rows' triangles, packed where rows are many."""
    edges = F.array(*(F.struct(F.expr(x).cast("long").alias("p"), F.expr(y).cast("long").alias("q")) for x, y in ((a, b), (b, c), (a, c))))
    pairs = df.select(F.inline(edges))
    return canonical(pairs, "p", "q") if rows <= DEALT else canonical_packed(pairs, F.col("p"), F.col("q"), 3 * rows)


def g_copurchase(spark, sf):
    return co_members_packed(_t(spark, sf, "lineitem"), "l_orderkey", "l_partkey")


def g_cosupply(spark, sf):
    return co_members_packed(_t(spark, sf, "lineitem"), "l_orderkey", "l_suppkey")


def g_part_supp(spark, sf):
    rows = _t(spark, sf, "lineitem")
    return canonical_packed(rows, F.expr("2 * l_partkey"), F.expr("2 * l_suppkey + 1"), rows.count())


def g_order_part_supp(spark, sf):
    rows = _t(spark, sf, "lineitem")
    return corners(rows, "3 * l_orderkey", "3 * l_partkey + 1", "3 * l_suppkey + 2", rows.count())


def g_cust_part_supp(spark, sf):
    rows = _t(spark, sf, "lineitem").join(_t(spark, sf, "orders"), F.expr("l_orderkey = o_orderkey"))
    return corners(rows, "3 * o_custkey", "3 * l_partkey + 1", "3 * l_suppkey + 2", _t(spark, sf, "lineitem").count())


def g_coactive(spark, sf):
    following = F.lead("user_id").over(Window.orderBy("ts", "event_id"))
    return canonical(_t(spark, sf, "events").select("user_id", following.alias("next")), "user_id", "next")


def g_hour_type(spark, sf):
    rows = _t(spark, sf, "events").select(F.date_trunc("hour", "ts").alias("hour"), "event_type", "user_id")
    types = rows.select("event_type").distinct().withColumn("type", F.dense_rank().over(Window.orderBy("event_type")))
    rows = rows.join(types, "event_type").select(F.unix_micros(F.col("hour").cast("timestamp")).alias("hour"), "type", "user_id")
    pairs = rows.groupBy("hour", "type").agg(F.count(F.lit(1)).alias("n")).agg(F.sum(F.expr("n * (n - 1) div 2"))).first()[0] or 0
    return co_members_packed(rows, ["hour", "type"], "user_id", pairs)


def _geo(people: DataFrame, spark, sf, key: str, nation: str):
    rows = people.join(_t(spark, sf, "nation"), F.col(nation) == F.col("n_nationkey"))
    return corners(rows, f"4 * {key}", "4 * n_nationkey + 1", "4 * n_regionkey + 2")


def g_geo(spark, sf):
    return _geo(_t(spark, sf, "customer"), spark, sf, "c_custkey", "c_nationkey")


def g_geo_supp(spark, sf):
    return _geo(_t(spark, sf, "supplier"), spark, sf, "s_suppkey", "s_nationkey")


def g_wheel(spark, sf):
    """A rim of all customers in key order and a hub."""
    ranked = _t(spark, sf, "customer").select(F.row_number().over(Window.orderBy("c_custkey")).alias("k"), F.count(F.lit(1)).over(Window.partitionBy()).alias("n"))
    spokes = F.array(F.struct(F.lit(0).alias("p"), F.col("k").alias("q")), F.struct(F.col("k").alias("p"), (F.col("k") % F.col("n") + 1).alias("q")))
    return canonical(ranked.select(F.inline(spokes)), "p", "q")


def g_book(spark, sf):
    """Two spine vertices and a page for each part."""
    pages = _t(spark, sf, "part").select((F.row_number().over(Window.orderBy("p_partkey")) + 1).alias("k"))
    spine = spark.range(1).select(F.lit(0).alias("p"), F.lit(1).alias("q"))
    return canonical(pages.select(F.inline(F.array(*(F.struct(F.lit(i).alias("p"), F.col("k").alias("q")) for i in (0, 1))))).unionByName(spine), "p", "q")


def g_pages(spark, sf):
    hrefs = _t(spark, sf, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="/([^"]*)"'), F.lit(1))).alias("token"))
    return capped_groups(hrefs, "page_id", "token", 1, 50)


def document_lines(docs: DataFrame) -> DataFrame:
    """(doc_id, token): lines of more than 20 characters by their md5."""
    lines = docs.select("doc_id", F.explode(F.split("text", "\n", -1)).alias("line")).where(F.char_length("line") > 20)
    return lines.select("doc_id", F.md5("line").alias("token"))


def g_docs(spark, sf):
    return capped_groups(document_lines(_t(spark, sf, "documents")), "doc_id", "token", 2, 60)


def g_docs_labelled(spark, sf):
    docs = _t(spark, sf, "documents").join(_t(spark, sf, "labels").select("doc_id"), "doc_id", "left_semi")
    return capped_groups(document_lines(docs), "doc_id", "token", 2, 60)


def g_conv(spark, sf):
    first = F.get(F.split(F.lower("text"), " ", -1), F.lit(0))
    return capped_groups(_t(spark, sf, "conversations").where("role = 'user'").select("conv_id", first.alias("token")), "conv_id", "token", 2, 60)


def g_doc_bench(spark, sf):
    items = _t(spark, sf, "benchmark").select(F.col("item_id").alias("doc_id"), "text")
    shared = document_lines(_t(spark, sf, "documents")).join(document_lines(items).withColumnRenamed("doc_id", "item_id"), "token")
    return canonical(shared, F.expr("2 * doc_id"), F.expr("2 * item_id + 1"))


#: Vectors in a block; blocks meet in pairs.
BLOCK = 1024


def _sequential(x: np.ndarray, y: np.ndarray) -> float:
    total = 0.0
    for p, q in zip(x.tolist(), y.tolist(), strict=True):
        total += p * q
    return total


def _millionths(cos: np.ndarray, i: np.ndarray, j: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """cos of vectors x[i] and y[j] in millionths, halves away from zero; next to a half the sums are taken one by one, as in SQL."""
    scaled = np.abs(cos) * 1e6
    out = np.floor(scaled + 0.5)
    for k in np.flatnonzero(np.abs(scaled - np.floor(scaled) - 0.5) < 1e-6):
        p, q = x[i[k]], y[j[k]]
        one = _sequential(p, q) / math.sqrt(_sequential(p, p)) / math.sqrt(_sequential(q, q))
        out[k] = int((abs(Decimal(repr(one))) * 1_000_000).to_integral_value(ROUND_HALF_UP))
    return np.where(cos < 0, -out, out).astype(np.int64)


def _vectors(ids: pa.Scalar, vectors: pa.Scalar) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(length, ids, vectors) of a block, by length."""
    ids, held = ids.values.to_numpy(zero_copy_only=False), vectors.values
    lengths, flat = np.diff(held.offsets.to_numpy()), held.flatten().to_numpy(zero_copy_only=False)
    first = np.cumsum(lengths) - lengths
    for n in np.unique(lengths[lengths > 0]).tolist():
        own = np.flatnonzero(lengths == n)
        yield n, ids[own], flat[first[own][:, None] + np.arange(n)].astype(np.float64)


def _compared(least: int | None, best: int):
    """Pairs of blocks -> (a, b, c): pairs a <> b of cosine c millionths, at least `least`, or else those that may be among the best of a in the block of b."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in range(batch.num_rows):
                one, other = list(_vectors(batch.column(0)[row], batch.column(1)[row])), list(_vectors(batch.column(2)[row], batch.column(3)[row]))
                for n, a, x in one:
                    for b, y in ((b, y) for m, b, y in other if m == n):
                        with np.errstate(divide="ignore", invalid="ignore"):
                            cos = x @ y.T / np.linalg.norm(x, axis=1)[:, None] / np.linalg.norm(y, axis=1)[None]
                        cos[~np.isfinite(cos) | (a[:, None] == b[None])] = -np.inf
                        low = (least - 1) / 1e6
                        if best:
                            low = np.partition(cos, -best, axis=1)[:, -best, None] - 2e-6 if len(b) > best else -2
                        i, j = np.nonzero((cos >= low) & np.isfinite(cos))
                        c = _millionths(cos[i, j], i, j, x, y)
                        keep = np.ones(len(c), bool) if best else c >= least
                        for k in range(0, len(c), 200_000):
                            part = slice(k, k + 200_000)
                            yield pa.RecordBatch.from_arrays([pa.array(z[part][keep[part]]) for z in (a[i], b[j], c)], names=["a", "b", "c"])

    return run


def _cosines(spark, sf, least: int = 0, best: int = 0) -> DataFrame:
    """(a, b, c): cosines in millionths of pairs of vectors, both ways, at least `least`, or else candidates for the `best` of each a."""
    e = _t(spark, sf, "embeddings").where("vec_id is not null and embedding is not null").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("x"))
    n = 1 + e.count() // BLOCK
    blocks = e.groupBy(F.pmod(F.xxhash64("id"), F.lit(n)).alias("k")).agg(F.collect_list(F.struct("id", "x")).alias("held")).select("k", F.col("held.id").alias("ids"), F.col("held.x").alias("xs"))
    a, b = blocks.select(F.col("ids").alias("ia"), F.col("xs").alias("xa"), F.col("k").alias("ka")), blocks.select(F.col("ids").alias("ib"), F.col("xs").alias("xb"), F.col("k").alias("kb"))
    met = spark.range(n).select(F.col("id").alias("ka")).join(spark.range(n).select(F.col("id").alias("kb")))
    met = met.join(a, "ka").join(b, "kb").repartition(min(n * n, 200), "ka", "kb")
    return met.select("ia", "xa", "ib", "xb").mapInArrow(_compared(least, best), "a long, b long, c long")


def g_vec(spark, sf):
    """Vectors of cosine at least 0.35; an all-pairs view of a small table, to have a graph with few triangles."""
    return canonical(_cosines(spark, sf, least=350_000).where("a < b"), "a", "b")


def g_knn(spark, sf):
    """Union of the 10-nearest lists."""
    pairs = _cosines(spark, sf, best=10)
    near = pairs.withColumn("place", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("c"), "b"))).where("place <= 10")
    return canonical(near, "a", "b")


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (g_copurchase, g_cosupply, g_part_supp, g_order_part_supp, g_cust_part_supp, g_coactive, g_hour_type, g_geo, g_geo_supp, g_wheel, g_book, g_pages, g_docs, g_docs_labelled, g_conv, g_doc_bench, g_vec, g_knn)
}
