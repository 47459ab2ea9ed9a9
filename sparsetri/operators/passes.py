"""Passes over the edges: degrees and closures by one scan, with watch lists as the small side."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


BROADCAST_KEYS = 500_000  # a watch list up to this goes to all tasks; its rows are some 50 bytes
SIEVE_BITS = 1 << 30  # no sieve is larger than 128 MB
BLOCK = 1 << 16  # bits in a row of a sieve


def sieved(rows: DataFrame, watch: DataFrame, on: list[str], n: int, most_bits: int = SIEVE_BITS) -> DataFrame:
    """The rows whose key may be among n watched ones: all that are, and of the others about one in sixteen while 16 bits a key fit into most_bits.

    Two bytes a key go to all tasks, a fraction of the list itself, so that what is not watched leaves in the scan."""
    blocks = max(1, min(16 * n, most_bits) // BLOCK)
    at = F.pmod(F.xxhash64(*on), F.lit(blocks * BLOCK))
    words = watch.select(at.alias("at")).groupBy(F.expr("at div 64").alias("word")).agg(F.bit_or(F.expr("shiftleft(1L, cast(at % 64 as int))")).alias("bits"))
    words = rows.sparkSession.range(blocks * BLOCK // 64).withColumnRenamed("id", "word").join(words, "word", "left").na.fill(0, ["bits"])
    sieve = words.groupBy(F.expr(f"word div {BLOCK // 64}").alias("block")).agg(F.sort_array(F.collect_list(F.struct("word", "bits")))["bits"].alias("held"))
    marked = rows.withColumn("sieve_at", at).withColumn("block", F.expr(f"sieve_at div {BLOCK}")).join(F.broadcast(sieve), "block")
    hit = F.expr(f"shiftright(get(held, cast(sieve_at % {BLOCK} div 64 as int)), cast(sieve_at % 64 as int)) & 1") == 1
    return marked.where(hit).drop("sieve_at", "block", "held")


def watched(rows: DataFrame, watch: DataFrame, on: list[str], n: int | None = None, most: int = BROADCAST_KEYS) -> DataFrame:
    """rows joined with a watch list of at most n rows (counted where not given): sent to all tasks up to `most`, beyond that by a shuffle of what passes a sieve."""
    n = watch.count() if n is None else n
    return rows.join(F.broadcast(watch), on) if n <= most else sieved(rows, watch, on, n).join(watch, on)


def probe_pass(edges: DataFrame, vertices: DataFrame, pairs: DataFrame | None = None, n: int | None = None, most: int = BROADCAST_KEYS) -> DataFrame:
    """(kind, a, b, n): degrees of watched vertices (kind V, b = -1) and presence of watched pairs (kind P), from one scan.

    Every edge emits two vertex keys and its own key.  Up to `most` watched keys (n is their number or a bound of it) the list goes to all tasks and counts
    combine map-side; beyond it keys pass a sieve, are counted map-side and meet the list by key.  Hubs cost one row a task either way, and of the
    edge relation only what passes the sieve crosses the network."""
    watch = vertices.select(F.lit("V").alias("kind"), F.col("x").alias("a"), F.lit(-1).cast("long").alias("b"))
    keys = [F.struct(F.lit("V").alias("kind"), F.col(c).alias("a"), F.lit(-1).cast("long").alias("b")) for c in "uv"]
    if pairs is not None:
        watch = watch.unionByName(pairs.select(F.lit("P").alias("kind"), F.col("p").alias("a"), F.col("q").alias("b")))
        keys.append(F.struct(F.lit("P").alias("kind"), F.col("u").alias("a"), F.col("v").alias("b")))
    emitted, watch, on = edges.select(F.inline(F.array(*keys))), watch.distinct(), ["kind", "a", "b"]
    n = watch.count() if n is None else n
    if n <= most:
        return emitted.join(F.broadcast(watch), on).groupBy(*on).agg(F.count(F.lit(1)).alias("n"))
    return sieved(emitted, watch, on, n).groupBy(*on).agg(F.count(F.lit(1)).alias("n")).join(watch, on)


def degrees_of(probed: DataFrame) -> DataFrame:
    return probed.where("kind = 'V'").select(F.col("a").alias("x"), F.col("n").alias("d"))


def pairs_of(probed: DataFrame) -> DataFrame:
    return probed.where("kind = 'P'").select(F.col("a").alias("p"), F.col("b").alias("q"))


def with_edge_degree(df: DataFrame, degree: DataFrame) -> DataFrame:
    """df with u, v -> d_u, d_v, d_e, x, y added; the second end is x on a tie."""
    out = df.join(degree.select(F.col("x").alias("u"), F.col("d").alias("d_u")), "u").join(degree.select(F.col("x").alias("v"), F.col("d").alias("d_v")), "v")
    first = F.col("d_u") < F.col("d_v")
    return out.withColumns({"d_e": F.least("d_u", "d_v"), "x": F.when(first, F.col("u")).otherwise(F.col("v")), "y": F.when(first, F.col("v")).otherwise(F.col("u"))})
