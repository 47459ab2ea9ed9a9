"""Mixing sources to target weights by hash-threshold histograms.

Every document gets a 36-bit hash of its id.  Words are summed by source and hash prefix; the prefix at which a
source's budget runs out is the boundary, and only documents inside the boundary prefix are summed again, by the
next digits.  After three rounds a source has one threshold, and a document is taken once more exactly if its hash lies
below it.  Nothing is sorted but histograms, which have at most 4096 rows a source, and all of it is DataFrame
expressions.

Targets: sources in code point order (null last) weigh 5, 2, 1 and so on in turn and share `share` times all words; no target
passes `cap` times its source's words, and what is over goes to the others by weight.  The level at which this stops
has a closed form over sources ordered by words per weight, so one window over the sources gives it: a row of some 50 bytes for each, which
one task orders; `MOST_SOURCES` bounds it, and more raise an error rather than slow down.

Defined results: a null text has size 0.  Rows without a doc_id are hashed by their text, equal rows share their fate.
A source without words has target 0.  The source column may hold nulls; these form one source.  An empty table gives an empty one.  Only
doc_id, text and source are read, so other columns may have any name, and take() passes them through.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

WORD = r"[^\x20\x09-\x0D]+"
DIGITS, ROUNDS, MOST_SOURCES = 3, 3, 1_000_000


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def _source_key(source: Column) -> Column:
    """Never null, so that plain equi-joins and their skew handling apply."""
    return F.coalesce(F.concat(F.lit("="), source), F.lit("-"))


def document_hash() -> Column:
    """Nine hex digits that any engine with md5 can repeat."""
    own = F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("text:"), F.md5(F.coalesce("text", F.lit("")).cast("binary"))))
    return F.substring(F.md5(F.concat(F.lit("mix|"), own).cast("binary")), 1, DIGITS * ROUNDS)


def source_targets(sizes: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, cap: int = 2) -> DataFrame:
    """(key, source_size, target): sizes has columns key and size."""
    per = sizes.groupBy("key").agg(F.sum("size").alias("source_size"))
    # code points sort as UTF-8 bytes do; the null key "-" sorts before "=", so it is put last explicitly
    ranked = per.withColumn("place", F.row_number().over(Window.orderBy(F.col("key") == "-", "key")) - 1)
    ranked = ranked.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (F.col("place") % len(weights) + 1).cast("int")).cast("double"))
    every = Window.orderBy(F.col("source_size") / F.col("weight"), "place")
    whole = Window.partitionBy()
    leveled = ranked.select(
        "key", "source_size", "weight",
        (F.col("source_size") * cap).cast("double").alias("most"),
        (F.sum("source_size").over(whole) * F.lit(share)).alias("budget"),
        F.coalesce(F.sum(F.col("source_size") * cap).over(every.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).cast("double").alias("full"),
        F.sum("weight").over(every.rowsBetween(Window.currentRow, Window.unboundedFollowing)).alias("rest"),
    )
    level = leveled.withColumn("level", (F.col("budget") - F.col("full")) / F.col("rest"))
    # the first source, by words per weight, that the common level leaves below its cap fixes the level for all
    fixed = F.min(F.when(F.col("level") * F.col("weight") <= F.col("most"), F.struct(F.col("source_size") / F.col("weight"), "level"))).over(whole)["level"]
    return level.withColumn("fixed", fixed).select("key", "source_size", F.coalesce(F.least("most", F.col("fixed") * F.col("weight")), F.col("most")).alias("target"))


def _boundary(histogram: DataFrame) -> DataFrame:
    """histogram: key, slice, words, left.  Per key the first slice that no longer fits, and what is left for it."""
    running = Window.partitionBy("key").orderBy("slice")
    return (
        histogram.withColumn("upto", F.sum("words").over(running))
        .where(F.col("upto") > F.col("left"))
        .groupBy("key").agg(F.min(F.struct("slice", (F.col("left") - F.col("upto") + F.col("words")).alias("left"), "words")).alias("b"))
        .select("key", F.col("b.slice").alias("slice"), F.col("b.left").alias("left"), F.col("b.words").alias("words"))
    )


def mix(docs: DataFrame, weights: tuple[int, ...] = (5, 2, 1), share: float = 1.5, cap: int = 2) -> DataFrame:
    """(doc_id, row_hash, size, source_size, target, copies): how often the mix takes each document.

    row_hash tells rows with one doc_id apart; rows equal in both are one decision repeated."""
    sized = stored(
        docs.select("doc_id", F.xxhash64("text").alias("row_hash"), _source_key(F.col("source")).alias("key"), word_count(F.col("text")).alias("size"), document_hash().alias("h")),
        "mix-sizes",
    )
    targets = source_targets(sized.select("key", "size"), weights, share, cap)
    targets = stored(
        targets.withColumn("whole", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long"))
        .withColumn("left", F.col("target") - F.col("whole") * F.col("source_size")),
        "mix-targets",
    )
    if (n := targets.count()) > MOST_SOURCES:
        raise ValueError(f"{n} sources; a mix has at most {MOST_SOURCES}")
    last, prefix = None, 0
    for _ in range(ROUNDS):
        if last is None:
            inside = sized.join(targets.select("key", "left"), "key").withColumn("before", F.lit(""))
        else:
            inside = sized.join(last.select("key", "left", F.col("slice").alias("before")), "key").where(F.substring("h", 1, prefix) == F.col("before"))
        prefix += DIGITS
        histogram = inside.groupBy("key", "left", F.substring("h", 1, prefix).alias("slice")).agg(F.sum("size").alias("words"))
        last = stored(_boundary(histogram), "mix-boundary")
    # the last slice cannot be split: it is taken if that brings the source nearer to its target
    closing = last.select("key", "slice", (F.col("left") * 2 > F.col("words")).alias("closing"))
    decided = targets.join(closing, "key", "left")
    once_more = F.when(F.col("slice").isNull(), F.col("left") > 0).otherwise((F.col("h") < F.col("slice")) | ((F.col("h") == F.col("slice")) & F.col("closing")))
    return sized.join(decided, "key").select("doc_id", "row_hash", "size", "source_size", "target", (F.col("whole") + once_more.cast("long")).alias("copies"))


def take(docs: DataFrame, **how) -> DataFrame:
    """docs as the mix takes them: a row for each copy, none for documents that are not taken."""
    copies = mix(docs, **how).select("doc_id", "row_hash", "copies").distinct().where(F.col("copies") > 0)
    return (
        docs.alias("d").join(copies.alias("c"), F.col("d.doc_id").eqNullSafe(F.col("c.doc_id")) & (F.xxhash64(F.col("d.text")) == F.col("c.row_hash")))
        .withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("c.copies").cast("int")))).select("d.*")
    )
