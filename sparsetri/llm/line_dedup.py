"""Line deduplication across documents.

Lines are exploded as hashes of their normalised form, the distinct documents of every hash are counted, and lines
whose hash is in too many documents go from all of them but one.  Documents are put together again by position.

Texts cross the network once, when the list of dropped hashes meets its document; until then only 128-bit hashes and
ids move.  Both counting steps combine on the map side.  Over-common hashes are a written table: up to MOST_SENT of them go to all tasks,
and lines meet them where they are; more are joined to the lines by an equi-join of two written sides, whose hot keys adaptive execution
splits.  Either way a line held by a third of all documents is no hot task.

Defined results: a null or empty text is one empty line.  Rows with the same doc_id and text are one document for
counting and each keep their own result row; rows that share a doc_id but not the text are told apart.  Rows with a null
doc_id are never counted and lose nothing.  Other columns pass through untouched.
"""

from __future__ import annotations

import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored

BLANKS = " \t\n\x0b\x0c\r"
#: Rows of two hashes and an id that a broadcast may have: some 10 MB.
MOST_SENT = 200_000


def lower_ascii(text: Column) -> Column:
    """A-Z in lower case and nothing else; the cheap built-in serves wherever all characters are ASCII."""
    return F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(F.translate(text, string.ascii_uppercase, string.ascii_lowercase))


def line_key(line: Column) -> Column:
    return lower_ascii(F.btrim(line, F.lit(BLANKS)))


def _hash(key: Column) -> Column:
    """Two differently seeded 64-bit hashes: 128 bits, so that no two lines of a 100 TB corpus meet by chance."""
    return F.struct(F.xxhash64(key).alias("a"), F.xxhash64(F.lit(1), key).alias("b"))


def over_common_lines(lined: DataFrame, min_chars: int = 40, min_docs: int = 5, most_sent: int = MOST_SENT) -> DataFrame:
    """lined: doc_id, __row, __lines.  (doc_id, __row, __drop: positions) for every document that loses lines."""
    # short lines get no hash: their place keeps its number, and no row leaves for them
    hashed = F.transform(F.col("__lines"), lambda x: F.when(F.char_length(F.btrim(x, F.lit(BLANKS))) >= min_chars, _hash(line_key(x))))
    lines = (
        lined.where(F.col("doc_id").isNotNull()).select("doc_id", "__row", F.posexplode(hashed).alias("at", "h")).where(F.col("h").isNotNull())
        .select("doc_id", "__row", "at", F.col("h.a").alias("a"), F.col("h.b").alias("b"))
    )
    common = (
        lines.select("a", "b", "doc_id").distinct().groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"), F.max("doc_id").alias("keeper"))
        .where(F.col("n") >= min_docs).select("a", "b", "keeper")
    )
    common = stored(common, "common-lines")
    lost = lines.join(F.broadcast(common) if common.count() <= most_sent else common.hint("merge"), ["a", "b"]).where(F.col("doc_id") != F.col("keeper"))
    return lost.groupBy("doc_id", "__row").agg(F.collect_set("at").alias("__drop"))


def dedup_lines(docs: DataFrame, min_chars: int = 40, min_docs: int = 5, most_sent: int = MOST_SENT) -> DataFrame:
    """docs with text replaced by what stays of it, and a struct column line_dedup (n_lines, n_dropped).

    A column of docs that is itself called line_dedup is replaced."""
    lined = docs.withColumns({"__row": F.xxhash64(F.coalesce("text", F.lit(""))), "__lines": F.split(F.coalesce("text", F.lit("")), "\n", -1)})
    lost = over_common_lines(lined.select("doc_id", "__row", "__lines"), min_chars, min_docs, most_sent).select(F.col("doc_id").alias("__id"), F.col("__row").alias("__of"), "__drop")
    # the lines, not the text, go through the join, so that positions index an array that is already there
    joined = lined.drop("text").join(lost, (F.col("doc_id") == F.col("__id")) & (F.col("__row") == F.col("__of")), "left")
    n = F.size("__lines")
    stay = F.array_except(F.sequence(F.lit(0), n - 1), F.col("__drop"))
    kept = F.when(F.col("__drop").isNull(), F.col("__lines")).otherwise(F.transform(stay, lambda i: F.get(F.col("__lines"), i)))
    counts = F.struct(n.cast("long").alias("n_lines"), F.coalesce(F.size("__drop"), F.lit(0)).cast("long").alias("n_dropped"))
    out = joined.withColumns({"text": F.array_join(kept, "\n"), "line_dedup": counts})
    return out.select(*dict.fromkeys([*docs.columns, "line_dedup"]))
