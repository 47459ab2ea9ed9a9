"""MinHash near-deduplication with tensored banding.

A document is the set of its distinct w-word shingles.  Instead of m*m tables with keys of their own, two small collections of m half
keys each are computed, and table (i, j) is keyed by half i of the first and half j of the second: m*m tables for the minhash work of 2m.
A pair that meets in a table shares a half in both collections, so documents without any shared half never form a table key.

1. Equal sets collapse to one class, named by its least doc_id.
2. Of classes that share a half in both collections the full sets are made.  Shingles that only one of these sets has are in no
   intersection, so their number bounds a set's similarity to any other: sets that cannot reach the threshold drop out.
3. The rest gets table keys; classes that meet in a table are candidates.  A bucket's members are first compared with its leader only, the class with
   the largest share of shingles that others have, then with a member drawn by hash; what that links is joined to components.
4. Buckets whose members are still in several components are compared across these components, so nothing that meets in a table is
   left unchecked; pairs inside one component need no check, as they cannot change it.
All candidates are confirmed on the full sets, in integers: 100 * common >= percent * union.

With halves of 2 minhashes and m = 10, a pair of similarity 0.8 is missed with probability below 1e-4, and one of 0.85 below 1e-5.

Defined results: A-Z are lowered, words end at blanks \\x20, \\x09-\\x0D.  With fewer words than w the whole sequence is one
shingle; null or wordless texts have empty sets and are linked with nothing.  Rows with a null doc_id are linked with nothing and have a
null component.  Rows that share a doc_id keep a row each and are one vertex: the row whose set has the least hash stands for
all.  Only doc_id and text are read.
Shingles are 64-bit hashes; two shingles of one comparison collide with a probability around 1e-13.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import arrow_rows, claim_cache, ease_driver, stored
from .components import connected_components

LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
SIDES, HALVES, PER_HALF = 2, 10, 2
PARITY_WORDS = 16
#: Classes of one half in a block.
BLOCK = 256


class _Words(dict):
    """64-bit hashes of words, kept while there is room."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= 200_000:
            self.clear()
        h = self[word] = xxhash.xxh3_64_intdigest(word)
        return h


_words = _Words()


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    return x ^ (x >> np.uint64(32))


def shingles(text: str | None, width: int) -> np.ndarray:
    """Sorted distinct hashes."""
    words = (text or "").encode().translate(LOWER).split()
    if not words:
        return np.empty(0, np.uint64)
    h = np.fromiter(map(_words.__getitem__, words), np.uint64, len(words))
    n = min(width, len(words))
    out = np.full(len(words) - n + 1, n, np.uint64)
    for k in range(n):
        out = out * np.uint64(0x9E3779B97F4A7C15) + h[k : len(words) - n + 1 + k]
    return np.unique(_mixed(out))


def parities(sh: np.ndarray) -> np.ndarray:
    """Whether each of the 64 * PARITY_WORDS cells holds an odd number of items.  Items that two sets share cancel out, so the
    cells in which two sets differ are never more than the items that only one of them has."""
    odd = np.bincount((sh >> np.uint64(32)).astype(np.int64) % (64 * PARITY_WORDS), minlength=64 * PARITY_WORDS) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.int64)


def set_hash(sh: np.ndarray) -> list[int]:
    return np.frombuffer(xxhash.xxh3_128_digest(sh.tobytes()), np.int64).tolist()


def _seeds(count: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(20)
    return rng.integers(0, 2**63, count, np.uint64), rng.integers(0, 2**62, count, np.uint64) * np.uint64(2) + np.uint64(1)


XOR, TIMES = _seeds(SIDES * HALVES * PER_HALF)


def half_keys(sh: np.ndarray) -> np.ndarray:
    """SIDES * HALVES keys; each carries its own number, so keys of different halves never meet."""
    least = np.full(len(XOR), np.iinfo(np.uint64).max)
    for start in range(0, len(sh), 4096):
        least = np.minimum(least, _mixed((sh[start : start + 4096] ^ XOR[:, None]) * TIMES[:, None]).min(axis=1))
    key = np.arange(SIDES * HALVES, dtype=np.uint64)
    for k in range(PER_HALF):
        key = _mixed(key * np.uint64(0x9E3779B97F4A7C15) + least[k::PER_HALF])
    return key.view(np.int64)


PROFILE = pa.schema([("doc_id", pa.int64()), ("n_shingles", pa.int64()), ("set_a", pa.int64()), ("set_b", pa.int64()), ("halves", pa.list_(pa.int64()))])
PROFILE_DDL = "doc_id long, n_shingles long, set_a long, set_b long, halves array<long>"


def _profile(width: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    claim_cache("minhash", _words.clear)
    add, rest = arrow_rows(PROFILE)
    for batch in batches:
        for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            sh = shingles(text.as_py(), width)
            row = (key, len(sh), *set_hash(sh), half_keys(sh) if len(sh) else [])
            if (full := add(row, 250)) is not None:
                yield full
    yield from rest()


def _sets(width: int, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("id", pa.int64()), ("set_a", pa.int64()), ("set_b", pa.int64()), ("items", pa.list_(pa.int64())), ("odd", pa.list_(pa.int64()))])
    claim_cache("minhash", _words.clear)
    add, rest = arrow_rows(schema, flush_bytes=4 << 20)
    for batch in batches:
        for key, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            sh = shingles(text.as_py(), width)
            if (full := add((key, *set_hash(sh), sh.view(np.int64), parities(sh)), 8 * (len(sh) + PARITY_WORDS))) is not None:
                yield full
    yield from rest()


def full_sets(candidates: DataFrame, docs: DataFrame, width: int, repeats: bool) -> DataFrame:
    """(id, items, odd) of the candidate classes.  Sets are made again from texts, which is cheaper than storing the sets of
    all; the join is always a merge join, so that the plan does not change with the number of candidates."""
    needed = candidates.select(F.col("rep").alias("id")).hint("merge")
    texts = docs.select(F.col("doc_id").alias("id"), "text").join(needed, "id", "left_semi")
    sets = texts.mapInArrow(partial(_sets, width), "id long, set_a long, set_b long, items array<long>, odd array<long>")
    if repeats:
        sets = sets.where("size(items) > 0").groupBy("id").agg(F.min(F.struct("set_a", "set_b", "items", "odd")).alias("s")).select("id", "s.items", "s.odd")
    return stored(sets.select("id", "items", "odd"), "sets")


def measured(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """pairs (a, b) with the distance of their full sets, and whether they link."""
    joined = pairs.join(sets.select(F.col("id").alias("b"), F.col("items").alias("items_b")).hint("merge"), "b")
    joined = joined.join(sets.select(F.col("id").alias("a"), F.col("items").alias("items_a")).hint("merge"), "a")
    common = F.size(F.array_intersect("items_a", "items_b")).cast("long")
    union = F.size("items_a") + F.size("items_b") - common
    return joined.select("a", "b", (1 - common / union).alias("distance"), (common * 100 >= union * percent).alias("linked"))


def shared_halves(halves: DataFrame) -> DataFrame:
    """Halves that another class has too, of classes that have such halves in both collections."""
    # counts are written first: a join of two tables can be split at hot keys, a join with an aggregate beneath it can not
    shared = stored(halves.groupBy("half").agg(F.count(F.lit(1)).alias("holders")).where("holders > 1").select("half"), "shared")
    kept = halves.join(shared, "half")
    both = kept.groupBy("rep").agg(F.min("place").alias("low"), F.max("place").alias("high")).where((F.col("low") < HALVES) & (F.col("high") >= HALVES)).select("rep")
    return stored(kept.join(both, "rep"), "halves")


def table_keys(halves: DataFrame) -> DataFrame:
    """(key, rep, n, common) for each table in which the class could meet another."""
    own = halves.groupBy("rep", "n", "common").agg(
        F.collect_list(F.when(F.col("place") < HALVES, F.col("half"))).alias("first"), F.collect_list(F.when(F.col("place") >= HALVES, F.col("half"))).alias("second")
    )
    keys = F.flatten(F.transform("first", lambda x: F.transform(F.col("second"), lambda y: F.xxhash64(x, y))))
    return own.select("rep", "n", "common", F.explode(keys).alias("key"))


def may_link(n: Column, common: Column, n2: Column, common2: Column, percent: int) -> Column:
    """Whether two sets of these sizes can be similar enough, if so many of their items occur in any other set at all."""
    most = F.least(common, common2)
    return most * 100 >= (n + n2 - most) * percent


def cells_link(n: Column, n2: Column, words: list[tuple[Column, Column]], percent: int) -> Column:
    """Whether two sets can be similar enough, if they differ in at least as many items as parity cells."""
    apart = sum((F.bit_count(x.bitwiseXOR(y)) for x, y in words), F.lit(0))
    most = F.floor((n + n2 - apart) / 2)
    return most * 100 >= (n + n2 - most) * percent


def in_components(rows: DataFrame, found: DataFrame) -> DataFrame:
    """rows with the component of rep, which is rep itself where nothing links."""
    return rows.join(found.withColumnRenamed("id", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))


def led_pairs(keyed: DataFrame, leading: Column, percent: int) -> DataFrame:
    """(a, b), a < b: in every bucket its leader, the maximum of `leading`, with each member of another component."""
    keyed = keyed.select("key", "rep", "n", "common", "component")
    leaders = keyed.groupBy("key").agg(F.max(leading).alias("m"), F.min("component").alias("low"), F.max("component").alias("high")).where("low < high")
    leaders = stored(leaders.select("key", F.col("m.rep").alias("lead"), F.col("m.n").alias("n2"), F.col("m.common").alias("common2"), F.col("m.component").alias("component2")), "leaders")
    met = keyed.join(leaders, "key").where((F.col("component") != F.col("component2")) & may_link(F.col("n"), F.col("common"), F.col("n2"), F.col("common2"), percent))
    return met.select(F.least("rep", "lead").alias("a"), F.greatest("rep", "lead").alias("b")).distinct()


def across_components(halves: DataFrame, found: DataFrame, tried: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(a, b): all pairs that meet in some table and whose classes are in different components, each once.

    To meet in a table is to share a half of the first collection and one of the second.  So the join is on halves of the first,
    a pair counts at its first shared half only, and the second collection is a filter: a pair is one row, however many tables hold it.
    Classes of a hot half are dealt to blocks of about BLOCK; each block meets the whole half in a task of its own.
    Distances obey the triangle inequality, so two sets whose measured distances to a third differ by too much are left out,
    and so are sets whose parity cells differ in too many places.  Both are bounds: they leave out no pair that links."""
    lists = halves.groupBy("rep", "n", "common").agg(
        F.array_sort(F.collect_list(F.when(F.col("place") < HALVES, F.struct("place", "half")))).alias("first"), F.collect_list(F.when(F.col("place") >= HALVES, F.col("half"))).alias("second")
    )
    # each class's measured third is the one that most classes were measured against
    ends = tried.select(F.inline(F.array(F.struct(F.col("a").alias("pivot"), F.col("b").alias("rep"), "distance"), F.struct(F.col("b").alias("pivot"), F.col("a").alias("rep"), "distance"))))
    used = stored(ends.groupBy("pivot").agg(F.count(F.lit(1)).alias("uses")), "uses")
    itself = used.select("pivot", F.col("pivot").alias("rep"), F.lit(0.0).alias("distance"), "uses")
    pivots = ends.join(used, "pivot").select("pivot", "rep", "distance", "uses").unionByName(itself)
    pivots = pivots.groupBy("rep").agg(F.max(F.struct("uses", "pivot", "distance")).alias("p")).select("rep", F.col("p.pivot").alias("pivot"), F.col("p.distance").alias("distance"))
    named = in_components(lists, found).join(pivots, "rep", "left")
    own = ["rep", "n", "common", "component", "second", "pivot", "distance"]
    earlier = lambda i: F.transform(F.slice("first", 1, i), lambda x: x["half"])
    rows = named.select(*own, "first", F.posexplode(F.transform("first", lambda x: x["half"])).alias("at", "half"))
    rows = stored(rows.select(*own, "half", earlier(F.col("at")).alias("earlier")), "across")
    open_ = rows.groupBy("half").agg(F.min("component").alias("low"), F.max("component").alias("high"), F.ceil(F.count(F.lit(1)) / BLOCK).cast("int").alias("blocks")).where("low < high").select("half", "blocks")
    open_ = stored(open_, "open-halves")
    odd = [f"odd_{k}_" for k in range(PARITY_WORDS)]
    cells = sets.select(F.col("id").alias("rep"), *(F.col("odd")[k].alias(c) for k, c in enumerate(odd)))
    left = stored(rows.join(open_, "half").join(cells.hint("merge"), "rep"), "open")
    right = left.select("half", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), *(F.col(c).alias(f"{c}2") for c in (*own, *odd, "earlier")))
    left = left.withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")).cast("int"))
    near = cells_link(F.col("n"), F.col("n2"), [(F.col(c), F.col(f"{c}2")) for c in odd], percent)
    once = ~F.arrays_overlap("earlier", "earlier2") & F.arrays_overlap("second", "second2")
    far = F.coalesce((F.col("pivot") == F.col("pivot2")) & (F.abs(F.col("distance") - F.col("distance2")) > 1 - percent / 100 + 1e-9), F.lit(False))
    met = left.join(right, ["half", "block"]).where((F.col("component") < F.col("component2")) & may_link(F.col("n"), F.col("common"), F.col("n2"), F.col("common2"), percent) & ~far & near & once)
    return met.select(F.least("rep", "rep2").alias("a"), F.greatest("rep", "rep2").alias("b"))


def near_duplicates(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept): a row for each row of docs."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("text"))
    profiles = stored(docs.mapInArrow(partial(_profile, width), PROFILE_DDL), "profiles")
    filled = profiles.where("n_shingles > 0 and doc_id is not null")
    repeats = not filled.groupBy("doc_id").count().where("count > 1").isEmpty()
    if repeats:
        one = filled.groupBy("doc_id").agg(F.min(F.struct("set_a", "set_b", "n_shingles", "halves")).alias("s"))
        filled = stored(one.select("doc_id", "s.*"), "profiles")
    classes = filled.groupBy("set_a", "set_b").agg(F.min(F.struct("doc_id", F.col("n_shingles").alias("n"), "halves")).alias("r"))
    classes = stored(classes.select("set_a", "set_b", F.col("r.doc_id").alias("rep"), F.col("r.n").alias("n"), F.col("r.halves").alias("halves")), "classes")
    halves = shared_halves(classes.select("rep", "n", F.posexplode("halves").alias("place", "half")))
    sets = full_sets(halves.select("rep").distinct(), docs, width, repeats)
    # an item that no other candidate has is in no intersection: this bounds what a set can be similar to, exactly
    alone = sets.select("id", F.explode("items").alias("item")).groupBy("item").agg(F.count(F.lit(1)).alias("holders"), F.min("id").alias("rep")).where("holders = 1")
    alone = alone.groupBy("rep").agg(F.count(F.lit(1)).alias("alone"))
    live = halves.join(alone, "rep", "left").withColumn("common", F.col("n") - F.coalesce("alone", F.lit(0))).drop("alone")
    live = shared_halves(live.where(F.col("common") * 100 >= F.col("n") * percent))
    keyed = stored(table_keys(live), "keys")
    ease_driver(docs.sparkSession)

    # a bucket is led by the class with the largest share of items that others have: the version the others were made from
    leading = F.struct((F.col("common") / F.col("n")).alias("share"), (-F.col("rep")).alias("first"), "rep", "n", "common", "component")
    tried = stored(measured(led_pairs(keyed.withColumn("component", F.col("rep")), leading, percent), sets, percent), "measured")
    found = connected_components(tried.where("linked").select("a", "b"))
    ease_driver(docs.sparkSession)
    # then, in buckets of several components, by any member: what has a near version of its own finds it there
    leading = F.struct(F.xxhash64("key", "rep").alias("by"), "rep", "n", "common", "component")
    more = led_pairs(in_components(keyed, found), leading, percent).join(tried.select("a", "b"), ["a", "b"], "left_anti")
    tried = stored(tried.unionByName(measured(more, sets, percent)), "measured")
    found = connected_components(tried.where("linked").select("a", "b"))
    ease_driver(docs.sparkSession)
    more = stored(across_components(live, found, tried, sets, percent).join(tried.select("a", "b"), ["a", "b"], "left_anti"), "pairs")
    if not more.isEmpty():
        late = stored(measured(more, sets, percent).where("linked").select("a", "b"), "links")
        if not late.isEmpty():
            found = connected_components(tried.where("linked").select("a", "b").unionByName(late))

    members = filled.select("doc_id", "set_a", "set_b").join(classes.select("set_a", "set_b", "rep"), ["set_a", "set_b"]).select("doc_id", "rep")
    named = members.join(found.withColumnRenamed("id", "rep"), "rep", "left").select("doc_id", F.coalesce("component", "rep").alias("component"))
    out = profiles.select("doc_id", "n_shingles").join(named, "doc_id", "left")
    return out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id")).withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def keep_one(docs: DataFrame, width: int = 5, percent: int = 80) -> DataFrame:
    """docs without the rows that are not kept; of rows that share a kept doc_id all stay."""
    gone = near_duplicates(docs, width, percent).where(~F.col("kept")).select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
