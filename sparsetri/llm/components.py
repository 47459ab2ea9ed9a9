"""Connected components of an edge table by contraction, without collecting anything.

In each round every vertex names its least neighbour (or itself) as parent, vertices are replaced by their parents and edges inside
one vertex vanish; the order is by id first, which ends star-shaped groups in one round, and by a new hash in later rounds, which
keeps long chains logarithmic.  Minima combine on the map side and the relabelling joins are plain equi-joins, so a vertex with
very many edges is no hot task.  Every round is a written table.

Defined results: edges with a null end are no edges, repeated and reversed edges are one, an edge of a vertex with itself joins nothing, and
no edges give an empty table.  Only a and b are read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored


def connected_components(edges: DataFrame) -> DataFrame:
    """edges: a, b (long).  (id, component: least id of the component) for every id that has an edge to another."""
    left = stored(edges.where(F.col("a") != F.col("b")).select("a", "b").distinct(), "edges")
    assigned, turn = None, 0
    while not left.isEmpty():
        def ranked(c, turn=turn):
            return F.struct((F.col(c) if turn == 0 else F.xxhash64(F.lit(turn), c)).alias("by"), F.col(c).alias("id"))

        both = left.select("a", "b").unionByName(left.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min(ranked("b")).alias("m"))
        parents = stored(least.select(F.col("a").alias("v"), F.least(F.col("m"), ranked("a"))["id"].alias("parent")), "parents")
        if assigned is None:
            assigned = parents.select(F.col("v").alias("id"), F.col("parent").alias("root"))
        else:
            moved = assigned.join(parents, F.col("root") == F.col("v"), "left").select("id", F.coalesce("parent", "root").alias("root"))
            assigned = stored(moved, "assigned")
        up = left.join(parents, F.col("a") == F.col("v")).select(F.col("parent").alias("a"), "b")
        up = up.join(parents, F.col("b") == F.col("v")).select("a", F.col("parent").alias("b"))
        left = stored(up.where(F.col("a") != F.col("b")).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
        turn += 1
    if assigned is None:
        return left.select(F.col("a").alias("id"), F.col("b").alias("component"))
    names = assigned.groupBy("root").agg(F.min("id").alias("component"))
    return assigned.join(names, "root").select("id", "component")
