"""Graphs in one task's memory: arrays and bits against joins and rounds."""

import math
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsetri import oracles, queries
from sparsetri.operators import closing, degeneracy, exact, whole
from sparsetri.plans.store import stored, written
from sparsetri.sources import graphs
from sparsetri.sources.edges import canonical

LARGE, FAR = 2**62, -(2**62)


def _graph(spark, pairs):
    return stored(canonical(spark.createDataFrame([(int(a), int(b)) for a, b in pairs], "a long, b long"), "a", "b"), "whole")


def _pairs(kind):
    rnd = np.random.default_rng(5)
    if kind == "dense":
        return [(a * 7, b * 7) for a in range(90) for b in range(a) if rnd.random() < 0.8]
    sparse = rnd.integers(0, 400, (1500, 2)).tolist() + [(0, x) for x in range(1, 300)] + [(LARGE, 3), (FAR, 3), (LARGE, FAR)]
    return sparse


@pytest.mark.parametrize("kind", ["dense", "sparse"])
def test_arrays_agree_with_joins_and_rounds(spark, monkeypatch, kind):
    e = _graph(spark, _pairs(kind))
    want, cores = exact.summary(e), sorted(map(tuple, degeneracy.peel(e)[1].collect()))
    d = exact.degrees(e)
    by_rows = (d.count(), e.count(), exact.count_by_matrix(e).first()[0], exact.edge_degrees(e).agg(F.sum("d_e")).first()[0])
    assert tuple(want.first()) == by_rows
    assert whole.dense(by_rows[0], by_rows[1]) == (kind == "dense")
    monkeypatch.setattr(exact, "JOIN_EDGES", 10)
    monkeypatch.setattr(closing, "count_triangles", closing.count_triangles if kind == "sparse" else None)
    assert tuple(exact.summary(e).first()) == by_rows
    counts = sorted(map(tuple, exact.edge_triangle_counts(e).collect()))
    monkeypatch.setattr(exact, "JOIN_EDGES", 10**9)
    assert counts == sorted(map(tuple, exact.edge_triangle_counts(e).collect()))
    monkeypatch.setattr(degeneracy, "peel", None)
    assert sorted(map(tuple, degeneracy.cores(e).collect())) == cores
    for as_bits in (False, True):
        files = stored(d, "degrees").inputFiles()
        assert sorted(map(tuple, e.coalesce(1).mapInArrow(whole.cores(files, as_bits), degeneracy.CORES).collect())) == cores


def test_few_vertices_with_many_edges_take_no_rounds(spark, monkeypatch):
    e = _graph(spark, _pairs("dense"))
    want = sorted(map(tuple, degeneracy.peel(e)[1].collect()))
    monkeypatch.setattr(degeneracy, "TASK_EDGES", 100)
    monkeypatch.setattr(degeneracy, "peel", None)
    assert sorted(map(tuple, degeneracy.cores(e).collect())) == want


def test_a_filtered_table_is_not_read_whole(spark):
    e = _graph(spark, _pairs("dense"))
    some = e.where("u < 210")
    assert written(e, "same") is e
    assert spark.read.parquet(*written(some, "some").inputFiles()).count() == some.count() < e.count()


def test_bound_comparison_takes_all_views(spark, sf):
    got = {r.view for r in queries.QUERIES["bound_comparison"](spark, sf).collect()}
    assert {"g_knn", "g_cosupply"} <= got
    assert all(f"'{v}' AS view" in queries.ORACLES["bound_comparison"] for v in oracles.VIEWS)


def test_cosines_in_blocks(spark, monkeypatch, tmp_path):
    """Several blocks, halves of a millionth, vectors of zeros, without entries and of another length."""
    rnd = np.random.default_rng(2)
    vectors = [(k, x) for k, x in enumerate(rnd.normal(size=(60, 5)).tolist())] + [(100, [0.0] * 5), (101, None), (102, [1.0, None, 1.0, 1.0, 1.0]), (103, [1.0, 1.0]), (104, [1.0, 1.0])]
    spark.createDataFrame(vectors, "vec_id long, embedding array<double>").write.parquet(f"{tmp_path}/embeddings.parquet")
    monkeypatch.setattr(graphs, "BLOCK", 16)
    seq = graphs._sequential
    norm = {k: math.sqrt(seq(np.array(x), np.array(x))) for k, x in vectors if x and None not in x and any(x)}
    held = dict(vectors)
    cos = {(a, b): int((Decimal(repr(seq(np.array(held[a]), np.array(held[b])) / norm[a] / norm[b])) * 10**6).to_integral_value(ROUND_HALF_UP)) for a in norm for b in norm if a != b and len(held[a]) == len(held[b])}
    got = sorted(map(tuple, graphs.g_vec(spark, str(tmp_path)).collect()))
    assert got == sorted((a, b) for (a, b), c in cos.items() if a < b and c >= 350_000)
    near = {tuple(sorted((a, b))) for a in norm for _, b in sorted((-c, b) for (x, b), c in cos.items() if x == a)[:10]}
    assert sorted(map(tuple, graphs.g_knn(spark, str(tmp_path)).collect())) == sorted(near)
    x, y = np.array([[1.0, 0.0]]), np.array([[0.3499995, math.sqrt(1 - 0.3499995**2)]])
    one = seq(x[0], y[0]) / math.sqrt(seq(y[0], y[0]))
    want = int((Decimal(repr(one)) * 10**6).to_integral_value(ROUND_HALF_UP))
    for nudge in (-1e-16, 0, 1e-16):
        assert graphs._millionths(np.array([one + nudge]), np.array([0]), np.array([0]), x, y).tolist() == [want]
