"""Golden facts, fixtures and invariants of the engine."""

import itertools
import math
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from sparsetri import queries
from sparsetri.operators import assign, baselines, closing, degeneracy, estimators, exact, passes, sampling
from sparsetri.plans import packed
from sparsetri.plans.ledger import SpaceBudgetExceeded, SpaceGuard
from sparsetri.plans.params import SamplePlan, plan_from_rse, plan_theory, predicted_rse
from sparsetri.plans.store import stored
from sparsetri.sources import graphs
from sparsetri.sources.edges import assert_simple, canonical
from sparsetri.sources.graphs import VIEWS
from sparsetri.streaming.passes import Halves, streamed_six_pass

GOLDEN = {"g_copurchase": (200, 8899, 125968, 743261), "g_geo": (180, 325, 150, 775), "g_wheel": (151, 300, 150, 900), "g_book": (202, 401, 200, 1001), "g_docs": (85, 475, 3709, 11649), "g_pages": (28, 37, 26, 121), "g_coactive": (15, 105, 455, 1470)}
KAPPA = {"g_geo": 2, "g_wheel": 3, "g_book": 2, "g_docs": 28, "g_pages": 5, "g_coactive": 14}


def edges_of(spark, pairs):
    return canonical(spark.createDataFrame(list(pairs) or [(0, 0)], "a long, b long"), "a", "b")


K4 = list(itertools.combinations(range(4), 2))
FIXTURES = {"empty": ([], 0, 0), "edge": ([(1, 2)], 0, 1), "triangle": ([(1, 2), (2, 3), (1, 3)], 1, 2), "k4": (K4, 4, 3), "k5": (list(itertools.combinations(range(-2, 3), 2)), 10, 4), "c6": ([(i, (i + 1) % 6) for i in range(6)], 0, 2), "star": ([(0, i) for i in range(1, 9)], 0, 1), "bow": ([(0, 1), (1, 2), (0, 2), (2, 3), (3, 4), (2, 4)], 2, 2), "dirty": ([(1, 2), (2, 1), (1, 1), (2, 3), (3, 1), (3, 1)], 1, 2), "big": ([(2**60, 2**60 + 1), (2**60 + 1, -5), (-5, 2**60)], 1, 2)}


@pytest.mark.parametrize("name", FIXTURES)
def test_fixtures(spark, name):
    pairs, t, kappa = FIXTURES[name]
    e = stored(edges_of(spark, pairs), name)
    for count in (exact.count_triangles, exact.count_by_intersection, exact.count_bruteforce, exact.count_by_matrix):
        assert count(e).first()["t"] == t
    assert degeneracy.peel(e)[0] == kappa
    m = e.count()
    got = estimators.six_pass(e, SamplePlan(m, 10, max(kappa, 1), max(t, 1), 0.1, 40, 80, 8, 3), None).per_rep.first()
    assert got["hits"] > 0 if t else got["hits"] == 0


@pytest.mark.parametrize("view", GOLDEN)
def test_golden(spark, sf, view):
    e = stored(VIEWS[view](spark, sf), view)
    assert tuple(exact.summary(assert_simple(e)).first()) == GOLDEN[view]
    if view in KAPPA:
        kappa, cores = degeneracy.peel(e)
        assert kappa == KAPPA[view]
        assert sorted(cores.collect()) == sorted(degeneracy.cores_by_hindex(e).collect())
        n, m, t, sum_de = GOLDEN[view]
        assert sum_de <= 2 * m * kappa and t <= 2 * m * kappa and kappa <= math.sqrt(2 * m)


def test_simple_check(spark):
    with pytest.raises(ValueError):
        assert_simple(spark.createDataFrame([(1, 2), (1, 2)], "u long, v long"))


def test_warm_up_is_unbiased(spark, sf):
    _, _, t, sum_de = GOLDEN["g_geo"]
    x = [r.x_est for r in estimators.oracle_estimate(stored(VIEWS["g_geo"](spark, sf), "geo"), 2000, 7).per_rep.collect()]
    assert abs(sum(x) / len(x) - t) < 4 * math.sqrt((sum_de * t - t * t) / len(x))


def test_assignment_tames_the_book(spark, sf):
    e = stored(VIEWS["g_book"](spark, sf), "book")
    plan = SamplePlan(401, 202, 2, 200, 0.1, 200, 800, 10, 3, reps=10)
    spread = {}
    for how in ("min_degree", None):
        x = [r.x_est for r in estimators.six_pass(e, plan, how).per_rep.collect()]
        mean = sum(x) / len(x)
        spread[how] = math.sqrt(sum((v - mean) ** 2 for v in x) / len(x)) / 200
    assert spread["min_degree"] < spread[None]


def test_passes_and_guard(spark, sf):
    e = stored(VIEWS["g_geo"](spark, sf), "geo")
    plan = SamplePlan(325, 180, 2, 150, 0.1, 100, 400, 6, 3)
    whole = estimators.six_pass(e, plan).ledger
    # what the ledger says is what the plans of the kept tables read
    assert whole.passes == whole.reads == 6
    three = estimators.oracle_estimate(e, 50, 3).ledger
    assert three.passes == three.reads == 3
    assert estimators.six_pass(e, plan, degree_oracle=exact.degrees(e)).ledger.passes == 5
    with pytest.raises(SpaceBudgetExceeded):
        estimators.six_pass(e, plan, guard=SpaceGuard(10, 2))


def test_assignment_properties(spark, sf):
    e = stored(VIEWS["g_docs"](spark, sf), "docs")
    for eps in (0.1, 0.5, 1.0):
        q = assign.quality(assign.assign_exact(e, 28, eps, 3709, 475)).first()
        assert q["triangles"] == 3709 and q["max_assigned"] <= 28 / eps and q["assigned"] >= (1 - 12 * eps) * 3709


def test_multiset_is_uniform_with_repeats(spark):
    e = stored(edges_of(spark, [(i, i + 1) for i in range(50)]), "path")
    rows = sampling.uniform_multiset(e, 5000, 50, 3).groupBy("u").count().collect()
    assert len(rows) == 50 and sum(r["count"] for r in rows) == 5000 and all(50 < r["count"] < 160 for r in rows)


def test_hard_graph(spark):
    for shared, t, kappa in ((False, 0, 4), (True, 64, 8)):
        e = stored(baselines.hard_graph(baselines.disjointness_bits(spark, 30, shared), 4, 4), "hard")
        assert (e.count(), exact.count_triangles(e).first()[0], degeneracy.peel(e)[0]) == (336, t, kappa)


def test_plans():
    p = plan_theory(3000, 1501, 3, 1500, 0.1)
    assert p.exact_is_cheaper and p.ell is None and p.with_degrees(9000).ell > 0
    assert predicted_rse(4001, 10001, 2000, 4004000, 2000, 2000, False) > 0.4 > predicted_rse(4001, 10001, 2000, 2000, 2000, 2000)
    assert plan_from_rse(3000, 1501, 3, 1500, 9000, 1500, 0.1).ell >= 4
    with pytest.raises(ValueError):
        plan_theory(10, 10, 1, 1, 0.5)


def test_assignment_takes_its_bounds_from_the_graph(spark, monkeypatch):
    """A complete graph of 40 has degeneracy 39, above that of the small table's view: every triangle still gets an owner."""
    clique = spark.range(40).select(F.col("id").alias("u")).crossJoin(spark.range(40).select(F.col("id").alias("v"))).where("u < v")
    monkeypatch.setitem(queries.VIEWS, "g_docs", lambda *_: clique)
    got = queries.QUERIES["assignment_exact_docs"](spark, "")
    assert got.count() == 9880 and got.where("owner_u IS NULL").count() == 0


def test_hindex_finishes_long_chains(spark):
    """A value moves one hop a round: with fewer rounds than half the chain, peeling has to finish the work."""
    chain = spark.range(40).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    assert {r.core for r in degeneracy.cores_by_hindex(chain, most_rounds=2).collect()} == {1}


def _cores(pairs):
    """Core numbers by taking away one vertex of least degree after the other."""
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    out, k = {}, 0
    while near:
        x = min(near, key=lambda v: len(near[v]))
        k = max(k, len(near[x]))
        out[x] = k
        for y in near.pop(x):
            near[y].discard(x)
    return out


def test_cores_of_a_long_chain_with_a_clique(spark):
    """A complete graph at the end of a chain, with enough rounds for h-indices and with too few, where peeling finishes."""
    pairs = [(i, i + 1) for i in range(8)] + [(100 + a, 100 + b) for a in range(6) for b in range(a)] + [(8, 100)]
    e = stored(edges_of(spark, pairs), "chain")
    for driver_edges in (0, 20, 1000):
        kappa, cores = degeneracy.peel(e, driver_edges)
        assert kappa == 5 and {r.v: r.core for r in cores.collect()} == _cores(pairs)
    assert len(cores.inputFiles()) > 0 and cores._jdf.queryExecution().optimizedPlan().collectLeaves().size() == 1
    assert {r.v: r.core for r in degeneracy.cores_by_hindex(e, 3).collect()} == _cores(pairs) == {r.v: r.core for r in degeneracy.cores_by_hindex(e).collect()}


def test_cores_of_a_path_of_300(spark):
    """Beyond what the default number of rounds reaches from the ends, and settled by peeling: both ends move in by one a round."""
    e = stored(spark.range(299).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v")), "path")
    for cores in (degeneracy.peel(e)[1], degeneracy.cores_by_hindex(e, most_rounds=5)):
        assert {r.core for r in cores.collect()} == {1} and cores.count() == 300


def test_whole_groups_by_brute_force(spark):
    """Like members fold into one vertex; counts are those of the unfolded graph."""
    import random

    rnd = random.Random(4)
    groups = {g: rnd.sample(range(60), n) for g, n in enumerate((2, 3, 5, 20, 40, 40, 1, 8))} | {99: list(range(200, 260))}
    held = [(x, f"g{g}") for g, xs in groups.items() for x in xs] + [(1, "g3"), (None, "g1"), (2, None)]
    pairs = {(min(a, b), max(a, b)) for xs in groups.values() for a in xs for b in xs if a != b}
    pairs |= {(min(1, b), max(1, b)) for b in groups[3] if b != 1}
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    t = sum(len(near[a] & near[b]) for a, b in pairs) // 3
    got = exact.group_summary(spark.createDataFrame(held, "member long, token string")).first()
    assert tuple(got) == (len(near), len(pairs), t, sum(min(len(near[a]), len(near[b])) for a, b in pairs))


def test_large_groups_are_counted_by_classes(spark):
    """Small and large groups that overlap in every way: counts do not depend on what is large.  Edges that are made are those of small groups."""
    import random

    rnd = random.Random(9)
    groups = [rnd.sample(range(120), n) for n in [2, 3, 4, 6] * 12 + [30, 30, 45, 80]]
    held = spark.createDataFrame([(x, f"g{g}") for g, xs in enumerate(groups) for x in xs] + [(x, f"h{k}") for x in range(130, 140) for k in range(2)], "member long, token string")
    near = {}
    for xs in groups + [list(range(130, 140))]:
        for a in xs:
            near.setdefault(a, set()).update(set(xs) - {a})
    pairs = {(a, b) for a in near for b in near[a] if a < b}
    want = (len(near), len(pairs), sum(len(near[a] & near[b]) for a, b in pairs) // 3, sum(min(len(near[a]), len(near[b])) for a, b in pairs))
    for low, most in ((5, 4000), (40, 4000), (1, 4000), (1000, 4000), (1, 20)):
        assert tuple(exact.group_summary(held, low, most).first()) == want


def test_one_group_of_differing_members(spark):
    """3000 members of one group, each with a partner of its own: 4,498,500 pairs and 4.5 billion triangles that are not made."""
    k = 3000
    held = spark.range(k).select(F.col("id").alias("member"), F.lit("all").alias("token"))
    held = held.unionByName(spark.range(2 * k).select(F.col("id").alias("member"), (F.col("id") % k).cast("string").alias("token")))
    got = tuple(exact.group_summary(held).first())
    assert got == (2 * k, k * (k - 1) // 2 + k, k * (k - 1) * (k - 2) // 6, k * (k - 1) // 2 * k + k)


def test_packed_rows_come_back(spark):
    """Any ids, and a few bytes for each of a million edges."""
    far = np.array([-(2**63), -5, 0, 7, 7, 2**63 - 1])
    for columns in ([far], [far, far[::-1].copy()], [far[:1], far[:1], far[-1:]]):
        for got, want in zip(packed.unpack(packed.pack(columns), len(columns[0])), columns, strict=True):
            assert got.tolist() == want.tolist()
    rnd = np.random.default_rng(3)
    u, v = rnd.integers(0, 20_000, 1_000_000), rnd.integers(0, 1_000_000, 1_000_000)
    sent = list(packed.packs(packed.place(u, 16), [u, v]))
    assert sum(b.nbytes for b in sent) < 4 * len(u)
    back = [packed.unpack(x.as_py(), n.as_py()) for b in sent for n, x in zip(b.column(1), b.column(2), strict=True)]
    assert sorted(zip(*(np.concatenate(c).tolist() for c in zip(*back, strict=True)), strict=True)) == sorted(zip(u.tolist(), v.tolist(), strict=True))


def test_pairs_and_degrees_in_packs(spark, monkeypatch):
    """Repeats, nulls and a group far above a chunk of pairs: the edges of the join, each once, without a shuffle of edges as rows."""
    rows = [(g, m) for g in range(300) for m in (g, g + 1, g % 7, g + 1)] + [(999, m) for m in range(400)] + [(None, 1), (5, None), (None, None)]
    df = spark.createDataFrame(rows, "g long, m long")
    monkeypatch.setattr(graphs, "DEALT", 100)
    got = stored(graphs.co_members_packed(df, "g", "m"), "packed-pairs")
    want = sorted(map(tuple, graphs.co_members(df, ["g"], "m").collect()))
    assert sorted(map(tuple, got.collect())) == want and got.columns == ["u", "v"]
    chunks = list(graphs._pairs(3, 50)(0, [np.zeros(30, np.int64), np.arange(30)]))
    assert sum(int(n) for b in chunks for n in b.column(1).to_pylist()) == 30 * 29 // 2 and len(chunks) > 5
    deg = sorted(map(tuple, exact.degrees(got).collect()))
    assert sorted(map(tuple, closing.degrees(got, len(want), 500).collect())) == deg


def test_guesses_share_the_passes(spark, sf):
    e = stored(VIEWS["g_geo"](spark, sf), "geo")
    plan = SamplePlan(325, 180, 2, 150, 0.1, 100, 400, 6, 3)
    guesses = [1300.0, 325.0, 81.25]
    rows, ledger = estimators.without_guess(e, plan, guesses)
    rows = {r.guess: r for r in rows.collect()}
    assert ledger.passes == ledger.reads == 6 and sum(r.accepted for r in rows.values()) <= 1
    for g in guesses:
        assert rows[g].est == estimators.six_pass(e, replace(plan, t_guess=g)).per_rep.first()["x_est"]


def test_streams_keep_no_neighbourhoods(spark):
    """Around a hub of 2000, the last passes keep a list of s neighbours for each edge that may own, whatever the hub's degree."""
    pairs = [(0, k) for k in range(1, 2001)] + [(k, k + 1) for k in range(1, 2000)]
    e = stored(edges_of(spark, pairs), "hub")
    plan = SamplePlan(e.count(), 2001, 3, 1999, 0.1, 60, 240, 5, 3)
    halves = Halves(stored(e.where("u = 0"), "first"), stored(e.where("u > 0"), "second"))
    got = streamed_six_pass(halves, plan).first()
    want = estimators.six_pass(e, plan).per_rep.first()
    assert (got.hits, got.sum_dr) == (want.hits, want.sum_dr) and len(halves.crossed) == 12
    owners_asked = estimators.six_pass(e, plan).stages["triangles"].count() * 3
    assert max(halves.crossed[8:]) <= owners_asked * plan.s


def test_neighbours_by_rank_are_uniform(spark):
    half = spark.createDataFrame([(1, 10 * k) for k in range(5)], "x long, nbr long")
    picks = spark.range(3000).select(F.lit(0).alias("rep"), F.col("id").alias("i"), F.lit(1).cast("long").alias("x"), F.lit(5).alias("d_e"))
    for draw in (sampling.ranked_neighbor, sampling.sample_neighbor):
        rows = draw(half, picks, 3).groupBy("w").count().collect()
        assert len(rows) == 5 and all(480 < r["count"] < 720 for r in rows)


def test_long_watch_lists_pass_a_sieve(spark):
    """Beyond its stated size a watch list is no longer sent to all tasks; counts are the same, whole ones, hub and unwatched ends included."""
    pairs = [(0, k) for k in range(1, 3001)] + [(k, k + 1) for k in range(1, 3000)]
    e = stored(edges_of(spark, pairs), "watched")
    ends = stored(spark.range(0, 3001, 3).withColumnRenamed("id", "x"), "ends")
    asked = stored(spark.range(1, 3500).select(F.col("id").alias("p"), (F.col("id") + 1 + F.col("id") % 2).alias("q")), "asked")
    short, long = passes.probe_pass(e, ends, asked), passes.probe_pass(e, ends, asked, 6000, most=100)
    assert sorted(short.collect()) == sorted(long.collect()) and short.where("kind = 'V' and a = 0").first()["n"] == 3000
    assert short.where("kind = 'P'").count() == len({(k, k + 1 + k % 2) for k in range(1, 3500)} & set(pairs))
    kept = passes.sieved(e, ends.withColumnRenamed("x", "u"), ["u"], 1001)
    want = sum(u % 3 == 0 for u, _ in pairs)
    assert want <= kept.count() <= want + 0.15 * (len(pairs) - want) and kept.where("u % 3 = 0").count() == want
    half = spark.createDataFrame([(x, 10 * x + k) for x in range(50) for k in range(5)], "x long, nbr long")
    few = spark.range(7).withColumnRenamed("id", "x")
    assert sorted(passes.watched(half, few, ["x"], 7, most=1).collect()) == sorted(passes.watched(half, few, ["x"]).collect())
    plan = passes.probe_pass(e, ends, asked, 6000, most=100)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("strategy=broadcast") == 1  # the sieve alone


def test_an_empty_watch_list(spark):
    e = stored(edges_of(spark, K4), "k4")
    nobody = spark.range(0).withColumnRenamed("id", "x")
    assert passes.probe_pass(e, nobody).count() == 0 and passes.probe_pass(e, nobody, n=1, most=0).count() == 0


@pytest.mark.parametrize("spread", (1, 2**40))
def test_triangles_without_moving_wedges(spark, spread, monkeypatch):
    """Lists and buckets give the triangles that joins give: hubs, negative ids, ids too far apart for half a key, several buckets and groups."""
    import random

    from sparsetri.operators import closing

    rnd = random.Random(7)
    pairs = {(0, k) for k in range(1, 300)} | {tuple(rnd.sample(range(-40, 300), 2)) for _ in range(4000)}
    e = stored(edges_of(spark, [(a * spread, b * spread) for a, b in pairs]), "closing")
    want = sorted(exact.triangles(e).collect())
    monkeypatch.setattr(closing, "TOGETHER", 500)
    assert len(want) > 1000 and sorted(closing.triangles(e, e.count(), 300).collect()) == want
    assert closing.count_triangles(e, e.count(), 300).first()["t"] == len(want)
    monkeypatch.setattr(exact, "JOIN_EDGES", 0)
    assert exact.count_triangles(e).first()["t"] == len(want) and "MapInArrow" in exact.triangles(e)._jdf.queryExecution().toString()
    assert exact.count_triangles(e.where("false")).first()["t"] == 0
    ids = spark.createDataFrame([(x,) for x in (0, -1, 2**62, 12345)], "x long")
    assert closing.xxhash64(np.array([r.x for r in ids.collect()])).tolist() == [r[0] for r in ids.select(F.xxhash64("x")).collect()]


def test_edges_of_a_window_are_counted_without_pairs(spark, monkeypatch):
    from sparsetri.streaming import windows

    rows = [(w, "abcd"[(x * 7 + w + k) % 4], x) for w in range(3) for x in range(40) for k in range(x % 3)] + [(1, None, 5), (2, "a", None)]
    m = stored(spark.createDataFrame(rows, "start int, event_type string, user_id long"), "members")
    want = sorted(tuple(r) for r in windows.window_edges(m).groupBy("start").count().collect())
    assert want and sorted(tuple(r) for r in windows.window_edge_counts(m).collect()) == want
    many = m.unionByName(spark.range(70).select(F.lit(0).alias("start"), F.concat(F.lit("t"), F.col("id")).alias("event_type"), (F.col("id") + 100).alias("user_id")))
    assert sorted(tuple(r) for r in windows.window_edge_counts(many).collect()) == want


def test_wedges_at_a_hub_are_not_made(spark, tmp_path):
    """300,000 neighbours of one vertex are 45 thousand million wedges."""
    n = 300_000
    spark.range(n).select(F.col("id").alias("c_custkey"), F.lit(0).cast("long").alias("c_nationkey")).write.parquet(f"{tmp_path}/customer.parquet")
    spark.createDataFrame([(0, 0)], "n_nationkey long, n_regionkey long").write.parquet(f"{tmp_path}/nation.parquet")
    every = {r.x: r.n for r in queries.queries()["join_semi_closure"](spark, str(tmp_path)).where("x in (1, 2)").collect()}
    rest = {r.x: r.n for r in queries.queries()["join_anti_open_wedges"](spark, str(tmp_path)).collect()}
    assert every == {1: n, 2: n} and rest == {1: n * (n + 1) // 2 - n, 2: n * (n + 1) // 2 - n}


def test_hard_graph_of_a_table(spark, sf, tmp_path):
    """The function's bits are the customers': another table, another graph."""
    spark.read.parquet(f"{sf}/customer.parquet").where("c_custkey < 10").write.parquet(f"{tmp_path}/customer.parquet")
    n = spark.read.parquet(f"{tmp_path}/customer.parquet").where("c_nationkey % 3 < 2").count()
    assert [tuple(r) for r in queries.queries()["udtf_hard_graph"](spark, str(tmp_path)).collect()] == [(True, 16 + 16 * n)]


def test_quality_for_several_eps_at_once(spark, sf):
    e = stored(VIEWS["g_docs"](spark, sf), "docs")
    t, m = exact.count_triangles(e).first()["t"], e.count()
    got = {r.eps: tuple(r)[1:] for r in assign.exact_quality(e, 28, [0.1, 0.5, 1.0], t, m).collect()}
    assert got == {eps: tuple(assign.quality(assign.assign_exact(e, 28, eps, t, m)).select("triangles", "assigned", "max_assigned", "sum_squares").first()) for eps in (0.1, 0.5, 1.0)}


def test_cores_in_one_task(spark, sf, monkeypatch):
    for e in (stored(VIEWS["g_docs"](spark, sf), "docs"), stored(edges_of(spark, [(i * 2**40, (i + 1) * 2**40) for i in range(-300, 300)]), "path"), edges_of(spark, []).where("false")):
        want = sorted(tuple(r) for r in degeneracy.peel(e, 0)[1].collect()) if e.count() < 500 else sorted(tuple(r) for r in degeneracy.peel(e)[1].collect())
        assert sorted(tuple(r) for r in degeneracy.cores(e).collect()) == want
    monkeypatch.setattr(degeneracy, "TASK_EDGES", 0)
    assert degeneracy.cores(stored(VIEWS["g_pages"](spark, sf), "pages")).agg(F.max("core")).first()[0] == KAPPA["g_pages"]


def test_counts_of_edges_without_moving_wedges(spark, monkeypatch):
    import random

    from sparsetri.operators import closing

    rnd = random.Random(8)
    e = stored(edges_of(spark, {(0, k) for k in range(1, 300)} | {tuple(rnd.sample(range(-40, 300), 2)) for _ in range(4000)}), "counting")
    want = sorted(exact.edge_triangle_counts(e).collect())
    monkeypatch.setattr(closing, "HELD", 900)
    got = sorted(tuple(r) for r in closing.edge_counts(e, e.count(), 300).collect())
    assert got == [(r.u, r.v, r.t_inc) for r in want] and any(r.t_inc == 0 for r in want)
    monkeypatch.setattr(exact, "JOIN_EDGES", 0)
    assert sorted(exact.edge_triangle_counts(e).collect()) == want
    marked = stored(edges_of(spark, [(0, 1), (5, 9)]).join(e, ["u", "v"], "left_semi"), "marked")
    some = {(0, 1), (5, 9)}
    t = {tuple(r) for r in exact.triangles(e).collect()}
    assert {tuple(r) for r in assign.triangles_by_edges(e, marked, False).collect()} == {x for x in t if some & {(x[0], x[1]), (x[0], x[2]), (x[1], x[2])} & {tuple(r) for r in marked.collect()}}
