"""DuckDB SQL of the graph views and of the sampled pipelines, with the same md5 coins, so that samples can be compared bit for bit."""

from __future__ import annotations


def coin(seed: int, *parts: str) -> str:
    return f"('0x' || substr(md5(concat_ws('|', '{seed}', {', '.join(parts)})), 1, 13))::BIGINT"


def _pairs(inner: str) -> str:
    """inner gives p, q."""
    return f"SELECT DISTINCT least(p, q)::BIGINT AS u, greatest(p, q)::BIGINT AS v FROM ({inner}) WHERE p <> q"


def _members(inner: str) -> str:
    """inner gives g, x."""
    return _pairs(f"SELECT a.x AS p, b.x AS q FROM (SELECT DISTINCT * FROM ({inner})) a JOIN (SELECT DISTINCT * FROM ({inner})) b ON a.g = b.g AND a.x < b.x")


def _capped(inner: str, low: int, high: int) -> str:
    return _members(f"SELECT g, x FROM (SELECT *, count(*) OVER (PARTITION BY g) AS held FROM (SELECT DISTINCT * FROM ({inner}))) WHERE held BETWEEN {low} AND {high}")


def _corners(a: str, b: str, c: str, tables: str) -> str:
    return _pairs(" UNION ALL ".join(f"SELECT {x} AS p, {y} AS q FROM {tables}" for x, y in ((a, b), (b, c), (a, c))))


def _lines(table: str, key: str) -> str:
    return f"SELECT md5(line) AS g, {key} AS x FROM (SELECT {key}, unnest(string_split(text, chr(10))) AS line FROM {table}) WHERE length(line) > 20"


_COS = "round(list_dot_product(a.e, b.e) / sqrt(list_dot_product(a.e, a.e)) / sqrt(list_dot_product(b.e, b.e)), 6)"
_E = "(SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS e FROM embeddings)"

VIEWS = {
    "g_copurchase": _members("SELECT l_orderkey AS g, l_partkey AS x FROM lineitem"),
    "g_cosupply": _members("SELECT l_orderkey AS g, l_suppkey AS x FROM lineitem"),
    "g_part_supp": _pairs("SELECT 2 * l_partkey AS p, 2 * l_suppkey + 1 AS q FROM lineitem"),
    "g_order_part_supp": _corners("3 * l_orderkey", "3 * l_partkey + 1", "3 * l_suppkey + 2", "lineitem"),
    "g_cust_part_supp": _corners("3 * o_custkey", "3 * l_partkey + 1", "3 * l_suppkey + 2", "lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "g_coactive": _pairs("SELECT user_id AS p, lead(user_id) OVER (ORDER BY ts, event_id) AS q FROM events"),
    "g_hour_type": _members("SELECT date_trunc('hour', ts)::VARCHAR || event_type AS g, user_id AS x FROM events"),
    "g_geo": _corners("4 * c_custkey", "4 * n_nationkey + 1", "4 * n_regionkey + 2", "customer JOIN nation ON c_nationkey = n_nationkey"),
    "g_geo_supp": _corners("4 * s_suppkey", "4 * n_nationkey + 1", "4 * n_regionkey + 2", "supplier JOIN nation ON s_nationkey = n_nationkey"),
    "g_wheel": _pairs("SELECT 0 AS p, k AS q FROM (SELECT row_number() OVER (ORDER BY c_custkey) AS k FROM customer) UNION ALL SELECT k, k % n + 1 FROM (SELECT row_number() OVER (ORDER BY c_custkey) AS k, count(*) OVER () AS n FROM customer)"),
    "g_book": _pairs("SELECT 0 AS p, 1 AS q UNION ALL SELECT s, k FROM (SELECT row_number() OVER (ORDER BY p_partkey) + 1 AS k FROM part), (VALUES (0), (1)) t(s)"),
    "g_pages": _capped("""SELECT unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS g, page_id AS x FROM pages""", 1, 50),
    "g_docs": _capped(_lines("documents", "doc_id"), 2, 60),
    "g_docs_labelled": _capped(_lines("(SELECT * FROM documents WHERE doc_id IN (SELECT doc_id FROM labels))", "doc_id"), 2, 60),
    "g_conv": _capped("SELECT string_split(lower(text), ' ')[1] AS g, conv_id AS x FROM conversations WHERE role = 'user'", 2, 60),
    "g_doc_bench": _pairs(f"SELECT 2 * a.x AS p, 2 * b.x + 1 AS q FROM ({_lines('documents', 'doc_id')}) a JOIN ({_lines('benchmark', 'item_id')}) b ON a.g = b.g"),
    "g_vec": _pairs(f"SELECT a.vec_id AS p, b.vec_id AS q FROM {_E} a JOIN {_E} b ON a.vec_id < b.vec_id WHERE {_COS} >= 0.35"),
    "g_knn": _pairs(f"SELECT p, q FROM (SELECT a.vec_id AS p, b.vec_id AS q, row_number() OVER (PARTITION BY a.vec_id ORDER BY {_COS} DESC, b.vec_id) AS k FROM {_E} a JOIN {_E} b ON a.vec_id <> b.vec_id) WHERE k <= 10"),
}


def graph(view: str) -> str:
    """CTEs e, h, d, ed, o, tri, inc over a view (without WITH)."""
    return f"""e AS MATERIALIZED ({VIEWS.get(view, view)}),
h AS (SELECT u AS x, v AS nbr FROM e UNION ALL SELECT v, u FROM e),
d AS MATERIALIZED (SELECT x, count(*) AS d FROM h GROUP BY x),
ed AS MATERIALIZED (SELECT e.u, e.v, a.d AS d_u, b.d AS d_v, least(a.d, b.d) AS d_e, CASE WHEN a.d < b.d THEN e.u ELSE e.v END AS x, CASE WHEN a.d < b.d THEN e.v ELSE e.u END AS y
  FROM e JOIN d a ON e.u = a.x JOIN d b ON e.v = b.x),
o AS MATERIALIZED (SELECT CASE WHEN d_u <= d_v THEN u ELSE v END AS p, CASE WHEN d_u <= d_v THEN v ELSE u END AS q FROM ed),
tri AS MATERIALIZED (SELECT list_sort([i.p, i.q, j.q]) AS t FROM o i JOIN o j ON i.p = j.p AND i.q < j.q JOIN e ON e.u = i.q AND e.v = j.q),
te AS (SELECT t[1] AS a, t[2] AS b, t[3] AS c, unnest([t[1], t[1], t[2]]) AS u, unnest([t[2], t[3], t[3]]) AS v FROM tri),
inc AS MATERIALIZED (SELECT ed.u, ed.v, ed.d_e, count(te.a) AS t_inc FROM ed LEFT JOIN te ON ed.u = te.u AND ed.v = te.v GROUP BY ALL)"""


#: CTEs kap (kappa: batch peeling's upper bound of the degeneracy), by rounds that drop all vertices of degree up to 1.5 times the mean.
KAPPA = """bp(i, u, v) AS (SELECT 0, u, v FROM e UNION ALL SELECT q.i, q.u, q.v FROM (
  WITH dg AS (SELECT x, count(*) AS d FROM (SELECT u AS x FROM bp UNION ALL SELECT v FROM bp) GROUP BY x), st AS (SELECT count(*) AS n, sum(d) AS s FROM dg), hi AS (SELECT x FROM dg, st WHERE 2 * d * n > 3 * s)
  SELECT bp.i + 1 AS i, bp.u, bp.v FROM bp JOIN hi a ON bp.u = a.x JOIN hi b ON bp.v = b.x) q),
bd AS (SELECT i, x, count(*) AS d FROM (SELECT i, u AS x FROM bp UNION ALL SELECT i, v FROM bp) GROUP BY i, x),
kap AS MATERIALIZED (SELECT coalesce(max(d), 0)::BIGINT AS kappa FROM bd JOIN (SELECT i, count(*) AS n, sum(d) AS s FROM bd GROUP BY i) USING (i) WHERE 2 * d * n <= 3 * s)"""

#: CTE cores (v, core): in each round all vertices of degree up to k go, k rising to the least degree that is left.
CORES = """pc(k, u, v) AS (SELECT (SELECT min(d) FROM d), u, v FROM e UNION ALL SELECT q.k, q.u, q.v FROM (
  WITH dg AS (SELECT x, count(*) AS d FROM (SELECT u AS x FROM pc UNION ALL SELECT v FROM pc) GROUP BY x), hi AS (SELECT x FROM dg WHERE d > (SELECT max(k) FROM pc)),
  st AS (SELECT pc.k, pc.u, pc.v FROM pc JOIN hi a ON pc.u = a.x JOIN hi b ON pc.v = b.x)
  SELECT greatest(st.k, (SELECT min(n) FROM (SELECT count(*) AS n FROM (SELECT u AS x FROM st UNION ALL SELECT v FROM st) GROUP BY x))) AS k, st.u, st.v FROM st) q),
cores AS MATERIALIZED (SELECT x AS v, max(k)::BIGINT AS core FROM (SELECT k, u AS x FROM pc UNION ALL SELECT k, v FROM pc) GROUP BY x)"""

#: CTE bounds (m, kappa, t): what a plan takes from the graph at hand.
BOUNDS = f"{KAPPA},\nm AS (SELECT count(*) AS m FROM e),\nbounds AS MATERIALIZED (SELECT m, kappa, (SELECT count(*) FROM tri)::DOUBLE AS t FROM m, kap)"


def cut(eps: float, t: str = "t") -> str:
    """The largest degree of an owner."""
    return f"CASE WHEN {t} > 0 THEN m * kappa::DOUBLE * kappa / ({eps}::DOUBLE * {eps}::DOUBLE * {t}) ELSE 'inf'::DOUBLE END"


def passes(view: str, seed: int, r: int, ell: int, s: int, eps: float, rep: int = 0, t: str | None = None, exhaustive: bool = False, neighbor: str = "argmin") -> str:
    """CTEs of all six passes over a view for one replica (with WITH RECURSIVE); t is a guess of the triangles, by default their number."""
    least = f"p.*, h.nbr AS w, row_number() OVER (PARTITION BY p.i ORDER BY {coin(seed, "'neighbor'", str(rep), 'p.i', 'h.nbr')}, h.nbr) AS k"
    if neighbor == "rank":
        least = f"p.*, h.nbr AS w, row_number() OVER (PARTITION BY p.i ORDER BY h.nbr) - {coin(seed, "'place'", str(rep), 'p.i')} % p.d_e AS k"
    draws = f"SELECT n.u, n.v, n.w, n.y, n.d_e, times * n.d_e AS weight FROM near n JOIN times k ON n.u = k.u AND n.v = k.v AND n.rk = k.rk"
    if exhaustive:
        draws = f"{draws} WHERE n.d_e > {s} UNION ALL SELECT u, v, w, y, d_e, {s} FROM near WHERE d_e <= {s}"
    return f"""{graph(view)}, {BOUNDS},
ranked AS (SELECT u, v, row_number() OVER (ORDER BY {coin(seed, "'edge'", str(rep), 'u', 'v')}, u, v) AS rk FROM e),
slots AS (SELECT slot, dense_rank() OVER (ORDER BY pos) AS rk FROM (SELECT i AS slot, {coin(seed, "'slot'", str(rep), 'i')} % m AS pos FROM range({r}) z(i), m)),
drawn AS (SELECT slot, u, v FROM slots JOIN ranked USING (rk)),
sampled AS (SELECT slot, ed.u, ed.v, x, y, d_e FROM drawn JOIN ed ON drawn.u = ed.u AND drawn.v = ed.v),
cum AS (SELECT *, sum(d_e) OVER (ORDER BY slot) AS upto FROM sampled),
total AS (SELECT sum(d_e) AS sum_dr FROM sampled),
aims AS (SELECT i, {coin(seed, "'pick'", str(rep), 'i')} % sum_dr::BIGINT AS aim FROM range({ell}) z(i), total),
picks AS MATERIALIZED (SELECT i, u, v, x, y, d_e FROM aims JOIN cum ON aim >= upto - d_e AND aim < upto),
chosen AS MATERIALIZED (SELECT i, u, v, x, y, d_e, w FROM (SELECT {least} FROM picks p JOIN h ON p.x = h.x) WHERE k = 1),
closed AS MATERIALIZED (SELECT i, c.u, c.v, list_sort([c.u, c.v, c.w]) AS t FROM chosen c JOIN e ON least(c.y, c.w) = e.u AND greatest(c.y, c.w) = e.v WHERE c.w <> c.y),
found AS (SELECT DISTINCT t FROM closed),
fe AS (SELECT t, unnest([t[1], t[1], t[2]]) AS u, unnest([t[2], t[3], t[3]]) AS v FROM found),
guess AS MATERIALIZED (SELECT m, kappa, {t or 't'} AS t FROM bounds),
targets AS MATERIALIZED (SELECT DISTINCT ed.* FROM fe JOIN ed ON fe.u = ed.u AND fe.v = ed.v, guess WHERE ed.d_e <= {cut(eps, 'guess.t')}),
near AS (SELECT g.u, g.v, g.y, g.d_e, h.nbr AS w, row_number() OVER (PARTITION BY g.u, g.v ORDER BY {coin(seed, "'owner'", 'g.u', 'g.v', 'h.nbr')}, h.nbr) AS rk FROM targets g JOIN h ON g.x = h.x),
times AS (SELECT u, v, rk, count(*) AS times FROM (SELECT u, v, dense_rank() OVER (PARTITION BY u, v ORDER BY pos) AS rk FROM (SELECT u, v, {coin(seed, "'draw'", 'u', 'v', 'j')} % d_e AS pos FROM targets, range({s}) z(j))) GROUP BY ALL),
counted AS (SELECT n.u, n.v, sum(weight)::BIGINT AS scaled FROM ({draws}) n JOIN e ON least(n.y, n.w) = e.u AND greatest(n.y, n.w) = e.v WHERE n.w <> n.y GROUP BY ALL),
estimated AS (SELECT g.u, g.v, coalesce(scaled, 0) AS scaled FROM targets g LEFT JOIN counted c ON g.u = c.u AND g.v = c.v),
least_ AS (SELECT t, min(CASE WHEN scaled IS NOT NULL THEN {{'s': scaled, 'u': fe.u, 'v': fe.v}} END) AS o FROM fe LEFT JOIN estimated x ON fe.u = x.u AND fe.v = x.v GROUP BY t),
memo AS MATERIALIZED (SELECT least_.t, CASE WHEN o.s <= kappa / (2 * {eps}::DOUBLE) * {s} THEN o.u END AS owner_u, CASE WHEN o.s <= kappa / (2 * {eps}::DOUBLE) * {s} THEN o.v END AS owner_v FROM least_, kap)"""


def owner_by(count: str) -> str:
    """CTE memo2 (t, owner_u, owner_v) over found triangles by a column of inc or ed."""
    source = "inc" if count == "t_inc" else "ed"
    return f"best AS (SELECT t, min({{'s': {count}, 'u': fe.u, 'v': fe.v}}) AS o FROM fe JOIN {source} x ON fe.u = x.u AND fe.v = x.v GROUP BY t), memo2 AS (SELECT t, o.u AS owner_u, o.v AS owner_v FROM best)"


def estimate(view: str, memo: str | None, share: float = 1.0, **plan) -> str:
    extra = "" if memo in (None, "memo") else ", " + owner_by(memo)
    name = "memo" if memo == "memo" else "memo2"
    hits = "closed" if memo is None else f"closed JOIN {name} USING (t) WHERE owner_u = u AND owner_v = v"
    r, ell = plan["r"], plan["ell"]
    return f"""WITH RECURSIVE {passes(view, **plan)}{extra},
hit AS (SELECT count(*) AS hits FROM {hits})
SELECT m, {r}::BIGINT AS r, {ell}::BIGINT AS ell, sum_dr::BIGINT AS sum_dr, hits, round(m::DOUBLE / {r} * sum_dr::DOUBLE * hits / {ell} / {share}, 6) AS x_est FROM m, total, hit"""


def hard(n: int, p: int, q: int, shared: bool) -> str:
    """Edges u, v of the hard graph: two sides, all joined, and blocks joined to one side by each party's bits."""
    y = "((i % 3 = 1 AND i <> 1) OR i = 0)" if shared else "i % 3 = 1"
    block = f"(SELECT i, i * {q} + j + {2 * p} AS w FROM range({n}) a(i), range({q}) b(j))"
    return f"SELECT a AS u, b + {p} AS v FROM range({p}) s(a), range({p}) t(b) UNION ALL SELECT a, w FROM range({p}) s(a), {block} WHERE i % 3 = 0 UNION ALL SELECT a + {p}, w FROM range({p}) s(a), {block} WHERE {y}"


def whole(inner: str) -> str:
    """Edges between members of a common group, groups of any size; inner gives g, x."""
    return _members(inner)


GROUPS = {
    "docs": _lines("documents", "doc_id"),
    "pages": """SELECT unnest(regexp_extract_all(html, 'href="/([^"]*)"', 1)) AS g, page_id AS x FROM pages""",
    "conv": "SELECT string_split(lower(text), ' ')[1] AS g, conv_id AS x FROM conversations WHERE role = 'user'",
}


def sampled(view: str, seed: int, r: int) -> str:
    """CTEs of a graph, its bounds and the first two passes: drawn (slot, u, v) and sampled (and x, y, d_e); with WITH RECURSIVE."""
    return passes(view, seed, r, 1, 1, 0.1).split("cum AS")[0].rstrip(" ,\n")
