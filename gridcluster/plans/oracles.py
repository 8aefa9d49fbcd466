"""DuckDB SQL twins of the queries that SQL can express, written from the definitions."""

from __future__ import annotations

import math

from ..functions.portable import gaussian_sql, uniform_sql
from . import workloads
from .queries import CENTERS, DIMS


def r(x: str, digits: int = 6) -> str:
    return f"round({x}, {digits}) + 0.0"


def vec(dims: int) -> str:
    return ", ".join(f"CAST(embedding[{i + 1}] AS DOUBLE) AS z{i}" for i in range(dims))


def _distance(center, dims: int) -> str:
    return " + ".join(f"pow(z{i} - ({float(center[i])!r}), 2)" for i in range(dims))


_Z = ", ".join(f"z{i}" for i in range(DIMS))
_V = f"v AS (SELECT vec_id AS row_id, label, {vec(DIMS)} FROM embeddings)"
_D = ", ".join(f"{_distance(c, DIMS)} AS d{k}" for k, c in enumerate(CENTERS))
_PICK = "CASE WHEN d0 <= d1 AND d0 <= d2 THEN 0 WHEN d1 <= d2 THEN 1 ELSE 2 END"
#: Points with label, truth and squared distance under the fixed centers.
ASSIGNED = f"{_V}, d AS (SELECT *, {_D} FROM v), a AS (SELECT row_id, {_Z}, label, label % 3 AS truth, {_PICK} AS pred, least(d0, d1, d2) AS dist FROM d)"
PARTS = "p AS (SELECT p_partkey AS row_id, CAST(p_partkey % 2 AS INT) AS row_grp, CAST(p_size AS DOUBLE) AS f0, p_retailprice / 100 AS f1, CAST(p_partkey % 13 AS DOUBLE) AS f2, p_partkey % 7 + p_size / 10 AS f3 FROM part)"
SMALL_LINES = "l AS (SELECT l_orderkey AS row_id, CAST(l_orderkey % 4 AS INT) AS row_grp, l_quantity AS f0, l_discount * 100 AS f1, l_tax * 100 AS f2, CAST(month(l_shipdate) AS DOUBLE) AS f3 FROM lineitem)"
CUSTOMERS = """b AS (SELECT o_custkey, CAST(count(*) AS DOUBLE) AS n, avg(o_totalprice) AS mean, stddev_pop(o_totalprice) AS sd, avg(CASE WHEN o_orderstatus = 'F' THEN 1.0 ELSE 0.0 END) AS share FROM orders GROUP BY o_custkey),
c AS (SELECT c_custkey AS row_id, n_regionkey AS row_grp, c_acctbal AS f0, CAST(c_nationkey AS DOUBLE) AS f1, coalesce(n, 0.0) AS f2, coalesce(mean, 0.0) AS f3, coalesce(sd, 0.0) AS f4, coalesce(share, 0.0) AS f5
FROM customer JOIN nation ON c_nationkey = n_nationkey LEFT JOIN b ON c_custkey = o_custkey)"""
#: The leading component of each two-feature party, in closed form.
PCA2 = f"""{PARTS},
q AS (SELECT row_grp, 0 AS col_grp, avg(f0) AS m0, avg(f1) AS m1, var_pop(f0) AS a, var_pop(f1) AS d, covar_pop(f0, f1) AS b FROM p GROUP BY row_grp
UNION ALL SELECT row_grp, 1, avg(f2), avg(f3), var_pop(f2), var_pop(f3), covar_pop(f2, f3) FROM p GROUP BY row_grp),
t AS (SELECT *, 0.5 * atan2(2 * b, a - d) AS ang FROM q),
s AS (SELECT *, CASE WHEN abs(cos(ang)) >= abs(sin(ang)) THEN sign(cos(ang)) ELSE sign(sin(ang)) END AS sg FROM t),
m AS (SELECT row_grp, col_grp, m0, m1, cos(ang) * sg AS u0, sin(ang) * sg AS u1 FROM s)"""


#: The same about zero: the leading eigenvector of each party's second moments.
PCA0 = f"""{PARTS},
q AS (SELECT row_grp, 0 AS col_grp, avg(f0 * f0) AS a, avg(f1 * f1) AS d, avg(f0 * f1) AS b FROM p GROUP BY row_grp
UNION ALL SELECT row_grp, 1, avg(f2 * f2), avg(f3 * f3), avg(f2 * f3) FROM p GROUP BY row_grp),
t AS (SELECT *, 0.5 * atan2(2 * b, a - d) AS ang FROM q),
s AS (SELECT *, CASE WHEN abs(cos(ang)) >= abs(sin(ang)) THEN sign(cos(ang)) ELSE sign(sin(ang)) END AS sg FROM t),
m AS (SELECT row_grp, col_grp, cos(ang) * sg AS u0, sin(ang) * sg AS u1 FROM s)"""
_PRICES = "g AS (SELECT o_custkey AS row_id, " + ", ".join(f"avg(o_totalprice) FILTER (o_orderstatus = '{c}') AS {c.lower()}" for c in "FOP") + " FROM orders GROUP BY o_custkey)"


def _anchors(name: str, rows: int, seed: int, width: int, bounds: str) -> str:
    feats = ", ".join(f"lo{j} + {uniform_sql(seed, 'id', j)} * (hi{j} - lo{j}) AS f{j}" for j in range(width))
    return f"{name} AS (SELECT id AS anchor_id, {feats} FROM range({rows}) g(id), {bounds})"


_BOUNDS = PARTS + ", e AS (SELECT " + ", ".join(f"min(f{j}) AS lo{j}, max(f{j}) AS hi{j}" for j in range(4)) + " FROM p)"
_KNN = """v AS (SELECT vec_id AS id, {v} FROM embeddings),
k AS (SELECT src, dst, dist FROM (SELECT x.id AS src, y.id AS dst, {d} AS dist, row_number() OVER (PARTITION BY x.id ORDER BY {d}, y.id) AS rn FROM v x, v y WHERE x.id <> y.id) WHERE rn <= 5)""".format(
    v=vec(DIMS), d=" + ".join(f"pow(x.z{i} - y.z{i}, 2)" for i in range(DIMS))
)
_BOTH = "b AS (SELECT src, dst FROM k UNION ALL SELECT dst, src FROM k)"
_SYM = f"{_KNN}, {_BOTH}, s AS (SELECT src, dst, CAST(count(*) AS DOUBLE) / 2 AS w FROM b GROUP BY src, dst), g AS (SELECT src AS id, sum(w) AS deg FROM s GROUP BY src)"


def _lloyd(passes: int, shifts: bool = False) -> str:
    z = _Z
    out = f"WITH {_V}, c0 AS (SELECT row_number() OVER (ORDER BY row_id) - 1 AS k, {z} FROM (SELECT * FROM v ORDER BY row_id LIMIT 3))"
    for p in range(1, passes + 1):
        d = " + ".join(f"pow(v.z{i} - c.z{i}, 2)" for i in range(DIMS))
        means = ", ".join(f"avg(z{i}) AS z{i}" for i in range(DIMS))
        keep = ", ".join(f"coalesce(n.z{i}, o.z{i}) AS z{i}" for i in range(DIMS))
        out += f""", a{p} AS (SELECT row_id, {z}, k FROM (SELECT v.row_id, {', '.join(f'v.z{i}' for i in range(DIMS))}, c.k, row_number() OVER (PARTITION BY v.row_id ORDER BY {d}, c.k) AS rn FROM v, c{p - 1} c) WHERE rn = 1),
n{p} AS (SELECT k, {means} FROM a{p} GROUP BY k), c{p} AS (SELECT o.k, {keep} FROM c{p - 1} o LEFT JOIN n{p} n ON o.k = n.k)"""
    if shifts:
        moved = [f"SELECT {p} AS pass, CAST(a.k AS INT) AS cluster, {r('sqrt(' + ' + '.join(f'pow(b.z{i} - a.z{i}, 2)' for i in range(DIMS)) + ')')} AS shift FROM c{p - 1} a JOIN c{p} b ON a.k = b.k" for p in range(1, passes + 1)]
        return f"{out} {' UNION ALL '.join(moved)}"
    parts = " UNION ALL ".join(f"SELECT CAST(k AS INT) AS cluster, {i} AS pos, {r(f'z{i}')} AS val FROM c{passes}" for i in range(DIMS))
    return f"{out} {parts}"


def _planted(majors: tuple[str, str], seed: int = 1) -> str:
    common = f"{gaussian_sql(seed, 'row_id', 'common')} * {workloads.MINOR_COMMON}"
    minors = [f"{gaussian_sql(seed, 'row_id', f'minor{i}')} * {workloads.MINOR_OWN} + {common}" for i in range(4)]
    cols = ", ".join(f"{r(x, 5)} AS f{i}" for i, x in enumerate([*majors, *minors]))
    return f"SELECT row_id, CAST(truth AS INT) AS truth, {cols} FROM (SELECT o_orderkey AS row_id, o_orderkey % 3 AS truth FROM orders)"


def _pick(values) -> str:
    return "CASE truth " + " ".join(f"WHEN {i} THEN {float(v)!r}" for i, v in enumerate(values)) + " END"


def _share(column: str, ch: str) -> str:
    return f"(length({column}) - length(translate(lower({column}), '{ch}', ''))) / greatest(length({column}), 1)"


_LETTERS = "aeinrstuoh"
_TEXT = "coalesce(text, '')"
_SCORED = """s AS (SELECT event_id, ts, user_id, CASE WHEN d0 <= d1 AND d0 <= d2 THEN 0 WHEN d1 <= d2 THEN 1 ELSE 2 END AS pred FROM (
SELECT event_id, ts, user_id, pow(value - 20, 2) + pow(hour(ts) - 6, 2) AS d0, pow(value - 20, 2) + pow(hour(ts) - 18, 2) AS d1, pow(value - 80, 2) + pow(hour(ts) - 12, 2) AS d2 FROM events))"""
_LEDGER = "g AS (SELECT o_orderpriority AS dataset, CASE o_orderstatus WHEN 'F' THEN 'pooled' WHEN 'O' THEN 'grid' ELSE 'solo' END AS method, 'ari' AS metric, o_totalprice / 1e5 AS value FROM orders), t AS (SELECT dataset, method, metric, avg(value) AS mean, coalesce(stddev(value), 0.0) AS sd, count(*) AS trials FROM g GROUP BY ALL)"
_DELTA = f"{_LEDGER}, d AS (SELECT t.dataset, t.method, t.metric, (t.mean - b.mean) / abs(b.mean) * 100 AS diff FROM t JOIN t b ON b.method = 'pooled' AND b.dataset = t.dataset AND b.metric = t.metric WHERE t.method <> 'pooled')"
_U = f"{ASSIGNED}, u AS (SELECT truth, pred, count(*) AS cnt FROM a GROUP BY truth, pred)"
_ROWS = "c AS (SELECT doc_id AS row_id FROM documents), o AS (SELECT DISTINCT doc_id AS row_id FROM labels)"


def _gram_rows(width: int, source: str, digits: int) -> str:
    names = [f"f{i}" for i in range(width)] + ["1.0"]
    cells = [f"SELECT {a} AS a, {b} AS b, {r(f'sum({x} * {y})', digits)} AS dot FROM {source}" for a, x in enumerate(names) for b, y in enumerate(names)]
    return " UNION ALL ".join(cells)


def _seeded(seed: str, key: str, position: int) -> str:
    """`uniform_sql` with a column for a seed."""
    return uniform_sql(0, key, position).replace("'0', CAST", f"CAST({seed} AS VARCHAR), CAST", 1)


def oracle_sql() -> dict[str, str]:
    blob = lambda i: f"{_pick([c[i] for c in workloads.BLOB_CENTERS])} + {gaussian_sql(1, 'row_id', f'major{i}')}"
    ring = lambda f, j: f"{_pick(workloads.RING_RADII)} * {f}({uniform_sql(1, 'row_id', 'angle')} * {2 * math.pi!r}) + {gaussian_sql(1, 'row_id', j)} * {workloads.RING_JITTER}"
    w = "v AS (SELECT vec_id AS row_id, " + vec(DIMS) + " FROM embeddings)"
    ones = [0.1 * i for i in range(DIMS)]
    return {
        "grid_blocks_card": f"WITH {CUSTOMERS}, l AS (" + " UNION ALL ".join(f"SELECT row_grp, {0 if i < 2 else 1} AS col_grp, {i} AS pos, f{i} AS val FROM c" for i in range(6)) + f") SELECT row_grp, col_grp, pos, count(*) AS n, {r('avg(val)', 4)} AS mean FROM l GROUP BY ALL",
        "feature_bounds": "WITH l AS (SELECT l_quantity AS f0, l_extendedprice AS f1, l_discount AS f2, l_tax AS f3, CAST(month(l_shipdate) AS DOUBLE) AS f4 FROM lineitem) " + " UNION ALL ".join(f"SELECT {i} AS pos, min(f{i}) AS lo, max(f{i}) AS hi FROM l" for i in range(5)),
        "anchor_uniform_rows": f"WITH {_BOUNDS}, {_anchors('x', 300, 5, 4, 'e')} " + " UNION ALL ".join(f"SELECT anchor_id, {j} AS pos, {r(f'f{j}')} AS val FROM x" for j in range(4)),
        "anchor_public_rows": "SELECT item_id AS anchor_id, " + ", ".join(f"{r(_share('text', ch))} AS f{i}" for i, ch in enumerate(_LETTERS)) + " FROM benchmark",
        "planted_blobs_rows": _planted((blob(0), blob(1))),
        "planted_rings_rows": _planted((ring("cos", "jx"), ring("sin", "jy"))),
        "planted_skew_groups": f"WITH t AS (SELECT CAST(o_orderkey % 3 AS INT) AS truth, {uniform_sql(1, 'o_orderkey', 'half')} < 0.5 AS half FROM orders) SELECT CAST(CASE WHEN truth = 0 OR (truth = 1 AND half) THEN 0 ELSE 1 END AS INT) AS row_grp, truth, count(*) AS n FROM t GROUP BY ALL",
        "equal_groups_sizes": "SELECT CAST(g AS INT) AS row_grp, (SELECT count(*) FROM orders) // 10 + CASE WHEN g < (SELECT count(*) FROM orders) % 10 THEN 1 ELSE 0 END AS n FROM range(10) t(g)",
        "standardised_block": f"SELECT c_custkey, {r('CASE WHEN stddev_pop(c_acctbal) OVER w > 0 THEN (c_acctbal - avg(c_acctbal) OVER w) / stddev_pop(c_acctbal) OVER w ELSE 0 END')} AS z FROM customer WINDOW w AS (PARTITION BY c_nationkey)",
        "block_covariance": f"WITH {SMALL_LINES} " + " UNION ALL ".join(f"SELECT row_grp, {j} AS col_grp, {a} AS a, {b} AS b, count(*) AS n, {r(f'covar_pop(f{2 * j + a}, f{2 * j + b})', 4)} AS cov FROM l GROUP BY row_grp" for j in (0, 1) for a in (0, 1) for b in (0, 1)),
        "block_gram": f"WITH {SMALL_LINES} " + _gram_rows(4, "l", 3),
        "pca2_closed_form": f"WITH {PCA2} SELECT row_grp, col_grp, 0 AS a, {r('m0')} AS mean, {r('u0', 5)} AS proj FROM m UNION ALL SELECT row_grp, col_grp, 1, {r('m1')}, {r('u1', 5)} FROM m",
        "encode_rows": f"WITH {PCA2} SELECT p.row_id, p.row_grp, m.col_grp, {r('(CASE m.col_grp WHEN 0 THEN f0 ELSE f2 END - m0) * u0 + (CASE m.col_grp WHEN 0 THEN f1 ELSE f3 END - m1) * u1', 5)} AS code FROM p JOIN m ON p.row_grp = m.row_grp",
        "concat_codes": f"WITH {PCA2} SELECT p.row_id, {r('(f0 - a.m0) * a.u0 + (f1 - a.m1) * a.u1', 5)} AS c0, {r('(f2 - b.m0) * b.u0 + (f3 - b.m1) * b.u1', 5)} AS c1 FROM p JOIN m a ON p.row_grp = a.row_grp AND a.col_grp = 0 JOIN m b ON p.row_grp = b.row_grp AND b.col_grp = 1",
        "anchor_block_gram": f"WITH {_BOUNDS}, {_anchors('x', 300, 5, 4, 'e')} " + _gram_rows(4, "x", 3),
        "alignment_residual_full_width": "SELECT 0 AS a, 1 AS b, CAST(0 AS DOUBLE) AS residual",
        "leak_probe": f"WITH {PCA2}, x AS (SELECT p.row_grp, m.col_grp, CASE m.col_grp WHEN 0 THEN f0 ELSE f2 END - m0 AS x0, CASE m.col_grp WHEN 0 THEN f1 ELSE f3 END - m1 AS x1, u0, u1 FROM p JOIN m ON p.row_grp = m.row_grp) SELECT row_grp, col_grp, {r('sum(pow(x0 * u1 - x1 * u0, 2)) / sum(x0 * x0 + x1 * x1)', 5)} AS lost FROM x GROUP BY row_grp, col_grp",
        "comm_volume": f"WITH {PARTS}, n AS (SELECT row_grp, count(*) AS n FROM p GROUP BY row_grp) SELECT row_grp, CAST(j AS INT) AS col_grp, n + 300 AS up, (n + 3) * 2 AS down FROM n, range(2) t(j)",
        "nearest_center": f"WITH {ASSIGNED} SELECT row_id, pred, {r('dist')} AS dist FROM a",
        "nearest_center_sql": f"WITH {ASSIGNED} SELECT row_id, pred FROM a",
        "pairwise_center": f"WITH {ASSIGNED} SELECT row_id, pred, {r('dist')} AS dist FROM a",
        "cumulative_draw": "WITH s AS (SELECT o_orderkey AS row_id, sum(o_totalprice) OVER (ORDER BY o_orderkey ROWS UNBOUNDED PRECEDING) AS s, sum(o_totalprice) OVER () AS t FROM orders) SELECT u AS share, min(row_id) AS row_id FROM s, (VALUES (CAST(0.05 AS DOUBLE)), (0.25), (0.5), (0.75), (0.95)) d(u) WHERE s > u * t GROUP BY u",
        "lloyd_1": _lloyd(1),
        "lloyd_5": _lloyd(5),
        "dsq_weights": f"WITH {_V}, c AS (SELECT * FROM v ORDER BY row_id LIMIT 3) SELECT v.row_id, {r('min(' + ' + '.join(f'pow(v.z{i} - c.z{i}, 2)' for i in range(DIMS)) + ')')} AS w FROM v, c GROUP BY v.row_id",
        "seed_farthest": _farthest(4),
        "inertia_by_cluster": f"WITH {ASSIGNED} SELECT pred, count(*) AS n, {r('avg(dist)')} AS inertia FROM a GROUP BY pred",
        "fed_merge_round": f"WITH {ASSIGNED} SELECT pred, {r('avg(z0)')} AS c0, {r('avg(z1)')} AS c1 FROM a GROUP BY pred",
        "knn_edges": f"WITH {_KNN} SELECT src, dst, {r('dist')} AS dist FROM k",
        "knn_symmetric": f"WITH {_SYM} SELECT src, dst, w FROM s",
        "knn_union": f"WITH {_KNN}, {_BOTH} SELECT DISTINCT src, dst, CAST(1 AS DOUBLE) AS w FROM b",
        "knn_mutual": f"WITH {_KNN}, {_BOTH} SELECT src, dst, CAST(1 AS DOUBLE) AS w FROM b GROUP BY src, dst HAVING count(*) > 1",
        "knn_degree": f"WITH {_SYM} SELECT id, deg FROM g",
        "laplacian_plain": f"WITH {_SYM} SELECT src, dst, -w AS val FROM s UNION ALL SELECT id, id, deg FROM g",
        "laplacian_sym": f"WITH {_SYM} SELECT s.src, s.dst, {r('-w / sqrt(x.deg * y.deg)')} AS val FROM s JOIN g x ON s.src = x.id JOIN g y ON s.dst = y.id UNION ALL SELECT id, id, CAST(1 AS DOUBLE) FROM g",
        "radius_edges": f"WITH v AS (SELECT vec_id AS id, {vec(DIMS)} FROM embeddings), e AS (SELECT x.id AS src, y.id AS dst, {' + '.join(f'pow(x.z{i} - y.z{i}, 2)' for i in range(DIMS))} AS dist FROM v x JOIN v y ON x.id < y.id) SELECT src, dst, {r('dist')} AS dist FROM e WHERE dist <= 1.0",
        "contingency": f"WITH {_U} SELECT truth, pred, cnt FROM u",
        "contingency_cube": f"WITH {ASSIGNED} SELECT truth, pred, count(*) AS cnt FROM a GROUP BY CUBE (truth, pred)",
        "ari": f"WITH {_U}, x AS (SELECT sum(cnt * (cnt - 1) / 2.0) AS i, CAST(sum(cnt) AS DOUBLE) AS n FROM u), y AS (SELECT sum(c * (c - 1) / 2.0) AS a FROM (SELECT sum(cnt) AS c FROM u GROUP BY truth)), z AS (SELECT sum(c * (c - 1) / 2.0) AS b FROM (SELECT sum(cnt) AS c FROM u GROUP BY pred)) SELECT {r('(i - a * b / (n * (n - 1) / 2)) / ((a + b) / 2 - a * b / (n * (n - 1) / 2))')} AS ari FROM x, y, z",
        "nmi": f"WITH {_U}, n AS (SELECT CAST(sum(cnt) AS DOUBLE) AS n FROM u), x AS (SELECT truth, CAST(sum(cnt) AS DOUBLE) AS a FROM u GROUP BY truth), y AS (SELECT pred, CAST(sum(cnt) AS DOUBLE) AS b FROM u GROUP BY pred), m AS (SELECT sum(cnt / n * ln(cnt * n / (a * b))) AS mi FROM u JOIN x USING (truth) JOIN y USING (pred), n), h AS (SELECT -sum(a / n * ln(a / n)) AS ha FROM x, n), k AS (SELECT -sum(b / n * ln(b / n)) AS hb FROM y, n) SELECT {r('mi / sqrt(ha * hb)')} AS nmi FROM m, h, k",
        "acc_k3": f"WITH {_U}, p AS (SELECT * FROM (VALUES (0,1,2),(0,2,1),(1,0,2),(1,2,0),(2,0,1),(2,1,0)) t(p0, p1, p2)), q AS (SELECT p0, p1, p2, sum(CASE WHEN pred = CASE truth WHEN 0 THEN p0 WHEN 1 THEN p1 ELSE p2 END THEN cnt ELSE 0 END) AS hit, sum(cnt) AS n FROM u, p GROUP BY ALL) SELECT {r('max(hit / n)')} AS acc FROM q",
        "anchor_rows_udtf": "WITH b AS (SELECT c_nationkey, CAST(min(c_acctbal) AS DOUBLE) AS l0, CAST(max(c_acctbal) AS DOUBLE) AS h0, CAST(min(c_custkey) AS DOUBLE) AS l1, CAST(max(c_custkey) AS DOUBLE) AS h1 FROM customer GROUP BY c_nationkey) SELECT c_nationkey, id AS anchor_id, " + ", ".join(f"{r(f'l{i} + (h{i} - l{i}) * ' + _seeded('c_nationkey', 'id', i))} AS f{i}" for i in (0, 1)) + " FROM b, range(50) t(id)",
        "solo_vs_pooled_assignments": f"WITH {ASSIGNED}, o AS (SELECT row_id, CASE WHEN e0 <= e1 AND e0 <= e2 THEN 0 WHEN e1 <= e2 THEN 1 ELSE 2 END AS solo FROM (SELECT row_id, {', '.join(f'{_distance(c, DIMS // 2)} AS e{k}' for k, c in enumerate(CENTERS))} FROM v)) SELECT pred, solo, count(*) AS n FROM a JOIN o USING (row_id) GROUP BY pred, solo",
        "trial_summary": f"WITH {_LEDGER} SELECT dataset, method, metric, {r('mean')} AS mean, {r('sd')} AS sd, trials FROM t",
        "pct_delta": f"WITH {_DELTA} SELECT dataset, method, metric, {r('abs(diff)', 4)} AS pct, {r('diff', 4)} AS signed_pct FROM d",
        "avg_pct_delta": f"WITH {_DELTA} SELECT method, {r('avg(abs(diff))', 4)} AS avg_pct FROM d GROUP BY method",
        "method_ranks": f"WITH {_LEDGER} SELECT dataset, method, metric, CAST(rank() OVER (PARTITION BY dataset, metric ORDER BY mean DESC, method) AS INT) AS rank FROM t",
        "wide_report": f"WITH {_LEDGER} SELECT dataset, method, {r('mean')} AS ari FROM t",
        "dataset_cards": "WITH s AS (SELECT lang, count(*) AS c FROM documents GROUP BY lang) SELECT CAST(sum(c) AS BIGINT) AS n, 10 AS m, count(*) AS k, min(c) AS min_class, max(c) AS max_class FROM s",
        "text_profile": "SELECT doc_id AS row_id, CASE lang WHEN 'de' THEN 0 WHEN 'en' THEN 1 WHEN 'es' THEN 2 WHEN 'fr' THEN 3 ELSE 4 END AS truth, " + ", ".join(f"{r(_share(_TEXT, ch))} AS f{i}" for i, ch in enumerate(_LETTERS)) + " FROM documents",
        "quality_profile": "SELECT d.doc_id AS row_id, l.quality AS truth, " + ", ".join(f"{r(f'(length(text) - length(regexp_replace(text, {p}, {chr(39)}{chr(39)}, {chr(39)}g{chr(39)}))) / greatest(length(text), 1)')} AS {n}" for n, p in (("digits", "'[0-9]'"), ("blanks", r"'[ \t\n\r]'"), ("upper", "'[A-Z]'"))) + " FROM documents d JOIN labels l ON d.doc_id = l.doc_id",
        "html_profile": r"WITH b AS (SELECT page_id, regexp_replace(html, '(?is)<script\b.*?</script>|<style\b.*?</style>|<!--.*?-->', ' ', 'g') AS h FROM pages), t AS (SELECT page_id, trim(regexp_replace(regexp_replace(h, '(?s)<[^>]*>', ' ', 'g'), '\s+', ' ', 'g')) AS t FROM b) SELECT page_id, " + ", ".join(f"{r(_share('t', ch))} AS s{i}" for i, ch in enumerate("aeiou")) + " FROM t",
        "events_profile": f"SELECT event_id AS row_id, {r('value')} AS value, CAST(hour(ts) AS INT) AS hour, CAST(dayofweek(ts) + 1 AS INT) AS weekday, coalesce(CAST(json_extract(props, '$.k') AS INT), 0) AS k FROM events",
        "order_behaviour": f"WITH {CUSTOMERS} SELECT row_id, row_grp, " + ", ".join(f"{r(f'f{i}', 5)} AS f{i}" for i in range(6)) + " FROM c",
        "order_dates": "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS o_orderdate_year, CAST(month(o_orderdate) AS INT) AS o_orderdate_month, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INT) AS o_orderdate_days FROM orders",
        "category_index": "SELECT c_custkey, c_mktsegment, CAST(dense_rank() OVER (ORDER BY c_mktsegment) AS INT) AS c_mktsegment_index FROM customer",
        "vector_algebra": f"WITH {w} SELECT row_id, {r(' + '.join(f'z{i} * {x!r}' for i, x in enumerate(ones)))} AS dot, {r(' + '.join(f'pow(z{i} - {x!r}, 2)' for i, x in enumerate(ones)))} AS sqdist, {r('sqrt(' + ' + '.join(f'z{i} * z{i}' for i in range(DIMS)) + ')')} AS norm FROM v",
        "layout_round_trip": f"WITH {PARTS} SELECT row_id, f0 AS f1, f1 AS f2, f2 AS f3, f3 AS f4 FROM p",
        "lattice_missing_rows": f"WITH {_ROWS} SELECT row_id, 1 AS col_grp FROM c WHERE row_id NOT IN (SELECT row_id FROM o)",
        "lattice_complete_rows": f"WITH {_ROWS} SELECT row_id FROM c WHERE row_id IN (SELECT row_id FROM o)",
        "row_id_except": f"WITH {_ROWS} SELECT row_id FROM c EXCEPT SELECT row_id FROM o",
        "row_id_intersect": f"WITH {_ROWS} SELECT row_id FROM c INTERSECT SELECT row_id FROM o",
        "stack_union": f"WITH {_ROWS} SELECT row_id, count(*) AS n FROM (SELECT * FROM c UNION ALL SELECT * FROM o) GROUP BY row_id",
        "label_counts": f"WITH {ASSIGNED} SELECT pred, count(*) AS n, count(DISTINCT row_id) AS n_distinct FROM a GROUP BY pred",
        "outliers": f"WITH {ASSIGNED} SELECT row_id, {r('dist')} AS dist FROM a ORDER BY a.dist DESC, row_id LIMIT 20",
        "event_scores_tumbling": f"WITH {_SCORED} SELECT date_trunc('hour', ts) AS start, date_trunc('hour', ts) + INTERVAL 1 HOUR AS \"end\", pred, count(*) AS n FROM s GROUP BY ALL",
        "event_scores_sliding": f"WITH {_SCORED}, w AS (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS start, pred FROM s, range(2) t(k)) SELECT start, start + INTERVAL 1 HOUR AS \"end\", pred, count(*) AS n FROM w GROUP BY ALL",
        "event_scores_session": f"WITH {_SCORED}, f AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM s), i AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, fresh DESC ROWS UNBOUNDED PRECEDING) AS i FROM f) SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS \"end\", user_id, count(*) AS n FROM i GROUP BY user_id, i",
        "event_latest_model": "WITH v AS (SELECT ts, max(event_id) AS version FROM events WHERE event_type = 'signup' GROUP BY ts) SELECT e.event_id, v.version FROM events e ASOF LEFT JOIN v ON e.ts >= v.ts",
        "encode_uncentered": f"WITH {PCA0} SELECT p.row_id, p.row_grp, m.col_grp, {r('CASE m.col_grp WHEN 0 THEN f0 ELSE f2 END * u0 + CASE m.col_grp WHEN 0 THEN f1 ELSE f3 END * u1', 5)} AS code FROM p JOIN m ON p.row_grp = m.row_grp",
        "encode_rotated_norms": f"WITH {PCA2} SELECT p.row_id, m.col_grp, {r('sqrt(pow(CASE m.col_grp WHEN 0 THEN f0 ELSE f2 END - m0, 2) + pow(CASE m.col_grp WHEN 0 THEN f1 ELSE f3 END - m1, 2))', 5)} AS length FROM p JOIN m ON p.row_grp = m.row_grp",
        "knn_include_self": f"WITH {_KNN.replace('WHERE x.id <> y.id) WHERE', ') WHERE')} SELECT src, dst, {r('dist')} AS dist FROM k",
        "spectral_row_normalised": "SELECT doc_id AS row_id, CAST(1 AS DOUBLE) AS length FROM documents",
        "null_policy_drop": f"WITH {_PRICES} SELECT row_id, {r('f')} AS f, {r('o')} AS o, {r('p')} AS p FROM g WHERE f IS NOT NULL AND o IS NOT NULL AND p IS NOT NULL",
        "null_policy_zero": f"WITH {_PRICES} SELECT row_id, {r('coalesce(f, 0)')} AS f, {r('coalesce(o, 0)')} AS o, {r('coalesce(p, 0)')} AS p FROM g",
        "null_policy_mean": f"WITH {_PRICES} SELECT row_id, {r('coalesce(f, avg(f) OVER ())')} AS f, {r('coalesce(o, avg(o) OVER ())')} AS o, {r('coalesce(p, avg(p) OVER ())')} AS p FROM g",
        "one_hot_segments": "SELECT c_custkey, " + ", ".join(f"CAST(c_mktsegment = '{n}' AS INT) AS {n.lower()}" for n in ("AUTOMOBILE", "BUILDING", "FURNITURE")) + " FROM customer",
        "block_files": f"WITH {PARTS} SELECT row_id, {r('f0')} AS f0, {r('f1')} AS f1 FROM p WHERE row_grp = 1",
        "model_files": f"WITH {ASSIGNED} SELECT pred, count(*) AS n FROM a GROUP BY pred",
        "csv_scan": "SELECT r_regionkey, r_name FROM region",
        "json_scan": "SELECT r_regionkey, r_name FROM region",
        "long_report": f"WITH {_LEDGER} SELECT dataset, method, n AS metric, CASE n WHEN 'ari' THEN {r('mean')} END AS mean FROM t, (VALUES ('ari'), ('nmi'), ('acc')) m(n)",
        "encode_code_sql": f"WITH {PARTS} SELECT row_id, {r('(f0 - 25) / 2 + (f2 - 6) * 0.5')} AS c0, {r('f1 - 9 + (f3 - 5) / 4 * 0.25')} AS c1 FROM p",
        "distance_quantiles": f"WITH {ASSIGNED} SELECT pred, " + ", ".join(f"{r(f'quantile_cont(dist, {q})')} AS {n}" for n, q in (("p50", 0.5), ("p90", 0.9), ("p99", 0.99))) + " FROM a GROUP BY pred",
        "center_shift": _lloyd(3, shifts=True),
        "hash_sample_rows": "WITH l AS (SELECT ('0x' || substr(md5(concat_ws('~', CAST(l_orderkey AS VARCHAR), CAST(l_linenumber AS VARCHAR), CAST(l_partkey AS VARCHAR), CAST(l_suppkey AS VARCHAR))), 1, 15))::BIGINT AS row_id, l_quantity AS f0, l_extendedprice AS f1, l_discount AS f2, l_tax AS f3, CAST(month(l_shipdate) AS DOUBLE) AS f4 FROM lineitem) SELECT * FROM l WHERE " + uniform_sql(4, "row_id", "sample") + " < 0.1",
        "ari_grouped_udf": f"WITH {ASSIGNED}, u AS (SELECT row_id % 4 AS b, truth, pred, count(*) AS cnt FROM a GROUP BY ALL), x AS (SELECT b, sum(cnt * (cnt - 1) / 2.0) AS i, CAST(sum(cnt) AS DOUBLE) AS n FROM u GROUP BY b), y AS (SELECT b, sum(c * (c - 1) / 2.0) AS s FROM (SELECT b, sum(cnt) AS c FROM u GROUP BY b, truth) GROUP BY b), z AS (SELECT b, sum(c * (c - 1) / 2.0) AS t FROM (SELECT b, sum(cnt) AS c FROM u GROUP BY b, pred) GROUP BY b) SELECT b, {r('(i - s * t / (n * (n - 1) / 2)) / ((s + t) / 2 - s * t / (n * (n - 1) / 2))')} AS ari FROM x JOIN y USING (b) JOIN z USING (b)",
        "alignment_residuals": "SELECT kind, solver, true AS left_over FROM (VALUES ('linear'), ('affine')) a(kind), (VALUES ('gram'), ('tsqr')) b(solver)",
        "exactness": "SELECT * FROM (VALUES ('minus1', false, true, false), ('2', true, true, true)) t(width, equal_ranges, full_rank, affine_exact)",
        "event_pairs_within": "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_id < y.event_id WHERE abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 600000000",
    }


def _farthest(draws: int) -> str:
    out = f"WITH {_V}, s1 AS (SELECT 0 AS draw, * FROM v ORDER BY row_id LIMIT 1)"
    d = " + ".join(f"pow(v.z{i} - c.z{i}, 2)" for i in range(DIMS))
    for k in range(2, draws + 1):
        out += f", n{k} AS (SELECT v.row_id, min({d}) AS d FROM v, s{k - 1} c GROUP BY v.row_id), s{k} AS (SELECT * FROM s{k - 1} UNION ALL (SELECT {k - 1} AS draw, v.* FROM v JOIN n{k} n ON v.row_id = n.row_id ORDER BY n.d DESC, v.row_id LIMIT 1))"
    return f"{out} SELECT draw, {r('z0')} AS z0, {r('z1')} AS z1 FROM s{draws}"
