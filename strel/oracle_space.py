"""More of the methods as plain SQL: merge trees of graphs, map tests, planted series, warping.

Composed like ``strel.oracle``: strings of CTEs that read those before them.
"""

from __future__ import annotations

from strel import oracle as O
from strel.operators.permute import grow_map

NATIONS = """SELECT CAST(a.n_nationkey AS VARCHAR) AS a, CAST(b.n_nationkey AS VARCHAR) AS b FROM nation a, nation b
  WHERE abs(a.n_nationkey // 5 - b.n_nationkey // 5) + abs(a.n_nationkey % 5 - b.n_nationkey % 5) = 1"""
REGIONS = "SELECT CAST(a.r_regionkey AS VARCHAR) AS a, CAST(b.r_regionkey AS VARCHAR) AS b FROM region a, region b WHERE abs(a.r_regionkey - b.r_regionkey) = 1"
NOWHERE = "SELECT '0' AS a, '0' AS b WHERE false"


def graph(links: str) -> str:
    """From ``fn`` and links of regions: ``px`` (points ranked from high to low), ``meet`` (for every
    point the components of higher points that touch it), ``pairs`` and ``tree``.

    A component is followed by walking over higher points only: quadratic, for small functions.
    """
    return f""",
adj AS ({links}),
px AS (SELECT function_id, side, region, t, value, row_number() OVER (PARTITION BY function_id, side ORDER BY x DESC, t, CAST(region AS INT)) AS k
  FROM (SELECT *, 'join' AS side, value AS x FROM fn UNION ALL SELECT *, 'split', -value FROM fn)),
touch AS (SELECT p.function_id, p.side, p.k, q.k AS u FROM px p JOIN px q ON q.function_id = p.function_id AND q.side = p.side AND q.region = p.region AND abs(q.t - p.t) = 1
  UNION ALL SELECT p.function_id, p.side, p.k, q.k FROM px p JOIN adj ON adj.a = p.region JOIN px q ON q.function_id = p.function_id AND q.side = p.side AND q.region = adj.b AND q.t = p.t),
reach AS (WITH RECURSIVE cl AS (SELECT function_id, side, k, u, u AS w FROM touch WHERE u < k
    UNION SELECT c.function_id, c.side, c.k, c.u, n.u FROM cl c JOIN touch n ON n.function_id = c.function_id AND n.side = c.side AND n.k = c.w WHERE n.u < c.k) SELECT * FROM cl),
meet AS (SELECT DISTINCT function_id, side, k, head, oldest FROM (SELECT *, min(head) OVER (PARTITION BY function_id, side, k) AS oldest FROM (SELECT function_id, side, k, u, min(w) AS head FROM reach GROUP BY ALL))),
peak AS (SELECT px.* FROM px WHERE NOT EXISTS (SELECT 1 FROM meet m WHERE m.function_id = px.function_id AND m.side = px.side AND m.k = px.k)),
saddle AS (SELECT function_id, side, k FROM meet GROUP BY ALL HAVING count(*) > 1),
dies AS (SELECT function_id, side, head AS c, k AS d, false AS essential FROM meet WHERE head <> oldest
  UNION ALL SELECT function_id, side, min(k), max(k), true FROM px GROUP BY ALL),
pairs AS (SELECT d.function_id, d.side, c.region AS creator_region, c.t AS creator_t, e.region AS destroyer_region, e.t AS destroyer_t, c.value AS birth, e.value AS death, abs(c.value - e.value) AS persistence, essential
  FROM dies d JOIN px c ON c.function_id = d.function_id AND c.side = d.side AND c.k = d.c JOIN px e ON e.function_id = d.function_id AND e.side = d.side AND e.k = d.d),
node AS (SELECT function_id, side, k FROM peak UNION SELECT function_id, side, k FROM saddle),
link AS (SELECT r.function_id, r.side, max(r.w) AS upper, r.k AS lower FROM reach r JOIN saddle USING (function_id, side, k) JOIN node n ON n.function_id = r.function_id AND n.side = r.side AND n.k = r.w
  JOIN (SELECT function_id, side, k, u, min(w) AS head FROM reach GROUP BY ALL) h ON h.function_id = r.function_id AND h.side = r.side AND h.k = r.k AND h.u = r.u GROUP BY r.function_id, r.side, r.k, h.head),
foot AS (SELECT n.function_id, n.side, max(n.k) AS upper, l.low AS lower FROM node n JOIN (SELECT function_id, side, max(k) AS low FROM px GROUP BY ALL) l USING (function_id, side) GROUP BY n.function_id, n.side, l.low HAVING max(n.k) <> l.low),
tree AS (SELECT x.function_id, x.side, a.region AS upper_region, a.t AS upper_t, b.region AS lower_region, b.t AS lower_t FROM (SELECT * FROM link UNION ALL SELECT * FROM foot) x
  JOIN px a ON a.function_id = x.function_id AND a.side = x.side AND a.k = x.upper JOIN px b ON b.function_id = x.function_id AND b.side = x.side AND b.k = x.lower)"""


def grown_maps(near: dict[str, list[str]], n_maps: int, seed: int = 11) -> str:
    """CTE ``maps``: the library's maps of a graph as rows."""
    rows = [f"({k}, '{r}', '{to}')" for k in range(1, n_maps + 1) for r, to in sorted(grow_map(near, sorted(near), seed * 1_000_003 + k).items())]
    return ",\nmaps AS (SELECT * FROM (VALUES " + ", ".join(rows) + ") v(k, region, image))"


def lattice_links(rows: int, cols: int) -> dict[str, list[str]]:
    """Neighbours on a lattice numbered row by row."""
    at = [(i, j) for i in range(rows) for j in range(cols)]
    return {str(i * cols + j): [str(x * cols + y) for x, y in ((i - 1, j), (i + 1, j), (i, j - 1), (i, j + 1)) if (x, y) in at] for i, j in at}


_P = """ob AS (SELECT left_fn, right_fn, feature_type, n_perm, s AS obs FROM st WHERE k = 0),
nl AS (SELECT o.left_fn, o.right_fn, o.feature_type, count(s) AS present, count(*) FILTER (s >= obs) AS ge, count(*) FILTER (s <= obs) AS le
  FROM ob o LEFT JOIN st ON st.left_fn = o.left_fn AND st.right_fn = o.right_fn AND st.feature_type = o.feature_type AND st.k <> 0 GROUP BY ALL),
test AS (SELECT left_fn, right_fn, feature_type, n_perm, obs, (CASE WHEN obs < 0 THEN le ELSE ge + CASE WHEN obs <= 0 THEN n_perm - present ELSE 0 END END) / n_perm AS p_value
  FROM ob JOIN nl USING (left_fn, right_fn, feature_type) WHERE n_perm > 0)"""
_SIGNS = "count(*) AS nc, count(*) FILTER (a.pos AND b.pos OR a.neg AND b.neg) AS np, count(*) FILTER (a.pos AND b.neg OR a.neg AND b.pos) AS nn"

#: CTE ``test`` from ``cand``, ``pts`` and ``maps``: maps of the regions of the second function.
MAP_TEST = f""",
co AS (SELECT left_fn, right_fn, a.feature_type, a.region AS r1, b.region AS r2, {_SIGNS}
  FROM cand JOIN pts a ON a.function_id = left_fn AND a.t BETWEEN lo AND hi JOIN pts b ON b.function_id = right_fn AND b.feature_type = a.feature_type AND b.t = a.t GROUP BY ALL),
st AS (SELECT left_fn, right_fn, feature_type, k, (SELECT count(DISTINCT k) FROM maps) AS n_perm, round((sum(np) - sum(nn)) / sum(nc), 9) AS s
  FROM co JOIN (SELECT k, region, image FROM maps UNION ALL SELECT DISTINCT 0, region, region FROM maps) m ON m.region = co.r2 AND m.image = co.r1 GROUP BY ALL),
{_P}"""

#: The same with every rotation in time as well.
TORUS_TEST = f""",
co AS (SELECT left_fn, right_fn, a.feature_type, lo, hi, a.region AS r1, b.region AS r2, ((a.t - b.t) % (hi - lo + 1) + (hi - lo + 1)) % (hi - lo + 1) AS lag, {_SIGNS}
  FROM cand JOIN pts a ON a.function_id = left_fn AND a.t BETWEEN lo AND hi JOIN pts b ON b.function_id = right_fn AND b.feature_type = a.feature_type AND b.t BETWEEN lo AND hi GROUP BY ALL),
st AS (SELECT left_fn, right_fn, feature_type, m.k * (hi - lo + 1) + lag AS k, ((SELECT count(DISTINCT k) FROM maps) + 1) * (hi - lo + 1) - 1 AS n_perm, round((sum(np) - sum(nn)) / sum(nc), 9) AS s
  FROM co JOIN (SELECT k, region, image FROM maps UNION ALL SELECT DISTINCT 0, region, region FROM maps) m ON m.region = co.r2 AND m.image = co.r1 GROUP BY left_fn, right_fn, feature_type, lo, hi, m.k, lag),
{_P}"""


def step_test(n_perm: int, block: int) -> str:
    """CTE ``test``: blocks of steps of the second function dealt anew by md5."""
    return f""",
bl AS (SELECT c.*, unnest(generate_series(0, (hi - lo) // {block})) AS b FROM (SELECT DISTINCT lo, hi FROM cand) c),
bk AS (SELECT lo, hi, k, b, row_number() OVER (PARTITION BY lo, hi, k ORDER BY md5('perm:' || k || ':' || b), b) - 1 AS place, least({block}, hi - lo + 1 - b * {block}) AS size FROM bl, (SELECT unnest(generate_series(1, {n_perm})) AS k)),
bs AS (SELECT *, lo + coalesce(sum(size) OVER (PARTITION BY lo, hi, k ORDER BY place ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start FROM bk),
mv AS (SELECT lo, hi, k, lo + b * {block} + i AS t, CAST(start + i AS BIGINT) AS image FROM (SELECT *, unnest(generate_series(0, size - 1)) AS i FROM bs)),
co AS (SELECT left_fn, right_fn, a.feature_type, m.k, {_SIGNS} FROM cand c
  JOIN pts b ON b.function_id = right_fn AND b.t BETWEEN c.lo AND c.hi
  JOIN (SELECT * FROM mv UNION ALL SELECT DISTINCT lo, hi, 0, t, t FROM mv) m ON m.lo = c.lo AND m.hi = c.hi AND m.t = b.t
  JOIN pts a ON a.function_id = left_fn AND a.feature_type = b.feature_type AND a.region = b.region AND a.t = m.image GROUP BY ALL),
st AS (SELECT left_fn, right_fn, feature_type, k, {n_perm} AS n_perm, round((np - nn) / nc, 9) AS s FROM co),
{_P}"""


#: CTE ``dtw`` from ``al`` (left_fn, right_fn, t, x, y): warping distance by anti-diagonals of the cost table.
WARP = """,
zs AS (SELECT left_fn, right_fn, t, (x - avg(x) OVER w) / stddev_pop(x) OVER w AS x, (y - avg(y) OVER w) / stddev_pop(y) OVER w AS y FROM al WINDOW w AS (PARTITION BY left_fn, right_fn)),
ser AS (SELECT left_fn, right_fn, list(x ORDER BY t) AS x, list(y ORDER BY t) AS y, count(*) AS n, sum(abs(x)) + sum(abs(y)) AS zero FROM zs GROUP BY ALL),
dtw AS (WITH RECURSIVE diag AS (
    SELECT left_fn, right_fn, 1 AS d, list_concat([0.0], list_transform(range(n), lambda i: CAST('inf' AS DOUBLE))) AS p2, list_transform(range(n + 1), lambda i: CAST('inf' AS DOUBLE)) AS p1 FROM ser
    UNION ALL SELECT g.left_fn, g.right_fn, g.d + 1, g.p1, list_transform(range(s.n + 1), lambda i: CASE WHEN i >= 1 AND g.d + 1 - i BETWEEN 1 AND s.n THEN abs(s.x[i] - s.y[g.d + 1 - i]) + least(g.p1[i], g.p1[i + 1], g.p2[i]) ELSE CAST('inf' AS DOUBLE) END)
    FROM diag g JOIN ser s USING (left_fn, right_fn) WHERE g.d < 2 * s.n)
  SELECT s.left_fn, s.right_fn, 1 - g.p1[s.n + 1] / s.zero AS dtw FROM diag g JOIN ser s USING (left_fn, right_fn) WHERE g.d = 2 * s.n)"""


def related(fn: str, time: str, links: str, test: str, seasonal: bool = True) -> tuple[str, ...]:
    """The whole chain over a graph of regions, from ``fn`` to ``test``."""
    return (fn, graph(links), O.thresholds(time, seasonal), O.points(time, seasonal), O.RELATION, test)


def both(*parts: str) -> str:
    """Rows of several whole queries."""
    return " UNION ALL ".join(f"SELECT * FROM ({p})" for p in parts)
