"""The methods once more as plain SQL, composed from common table expressions.

Used as the independent side of the correctness check: each piece is a string of CTEs that reads
those before it.
"""

from __future__ import annotations

DAY = "date_diff('day', DATE '1970-01-01', CAST({c} AS DATE))"
STEP = {
    "hour": f"CAST({DAY} * 24 + hour({{c}}) AS INTEGER)",
    "day": f"CAST({DAY} AS INTEGER)",
    "week": f"CAST(floor(({DAY} - 4) / 7.0) AS INTEGER)",
    "month": "CAST((year({c}) - 1970) * 12 + month({c}) - 1 AS INTEGER)",
}
SEASON = {
    "hour": "CAST((year(DATE '1970-01-01' + CAST({t} // 24 AS INTEGER)) - 1970) * 12 + month(DATE '1970-01-01' + CAST({t} // 24 AS INTEGER)) - 1 AS INTEGER)",
    "day": "CAST((year(DATE '1970-01-01' + {t}) - 1970) * 4 + quarter(DATE '1970-01-01' + {t}) - 1 AS INTEGER)",
    "week": "0",
    "month": "0",
}
SETS = {
    "orders": ("(SELECT o.*, c_nationkey, c_nationkey % 5 AS c_regionkey, c_mktsegment FROM orders o LEFT JOIN customer ON o_custkey = c_custkey)", "o_orderdate", ("o_custkey",), ("o_totalprice",), {"nation": "c_nationkey", "region": "c_regionkey", "segment": "c_mktsegment"}),
    "lineitem": ("(SELECT l.*, s_nationkey, s_nationkey % 5 AS s_regionkey FROM lineitem l LEFT JOIN supplier ON l_suppkey = s_suppkey)", "l_shipdate", ("l_suppkey", "l_partkey"), ("l_quantity", "l_extendedprice", "l_discount", "l_tax"), {"nation": "s_nationkey", "region": "s_regionkey"}),
    "events": ("(SELECT e.*, CAST(json_extract(props, '$.k') AS DOUBLE) AS k, c_nationkey, c_nationkey % 5 AS c_regionkey, c_mktsegment FROM events e LEFT JOIN customer ON user_id = c_custkey)", "ts", ("user_id",), ("value", "k"), {"nation": "c_nationkey", "region": "c_regionkey", "segment": "c_mktsegment"}),
}
TAGS = {f"orders_{s}": ("orders", f"o_orderstatus = '{s}'") for s in "FOP"} | {f"lineitem_{s}": ("lineitem", f"l_returnflag = '{s}'") for s in "ANR"}


def step(col: str, res: str) -> str:
    return STEP[res].replace("{c}", col)


def raw(name: str, space: str, time: str, measures: tuple[str, ...] | None = None) -> str:
    """One SELECT for each measure of a data set: function_id, region, t, value."""
    base, cond = TAGS.get(name, (name, "true"))
    src, when, ids, attrs, places = SETS[base]
    region = "'0'" if space == "world" else f"CAST({places[space]} AS VARCHAR)"
    every = {"density": "CAST(count(*) AS DOUBLE)"}
    every |= {f"unique({c})": f"CAST(count(DISTINCT {c}) AS DOUBLE)" for c in ids}
    every |= {f"avg({c})": f"sum(CAST(round({c} * 100) AS BIGINT)) / count({c}) / 100" for c in attrs}
    parts = [
        f"SELECT '{name}.{m}' AS function_id, {region} AS region, {step(when, time)} AS t, {e} AS value FROM {src} AS s WHERE {cond} GROUP BY ALL"
        for m, e in every.items() if measures is None or m in measures
    ]
    return " UNION ALL ".join(parts)


def functions(names: tuple[str, ...], space: str, time: str, measures: tuple[str, ...] | None = None) -> str:
    """CTE ``fn``: dense functions, empty points 0 for counts and carried for the rest."""
    return f"""raw AS ({" UNION ALL ".join(raw(n, space, time, measures) for n in names)}),
sp AS (SELECT function_id, min(t) AS lo, max(t) AS hi FROM raw GROUP BY function_id),
gr AS (SELECT r.function_id, r.region, unnest(generate_series(lo, hi)) AS t FROM (SELECT DISTINCT function_id, region FROM raw) r JOIN sp USING (function_id)),
fn AS (SELECT g.function_id, g.region, CAST(g.t AS INTEGER) AS t,
  coalesce(raw.value, CASE WHEN regexp_matches(g.function_id, '\\.(density|unique)') THEN 0.0 ELSE coalesce(
    last_value(raw.value IGNORE NULLS) OVER (PARTITION BY g.function_id, g.region ORDER BY g.t ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW),
    first_value(raw.value IGNORE NULLS) OVER (PARTITION BY g.function_id, g.region ORDER BY g.t ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)) END) AS value
  FROM gr g LEFT JOIN raw ON raw.function_id = g.function_id AND raw.region = g.region AND raw.t = g.t)"""


#: CTE ``pairs`` from ``fn``, for functions of time alone.
PAIRS = """,
px AS (SELECT function_id, 'join' AS side, t, value, value AS x FROM fn UNION ALL SELECT function_id, 'split', t, value, -value FROM fn),
pn AS (SELECT *, lag(x) OVER w AS l, lead(x) OVER w AS r FROM px WINDOW w AS (PARTITION BY function_id, side ORDER BY t)),
pk AS (SELECT function_id, side, t, value, x FROM pn WHERE (l IS NULL OR x > l) AND (r IS NULL OR x >= r)),
wl AS (SELECT k.function_id, k.side, k.t, k.value, k.x, max(q.t) FILTER (q.t < k.t AND q.x >= k.x) AS lt, min(q.t) FILTER (q.t > k.t AND q.x > k.x) AS rt
  FROM pk k JOIN px q ON q.function_id = k.function_id AND q.side = k.side GROUP BY ALL),
fl AS (SELECT k.function_id, k.side, k.t, k.value, k.lt, k.rt, min(q.x) FILTER (q.t BETWEEN k.lt AND k.t) AS xl, min(q.x) FILTER (q.t BETWEEN k.t AND k.rt) AS xr, min(q.x) AS xb
  FROM wl k JOIN px q ON q.function_id = k.function_id AND q.side = k.side GROUP BY ALL),
dx AS (SELECT *, coalesce(CASE WHEN xl >= xr THEN xl WHEN xr > xl THEN xr END, xl, xr, xb) AS xd FROM fl),
pairs AS (SELECT function_id, side, t AS creator_t, value AS birth, CASE WHEN side = 'join' THEN xd ELSE -xd END AS death,
  abs(value - CASE WHEN side = 'join' THEN xd ELSE -xd END) AS persistence, lt IS NULL AND rt IS NULL AS essential FROM dx)"""


def thresholds(time: str, seasonal: bool = True) -> str:
    """CTEs ``high``, ``salient`` and ``extreme`` from ``pairs``."""
    season = SEASON[time].replace("{t}", "creator_t") if seasonal else "0"
    return f""",
ps AS (SELECT *, {season} AS season FROM pairs),
tm AS (SELECT function_id, side, season, persistence, count(*) AS c FROM ps GROUP BY ALL),
tc AS (SELECT *, sum(c) OVER w AS n, sum(c * persistence) OVER w AS s, sum(c * persistence * persistence) OVER w AS q,
  sum(c) OVER a AS na, sum(c * persistence) OVER a AS sa, sum(c * persistence * persistence) OVER a AS qa FROM tm
  WINDOW w AS (PARTITION BY function_id, side, season ORDER BY persistence ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), a AS (PARTITION BY function_id, side, season)),
tk AS (SELECT function_id, side, season, persistence, round((q - s * s / n) + (qa - q - (sa - s) * (sa - s) / (na - n)), 6) AS cost FROM tc WHERE n < na),
tb AS (SELECT function_id, side, season, persistence AS cut FROM tk QUALIFY row_number() OVER (PARTITION BY function_id, side, season ORDER BY cost, persistence DESC) = 1),
high AS (SELECT ps.*, CASE WHEN cut IS NOT NULL THEN persistence > cut ELSE persistence > 0 END AS high FROM ps LEFT JOIN tb USING (function_id, side, season)),
salient AS (SELECT function_id, side, season, CASE WHEN side = 'join' THEN min(birth) ELSE max(birth) END AS theta FROM high WHERE high GROUP BY function_id, side, season),
ep AS (SELECT ps.* FROM ps JOIN salient USING (function_id, side, season) WHERE CASE WHEN side = 'join' THEN birth >= theta ELSE birth <= theta END),
eq AS (SELECT function_id, side, quantile_cont(birth, 0.25) AS q1, quantile_cont(birth, 0.75) AS q3 FROM ep GROUP BY ALL),
extreme AS (SELECT function_id, side, CASE WHEN side = 'join' THEN q3 + 1.5 * (q3 - q1) ELSE q1 - 1.5 * (q3 - q1) END AS theta FROM eq)"""


def points(time: str, seasonal: bool = True) -> str:
    """CTE ``pts`` from ``fn``, ``salient`` and ``extreme``: feature_type, region, t, pos, neg."""
    season = SEASON[time].replace("{t}", "t") if seasonal else "0"
    return f""",
fs AS (SELECT *, {season} AS season FROM fn),
sw AS (SELECT function_id, season, max(theta) FILTER (side = 'join') AS up, max(theta) FILTER (side = 'split') AS down FROM salient GROUP BY ALL),
ew AS (SELECT function_id, max(theta) FILTER (side = 'join') AS eu, max(theta) FILTER (side = 'split') AS ed FROM extreme GROUP BY ALL),
sa AS (SELECT function_id, region, t, value, coalesce(value >= up, false) AS pos, coalesce(value <= down, false) AS neg FROM fs JOIN sw USING (function_id, season)),
pts AS (SELECT function_id, 'salient' AS feature_type, region, t, pos, neg FROM sa WHERE pos OR neg UNION ALL
  SELECT * FROM (SELECT function_id, 'extreme' AS feature_type, region, t, pos AND coalesce(value >= eu, false) AS pos, neg AND coalesce(value <= ed, false) AS neg FROM sa JOIN ew USING (function_id)) WHERE pos OR neg)"""


#: CTEs ``cand`` and ``rel`` from ``fn`` and ``pts``.
RELATION = """,
mt AS (SELECT function_id, split_part(function_id, '.', 1) AS ds, min(t) AS lo, max(t) AS hi FROM fn GROUP BY ALL),
cand AS (SELECT a.function_id AS left_fn, b.function_id AS right_fn, a.ds AS left_dataset, b.ds AS right_dataset, greatest(a.lo, b.lo) AS lo, least(a.hi, b.hi) AS hi
  FROM mt a JOIN mt b ON a.ds < b.ds WHERE least(a.hi, b.hi) - greatest(a.lo, b.lo) >= 1),
ft AS (SELECT * FROM (VALUES ('salient'), ('extreme')) v(feature_type)),
c1 AS (SELECT left_fn, right_fn, feature_type, count(*) AS n1 FROM cand JOIN pts ON function_id = left_fn AND t BETWEEN lo AND hi GROUP BY ALL),
c2 AS (SELECT left_fn, right_fn, feature_type, count(*) AS n2 FROM cand JOIN pts ON function_id = right_fn AND t BETWEEN lo AND hi GROUP BY ALL),
cc AS (SELECT left_fn, right_fn, a.feature_type, count(*) AS n_common, count(*) FILTER (a.pos AND b.pos OR a.neg AND b.neg) AS n_pos, count(*) FILTER (a.pos AND b.neg OR a.neg AND b.pos) AS n_neg
  FROM cand JOIN pts a ON a.function_id = left_fn AND a.t BETWEEN lo AND hi JOIN pts b ON b.function_id = right_fn AND b.feature_type = a.feature_type AND b.region = a.region AND b.t = a.t GROUP BY ALL),
rel AS (SELECT c.*, f.feature_type, coalesce(n1, 0) AS n1, coalesce(n2, 0) AS n2, coalesce(n_common, 0) AS n_common, coalesce(n_pos, 0) AS n_pos, coalesce(n_neg, 0) AS n_neg,
  CASE WHEN n_common > 0 THEN (n_pos - n_neg) / n_common END AS score, coalesce(n_common / nullif(n1, 0), 0.0) AS precision, coalesce(n_common / nullif(n2, 0), 0.0) AS recall,
  coalesce(2 * n_common / (coalesce(n1, 0) + coalesce(n2, 0)), 0.0) AS strength
  FROM cand c CROSS JOIN ft f LEFT JOIN c1 USING (left_fn, right_fn, feature_type) LEFT JOIN c2 USING (left_fn, right_fn, feature_type) LEFT JOIN cc USING (left_fn, right_fn, feature_type)
  WHERE n1 IS NOT NULL OR n2 IS NOT NULL)"""

#: CTE ``test`` from ``cand`` and ``pts``: rotations in time, direction of the observed score.
ROTATION = """,
lg AS (SELECT left_fn, right_fn, a.feature_type, lo, hi, ((a.t - b.t) % (hi - lo + 1) + (hi - lo + 1)) % (hi - lo + 1) AS lag, count(*) AS n_common,
  count(*) FILTER (a.pos AND b.pos OR a.neg AND b.neg) AS n_pos, count(*) FILTER (a.pos AND b.neg OR a.neg AND b.pos) AS n_neg
  FROM cand JOIN pts a ON a.function_id = left_fn AND a.t BETWEEN lo AND hi JOIN pts b ON b.function_id = right_fn AND b.feature_type = a.feature_type AND b.region = a.region AND b.t BETWEEN lo AND hi GROUP BY ALL),
st AS (SELECT *, round((n_pos - n_neg) / n_common, 9) AS s FROM lg),
ob AS (SELECT left_fn, right_fn, feature_type, hi - lo AS n_perm, s AS obs FROM st WHERE lag = 0),
nl AS (SELECT o.left_fn, o.right_fn, o.feature_type, count(s) AS present, count(*) FILTER (s >= obs) AS ge, count(*) FILTER (s <= obs) AS le
  FROM ob o LEFT JOIN st ON st.left_fn = o.left_fn AND st.right_fn = o.right_fn AND st.feature_type = o.feature_type AND lag <> 0 GROUP BY ALL),
test AS (SELECT left_fn, right_fn, feature_type, n_perm, obs, (CASE WHEN obs < 0 THEN le ELSE ge + CASE WHEN obs <= 0 THEN n_perm - present ELSE 0 END END) / n_perm AS p_value
  FROM ob JOIN nl USING (left_fn, right_fn, feature_type) WHERE n_perm > 0)"""


def query(select: str, *ctes: str) -> str:
    return "WITH " + "".join(ctes) + "\n" + select
