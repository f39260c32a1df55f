"""Registered queries: planted workloads, relational operators, functions for SQL, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from strel import oracle as O
from strel import oracle_space as S
from strel.functions import registered
from strel.functions.steps import to_step
from strel.operators import features, permute, relate, scalar, space, topology
from strel.plans import workloads as W
from strel.plans.query import Clause, Index, RelationshipQuery, index_functions
from strel.queries import _REL_COLS, ORACLES, REGISTRY, _tested, _week, dense, r6, register
from strel.runtime import materialize, table
from strel.sources import catalog
from strel.streaming import live

_TEST = "SELECT r.left_fn, r.right_fn, r.feature_type, r.n1, r.n2, r.n_common, r.n_pos, r.n_neg, round(r.score, 6) AS score, round(r.strength, 6) AS strength, CAST(n_perm AS BIGINT) AS n_perm, round(p_value, 6) AS p_value, coalesce(p_value <= 0.05, false) AS significant FROM rel r LEFT JOIN test USING (left_fn, right_fn, feature_type) WHERE n_common > 0"


def u(expr: str) -> str:
    return f"(CAST(('0x' || substr(md5({expr}), 1, 8)) AS BIGINT) / 4294967296)"


def _fill(source: str) -> str:
    """CTE ``fn`` from a SELECT of function_id, region, t, value."""
    body = O.functions(("orders",), "world", "week", ("density",))
    return body.replace(O.raw("orders", "world", "week", ("density",)), source)


def _all(time: str, fn: str) -> tuple[str, ...]:
    return (fn, O.PAIRS, O.thresholds(time), O.points(time), O.RELATION, O.ROTATION)


def _related(fn: DataFrame, left: tuple[str, ...] = ()) -> DataFrame:
    return _tested(RelationshipQuery(index_functions(fn), left).run(False))


_DAY_L, _DAY_O = O.step("l_shipdate", "day"), O.step("o_orderdate", "day")
_STORM = u("'storm:' || t") + " < 0.01"
_storm_fn = _fill(f"""SELECT 'trips.density' AS function_id, '0' AS region, t, CAST(count(*) AS DOUBLE) AS value FROM (SELECT {_DAY_L} AS t, l_orderkey, l_linenumber FROM lineitem) WHERE NOT ({_STORM} AND {u("'drop:' || l_orderkey || ':' || l_linenumber")} < 0.8) GROUP BY t
 UNION ALL SELECT 'wind.avg', '0', t, sum(CAST(round(o_totalprice * 100) AS BIGINT)) / count(*) / 100 / 10000 + CASE WHEN {_STORM} THEN 40 ELSE 0 END FROM (SELECT {_DAY_O} AS t, o_totalprice FROM orders) GROUP BY t""")


@register(O.query(_TEST, *_all("day", _storm_fn)))
def planted_storms_day(spark: SparkSession, sf: str) -> DataFrame:
    return _related(W.storms(spark, sf))


_WEEK_O, _WEEK_L = O.step("o_orderdate", "week"), O.step("l_shipdate", "week")


def _years(planted: bool) -> str:
    keep = f"WHERE {u("'keep:' || o_orderkey")} < CASE WHEN {u("'wk:' || (t % 52)")} < 0.15 THEN 0.25 ELSE 1.0 END" if planted else ""
    src = f"SELECT t, count(*) AS n FROM (SELECT o_orderkey, {_WEEK_O} - (SELECT min({_WEEK_O}) + 52 FROM orders) AS t FROM orders) {keep} GROUP BY t"
    return "cnt AS (" + src + "), fn AS (" + " UNION ALL ".join(f"SELECT '{n}.density' AS function_id, '0' AS region, CAST(g - {s} AS INTEGER) AS t, CAST(coalesce(n, 0) AS DOUBLE) AS value FROM (SELECT unnest(generate_series({s}, {s + 51})) AS g) LEFT JOIN cnt ON t = g WHERE g BETWEEN (SELECT min(t) FROM cnt WHERE t BETWEEN 0 AND 103) AND (SELECT max(t) FROM cnt WHERE t BETWEEN 0 AND 103)" for n, s in (("year1", 0), ("year2", 52))) + ")"


@register(O.query(_TEST, *_all("week", _years(True))))
def planted_year_over_year(spark: SparkSession, sf: str) -> DataFrame:
    return _related(W.two_years(spark, sf))


@register(O.query(_TEST, *_all("week", _years(False))))
def relation_year_over_year(spark: SparkSession, sf: str) -> DataFrame:
    return _related(W.two_years(spark, sf, planted=False))


_RAIN = u("'rain:' || t") + " < 0.1"
_severity_fn = _fill(f"""SELECT 'lineitem.avg(l_discount)' AS function_id, '0' AS region, t, sum(CAST(round(l_discount * 100) AS BIGINT)) / count(*) / 100 + CASE WHEN {_RAIN} THEN 0.03 ELSE 0.0 END AS value FROM (SELECT {_WEEK_L} AS t, l_discount FROM lineitem) GROUP BY t
 UNION ALL SELECT 'lineitem.density', '0', {_WEEK_L} AS t, CAST(count(*) AS DOUBLE) FROM lineitem GROUP BY ALL
 UNION ALL SELECT 'orders.avg(o_totalprice)', '0', t, sum(CAST(round(o_totalprice * 100) AS BIGINT)) / count(*) / 100 * CASE WHEN {_RAIN} THEN 1.5 ELSE 1.0 END FROM (SELECT {_WEEK_O} AS t, o_totalprice FROM orders) GROUP BY t
 UNION ALL SELECT 'orders.density', '0', {_WEEK_O} AS t, CAST(count(*) AS DOUBLE) FROM orders GROUP BY ALL""").replace("+ CASE WHEN " + _RAIN + " THEN 0.03 ELSE 0.0 END", "+ CAST(CASE WHEN " + _RAIN + " THEN 0.03 ELSE 0.0 END AS DOUBLE)").replace("* CASE WHEN " + _RAIN + " THEN 1.5 ELSE 1.0 END", "* CAST(CASE WHEN " + _RAIN + " THEN 1.5 ELSE 1.0 END AS DOUBLE)")


@register(O.query(_TEST, *_all("week", _severity_fn)))
def planted_severity_week(spark: SparkSession, sf: str) -> DataFrame:
    return _related(W.severity(spark, sf))


_BURST = u("'burst:' || region || ':' || (t - lo)") + " < 0.01"
_bursts = f"""sp AS (SELECT min({O.step('ts', 'hour')}) AS lo, max({O.step('ts', 'hour')}) AS hi FROM events),
cn AS (SELECT event_type, CAST(c_nationkey AS VARCHAR) AS region, {O.step('ts', 'hour')} AS t, count(*) AS n FROM events JOIN customer ON user_id = c_custkey WHERE event_type IN ('click', 'purchase') GROUP BY ALL),
gr AS (SELECT kind, CAST(n_nationkey AS VARCHAR) AS region, unnest(generate_series(lo, hi)) AS t, lo FROM nation, sp, (SELECT unnest(['click', 'purchase']) AS kind)),
fn AS (SELECT kind || '.density' AS function_id, g.region, CAST(g.t AS INTEGER) AS t, CAST(coalesce(n, 0) + CASE WHEN {_BURST.replace('region', 'g.region').replace('(t - lo)', '(g.t - lo)')} THEN 5 ELSE 0 END AS DOUBLE) AS value
  FROM gr g LEFT JOIN cn ON cn.event_type = g.kind AND cn.region = g.region AND cn.t = g.t)"""
_shifts = """,
maps AS (SELECT k, CAST(r AS VARCHAR) AS region, CAST((r // 5 + k // 5) % 5 * 5 + (r % 5 + k % 5) % 5 AS VARCHAR) AS image FROM (SELECT unnest(range(1, 25)) AS k), (SELECT unnest(range(25)) AS r))"""
_FIXED = ", pts AS (SELECT function_id, 'salient' AS feature_type, region, t, value >= 4 AS pos, value <= 0 AS neg FROM fn WHERE value >= 4 OR value <= 0)"


@register(O.query("SELECT r.left_fn, r.right_fn, r.n1, r.n2, r.n_common, r.n_pos, r.n_neg, round(r.score, 6) AS score, round(r.strength, 6) AS strength, CAST(n_perm AS BIGINT) AS n_perm, round(p_value, 6) AS p_value FROM rel r JOIN test USING (left_fn, right_fn, feature_type)", _bursts, _FIXED, O.RELATION, _shifts, S.MAP_TEST))
def planted_bursts_fixed_thresholds(spark: SparkSession, sf: str) -> DataFrame:
    """Local bursts under thresholds that a user gives, tested with all shifts of the lattice."""
    fn = materialize(W.bursts(spark, sf), "bursts")
    pts = features.from_user(fn, {"click.density": (0.0, 4.0), "purchase.density": (0.0, 4.0)}).withColumn("feature_type", F.lit("salient"))
    pairs = relate.candidate_pairs(relate.spans(fn))
    counts = relate.measures(relate.pair_counts(pairs, features.to_bits(pts)))
    test = relate.spatial_test(pairs, pts, permute.lattice_maps(spark, 5, 5))
    found = counts.join(test, ["left_fn", "right_fn", "space_res", "time_res", "feature_type"])
    return found.select("left_fn", "right_fn", "n1", "n2", "n_common", "n_pos", "n_neg", r6("score"), r6("strength"), "n_perm", r6("p_value"))


@register()
def planted_bursts_hour_nation(spark: SparkSession, sf: str) -> DataFrame:
    fn = W.bursts(spark, sf)
    ix = index_functions(fn, space.lattice(spark, 5, 5), False, "nation")
    pairs = relate.candidate_pairs(ix.meta)
    counts = relate.measures(relate.pair_counts(pairs, ix.bits))
    test = relate.spatial_test(pairs, ix.points, permute.lattice_maps(spark, 5, 5))
    return counts.join(test, ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]).select(*_REL_COLS, r6("score"), r6("strength"), "n_perm", r6("p_value"))


_THETA = ", pts AS (SELECT function_id, 'user' AS feature_type, region, t, value >= up AS pos, value <= down AS neg FROM fn JOIN (VALUES ('orders.density', 50, 32), ('lineitem.density', 180, 160)) v(function_id, up, down) USING (function_id) WHERE value >= up OR value <= down)"


@register(O.query("SELECT a.function_id AS left_fn, b.function_id AS right_fn, count(*) AS n_common, count(*) FILTER (a.pos AND b.pos OR a.neg AND b.neg) AS n_pos, count(*) FILTER (a.pos AND b.neg OR a.neg AND b.pos) AS n_neg FROM pts a JOIN pts b USING (region, t) WHERE a.function_id = 'lineitem.density' AND b.function_id = 'orders.density' GROUP BY ALL", O.functions(("orders", "lineitem"), "world", "week", ("density",)), _THETA))
def relation_user_thresholds(spark: SparkSession, sf: str) -> DataFrame:
    c = Clause(feature_types=("salient",), thresholds={"orders.density": (32.0, 50.0), "lineitem.density": (160.0, 180.0)})
    fn = dense(spark, sf, ("orders", "lineitem"), "world", "week", ("density",))
    return RelationshipQuery(index_functions(fn), clause=c).evaluate().select("left_fn", "right_fn", "n_common", "n_pos", "n_neg")


# --- relational operators over functions, extrema and features -----------------------------------

_CHAIN = (O.functions(("orders", "lineitem"), "world", "week"), O.PAIRS, O.thresholds("week"), O.points("week"))


def _over(key: str, text: str, oracle: str | None = None, fresh: bool = False) -> None:
    """A question in SQL about the stored weekly index: functions ``fn``, extrema ``pairs``, features ``pts``."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        ix = _week(spark, sf, fresh)
        for name, df in (("fn", ix.functions), ("pairs", ix.pairs), ("pts", ix.points)):
            df.createOrReplaceTempView(f"strel_{name}")
        body = text
        for name in ("fn", "pairs", "pts"):
            body = body.replace("{" + name + "}", f"strel_{name}")
        return spark.sql(body)

    run.__name__ = key
    plain = oracle or text
    for name in ("fn", "pairs", "pts"):
        plain = plain.replace("{" + name + "}", name)
    register(O.query(f"SELECT * FROM ({plain}) q", *_CHAIN))(run)


_over("cube_extrema", "SELECT function_id, side, count(*) AS n, round(max(persistence), 6) AS top FROM {pairs} GROUP BY CUBE (function_id, side)")
_over("rollup_features", "SELECT function_id, feature_type, pos, count(*) AS n FROM {pts} GROUP BY ROLLUP (function_id, feature_type, pos)")
_over("union_of_features_and_extrema", "SELECT function_id, CAST(t AS BIGINT) AS t FROM {pts} UNION SELECT function_id, CAST(creator_t AS BIGINT) FROM {pairs}")
_over("semi_join_functions_with_extremes", "SELECT function_id, CAST(t AS BIGINT) AS t, value FROM {fn} f WHERE EXISTS (SELECT 1 FROM {pts} p WHERE p.function_id = f.function_id AND p.t = f.t AND p.feature_type = 'salient')")
_over("anti_join_steps_without_features", "SELECT function_id, CAST(t AS BIGINT) AS t, value FROM {fn} f WHERE NOT EXISTS (SELECT 1 FROM {pts} p WHERE p.function_id = f.function_id AND p.t = f.t)", fresh=True)
_over("range_join_features_near_peaks", "SELECT p.function_id, p.side, CAST(p.creator_t AS BIGINT) AS creator_t, count(*) AS n FROM {pairs} p JOIN {pts} f ON f.function_id = p.function_id AND f.t BETWEEN p.creator_t - 2 AND p.creator_t + 2 GROUP BY p.function_id, p.side, p.creator_t")
_RUNS = "(SELECT function_id, min(t) AS lo, max(t) AS hi FROM (SELECT function_id, t, sum(CASE WHEN t - b = 1 THEN 0 ELSE 1 END) OVER (PARTITION BY function_id ORDER BY t) AS run FROM (SELECT function_id, t, lag(t) OVER (PARTITION BY function_id ORDER BY t) AS b FROM {pts} WHERE feature_type = 'salient' AND pos)) GROUP BY function_id, run)"
_over("interval_join_feature_runs", f"SELECT a.function_id AS f, b.function_id AS g, count(*) AS n, CAST(sum(least(a.hi, b.hi) - greatest(a.lo, b.lo) + 1) AS BIGINT) AS steps FROM {_RUNS} a JOIN {_RUNS} b ON a.function_id < b.function_id AND a.lo <= b.hi AND b.lo <= a.hi GROUP BY a.function_id, b.function_id", fresh=True)
_over("window_ranking_persistence", "SELECT function_id, side, CAST(creator_t AS BIGINT) AS creator_t, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS q, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM {pairs} WINDOW w AS (PARTITION BY function_id, side ORDER BY round(persistence, 6) DESC, creator_t)")
_over("window_lag_lead_extrema", "SELECT function_id, side, CAST(creator_t AS BIGINT) AS creator_t, lag(birth) OVER w AS before, lead(birth) OVER w AS after, first_value(birth) OVER w AS head FROM {pairs} WINDOW w AS (PARTITION BY function_id, side ORDER BY creator_t)")
_over("window_moving_average", "SELECT function_id, CAST(t AS BIGINT) AS t, round(avg(value) OVER w, 6) AS smooth, count(*) OVER w AS n FROM {fn} WINDOW w AS (PARTITION BY function_id ORDER BY t ROWS BETWEEN 6 PRECEDING AND CURRENT ROW)")
_over("window_running_total", "SELECT function_id, CAST(t AS BIGINT) AS t, CAST(sum(value) OVER (PARTITION BY function_id ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS total FROM {fn} WHERE function_id LIKE '%.density'")
_over("iqr_boxplot_minima", "SELECT function_id, round(percentile(birth, 0.25), 6) AS q1, round(percentile(birth, 0.5), 6) AS q2, round(percentile(birth, 0.75), 6) AS q3 FROM {pairs} WHERE side = 'split' GROUP BY function_id", "SELECT function_id, round(quantile_cont(birth, 0.25), 6) AS q1, round(quantile_cont(birth, 0.5), 6) AS q2, round(quantile_cont(birth, 0.75), 6) AS q3 FROM {pairs} WHERE side = 'split' GROUP BY function_id")
_over("distinct_steps_of_features", "SELECT feature_type, count(DISTINCT function_id) AS functions, count(DISTINCT t) AS steps FROM {pts} GROUP BY feature_type", fresh=True)
_over("pivot_signs", "SELECT * FROM (SELECT function_id, feature_type FROM {pts}) PIVOT (count(*) FOR feature_type IN ('salient' AS salient, 'extreme' AS extreme))", "SELECT function_id, nullif(count(*) FILTER (feature_type = 'salient'), 0) AS salient, nullif(count(*) FILTER (feature_type = 'extreme'), 0) AS extreme FROM {pts} GROUP BY function_id", fresh=True)
_over("unpivot_birth_death", "SELECT function_id, side, CAST(creator_t AS BIGINT) AS creator_t, what, v FROM {pairs} LATERAL VIEW stack(2, 'birth', birth, 'death', death) AS what, v", "SELECT function_id, side, CAST(creator_t AS BIGINT) AS creator_t, 'birth' AS what, birth AS v FROM {pairs} UNION ALL SELECT function_id, side, CAST(creator_t AS BIGINT), 'death', death FROM {pairs}")
_over("self_join_year_before", "SELECT a.function_id, CAST(a.t AS BIGINT) AS t, a.value - b.value AS change FROM {fn} a JOIN {fn} b ON b.function_id = a.function_id AND b.t = a.t - 52")


def _ordinal(key: str, name: str, axis: str, place: str, unique: tuple[str, ...], attr: str, space_res: str, src: str, sql_place: str, sql_attr: str) -> None:
    """A table without time as a data set over an integer axis."""

    def run(spark: SparkSession, sf: str) -> DataFrame:
        rows = table(spark, sf, name).select(F.expr(axis).alias("axis"), F.expr(place).alias(space_res), *unique, F.expr(attr).alias("size"))
        spec = catalog.DatasetSpec(name, rows, "axis", "ordinal", unique, {space_res: space_res}, ("size",), 0)
        found = [("world", "ordinal"), (space_res, "ordinal")]
        fn = scalar.from_observed(*scalar.observe(spec, found), spec, found)
        return fn.select("function_id", "space_res", "region", F.col("t").cast("long").alias("t"), F.round("value", 6).alias("value"))

    run.__name__ = key
    parts = []
    for res, region in (("world", "'0'"), (space_res, f"CAST({sql_place} AS VARCHAR)")):
        for m, v in (("density", "count(*)"), ("avg(size)", f"sum(CAST({sql_attr} AS BIGINT)) / count({sql_attr})"), *((f"unique({c})", f"count(DISTINCT {c})") for c in unique)):
            parts.append(f"SELECT '{name}.{m}' AS function_id, '{res}' AS space_res, {region} AS region, {src} AS t, round(CAST({v} AS DOUBLE), 6) AS value FROM {name} WHERE {region} IS NOT NULL GROUP BY 3, 4")
    register(" UNION ALL ".join(parts))(run)


_ordinal("ordinal_axis_documents", "documents", "doc_id div 50", "lang", (), "n_chars", "lang", "doc_id // 50", "lang", "n_chars")
_ordinal("ordinal_axis_conversations", "conversations", "conv_id div 5", "role", ("conv_id",), "length(text)", "role", "conv_id // 5", "role", "length(text)")
_ordinal("ordinal_axis_pages", "pages", "page_id div 10", "regexp_extract(url, '^https?://([^/:?#]+)', 1)", (), "length(html)", "host", "page_id // 10", "regexp_extract(url, '^https?://([^/:?#]+)', 1)", "length(html)")


@register(O.query("SELECT region, t FROM pts a WHERE function_id = 'orders.density' AND feature_type = 'salient' AND EXISTS (SELECT 1 FROM pts b WHERE b.function_id = 'lineitem.density' AND b.feature_type = 'salient' AND b.t = a.t)", O.functions(("orders", "lineitem"), "world", "week"), O.PAIRS, O.thresholds("week"), O.points("week")))
def intersect_feature_points(spark: SparkSession, sf: str) -> DataFrame:
    p = _week(spark, sf, True).points.where("feature_type = 'salient'")
    one = lambda f: p.where(F.col("function_id") == f).select("region", "t")
    return one("orders.density").intersect(one("lineitem.density"))


@register(O.query("SELECT region, t FROM pts a WHERE function_id = 'orders.density' AND feature_type = 'salient' AND NOT EXISTS (SELECT 1 FROM pts b WHERE b.function_id = 'lineitem.density' AND b.feature_type = 'salient' AND b.t = a.t)", O.functions(("orders", "lineitem"), "world", "week"), O.PAIRS, O.thresholds("week"), O.points("week")))
def except_feature_points(spark: SparkSession, sf: str) -> DataFrame:
    p = _week(spark, sf).points.where("feature_type = 'salient'")
    one = lambda f: p.where(F.col("function_id") == f).select("region", "t")
    return one("orders.density").exceptAll(one("lineitem.density"))


@register(O.query("SELECT function_id, list(round(value, 4) ORDER BY t) AS series FROM fn GROUP BY function_id", O.functions(("orders",), "world", "month", ("density",))))
def array_series_by_function(spark: SparkSession, sf: str) -> DataFrame:
    fn = dense(spark, sf, ("orders",), "world", "month", ("density",))
    return fn.groupBy("function_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("t", "value"))), lambda x: F.round(x["value"], 4)).alias("series"))


@register("SELECT vec_id, embedding[1] > 0 AND embedding[1] < 0.2 AND embedding[2] > -0.1 AND embedding[2] < 0.1 AS hit FROM embeddings")
def udf_point_in_polygon(spark: SparkSession, sf: str) -> DataFrame:
    registered.register_all(spark)
    e = table(spark, sf, "embeddings").select("vec_id", F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"))
    return e.withColumn("hit", F.expr("inside(x, y, array(0D, 0.2D, 0.2D, 0D), array(-0.1D, -0.1D, 0.1D, 0.1D))")).select("vec_id", "hit")


@register("SELECT o_orderpriority, round(avg(o_totalprice), 4) AS m FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice) AS rn, count(*) OVER (PARTITION BY o_orderpriority) AS n FROM orders) WHERE rn > n // 10 AND rn <= n - n // 10 GROUP BY o_orderpriority")
def udaf_custom_agg(spark: SparkSession, sf: str) -> DataFrame:
    registered.register_all(spark)
    return catalog.orders(spark, sf).df.groupBy("o_orderpriority").agg(F.expr("round(trimmed_mean(o_totalprice), 4)").alias("m"))


@register(O.query("SELECT side, CAST(creator_t AS INTEGER) AS creator_t, birth, death FROM pairs", O.functions(("orders",), "world", "month", ("density",)), O.PAIRS))
def udtf_persistence(spark: SparkSession, sf: str) -> DataFrame:
    registered.register_all(spark)
    dense(spark, sf, ("orders",), "world", "month", ("density",)).createOrReplaceTempView("strel_fn")
    return spark.sql("SELECT side, creator_t, birth, death FROM persistence_of(TABLE(strel_fn) PARTITION BY function_id)")


@register()
def udtf_related(spark: SparkSession, sf: str) -> DataFrame:
    registered.register_all(spark, RelationshipQuery(_week(spark, sf)).run(False))
    return spark.sql("SELECT * FROM related('orders', 0.05D)")


# --- streams ----------------------------------------------------------------------------------


@register(f"SELECT CAST({O.step('ts', 'hour')} AS BIGINT) AS t, count(*) AS value FROM events GROUP BY ALL")
def stream_density_hour(spark: SparkSession, sf: str) -> DataFrame:
    out = live.drain(live.density(live.source(spark, f"{sf}/events.parquet")))
    return out.select((F.col("w.start").cast("long") / 3600).cast("long").alias("t"), "value")


@register("""SELECT user_id, count(*) AS n FROM (SELECT user_id, ts, sum(CASE WHEN ts - p <= INTERVAL 6 HOUR THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM
 (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events)) GROUP BY user_id, s""")
def stream_session_users(spark: SparkSession, sf: str) -> DataFrame:
    return live.drain(live.sessions(live.source(spark, f"{sf}/events.parquet"))).select("user_id", "n")


@register(f"SELECT t, value, value >= 20 AS pos, value <= 8 AS neg FROM (SELECT CAST({O.step('ts', 'hour')} AS BIGINT) AS t, count(*) AS value FROM events GROUP BY ALL) WHERE (value >= 20 OR value <= 8) AND t < (SELECT CAST(max({O.step('ts', 'hour')}) - 1 AS BIGINT) FROM events)")
def stream_feature_flags(spark: SparkSession, sf: str) -> DataFrame:
    """Flags of closed hours, joined with stored thresholds inside the stream."""
    th = spark.createDataFrame([(20.0, 8.0)], "up double, down double")
    out = live.drain(live.flags(live.density(live.source(spark, f"{sf}/events.parquet")), th), "append")
    return out.select((F.col("w.start").cast("long") / 3600).cast("long").alias("t"), "value", "pos", "neg")


@register(f"""SELECT t, count(*) AS value FROM (SELECT CAST({O.step('ts', 'hour')} AS BIGINT) - 1 + unnest([0, 1]) AS t FROM events) GROUP BY t""")
def stream_sliding_density(spark: SparkSession, sf: str) -> DataFrame:
    """Windows of two hours that begin every hour."""
    out = live.drain(live.density(live.source(spark, f"{sf}/events.parquet"), "2 hours", "1 hour"))
    return out.select((F.col("w.start").cast("long") / 3600).cast("long").alias("t"), "value")


_SIGNED = "SELECT DISTINCT CAST(epoch(date_trunc('minute', ts)) AS BIGINT) AS m, value >= 0 AS pos, value < 0 AS neg FROM events WHERE event_type = '{}'"


@register(f"""SELECT count(*) AS n_common, CAST(sum(CAST(a.pos AND b.pos OR a.neg AND b.neg AS INT)) AS BIGINT) AS n_pos, CAST(sum(CAST(a.pos AND b.neg OR a.neg AND b.pos AS INT)) AS BIGINT) AS n_neg FROM ({_SIGNED.format('click')}) a JOIN ({_SIGNED.format('view')}) b USING (m)""".replace("value >= 0", "event_id % 2 = 0").replace("value < 0", "event_id % 2 = 1"))
def stream_running_relation(spark: SparkSession, sf: str) -> DataFrame:
    """Two live streams of signed features joined step by step, and their running counts."""

    def signed(kind: str) -> DataFrame:
        e = live.source(spark, f"{sf}/events.parquet").where(F.col("event_type") == kind)
        e = e.select(F.date_trunc("minute", "ts").alias("ts"), (F.col("event_id") % 2 == 0).alias("pos"), (F.col("event_id") % 2 == 1).alias("neg"))
        return e.withWatermark("ts", "1 hour").dropDuplicates(["ts", "pos", "neg"])

    met = live.drain(live.met(signed("click"), signed("view")), "append")
    return live.running_relation(met).select("n_common", "n_pos", "n_neg")


@register("SELECT count(*) AS n, sum(v) AS total FROM (SELECT count(*) AS v FROM events GROUP BY event_id)")
def stream_deduplicated(spark: SparkSession, sf: str) -> DataFrame:
    out = live.drain(live.deduplicated(live.source(spark, f"{sf}/events.parquet")), "append")
    return out.agg(F.count(F.lit(1)).alias("n"), F.count("event_id").alias("total"))


@register()
def stream_open_peaks(spark: SparkSession, sf: str) -> DataFrame:
    s = live.source(spark, f"{sf}/events.parquet").select(F.lit("events.value").alias("function_id"), F.col("event_id").alias("t"), "value")
    return live.drain(live.open_peaks(s), "append")
