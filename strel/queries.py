"""Registered queries of the library and, where SQL can say the same, their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from strel import oracle as O
from strel.functions.steps import coarser, to_step
from strel.operators import baselines, features, permute, relate, scalar, space, topology
from strel.plans.query import Clause, Index, RelationshipQuery, dataset_degree, explain, index_corpus, index_functions, rank_relationships
from strel.runtime import table
from strel.sources import catalog

Query = Callable[[SparkSession, str], DataFrame]
REGISTRY: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
_INDEX: dict[tuple, Index] = {}
WEEK_SETS = ("orders", "lineitem")
#: Measures of the weekly pairs: all of both tables.
WEEK_MEASURES = None


def register(sql: str | None = None):
    def add(f: Query) -> Query:
        REGISTRY[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def _specs(spark: SparkSession, sf: str, names: tuple[str, ...]) -> list[catalog.DatasetSpec]:
    every = {s.name: s for s in [*catalog.corpus(spark, sf), catalog.events(spark, sf)]}
    return [every[n] for n in names]


def dense(spark: SparkSession, sf: str, names: tuple[str, ...], space_res: str, time_res: str, measures: tuple[str, ...] | None = None, missing: str = "carry") -> DataFrame:
    """Dense functions of some data sets and measures."""
    out = None
    for s in _specs(spark, sf, names):
        keep = lambda c, s=s: measures is None or c in measures
        points = scalar.wide(s, space_res, time_res, [i for i in s.ids if keep(f"unique({i})")], [a for a in s.attrs if keep(f"avg({a})")])
        if not keep("density"):
            points = points.drop("density")
        fn = scalar.long(points, s.name, space_res, time_res)
        out = fn if out is None else out.unionByName(fn)
    return scalar.densify(out, missing)


def index(spark: SparkSession, sf: str, names: tuple[str, ...], time_res: str, measures: tuple[str, ...] | None = None, seasonal: bool = True, fresh: bool = False) -> Index:
    """The stored index of some functions at world level, built once a session.

    With ``fresh`` it is built from the tables as they are now, whatever an earlier query has left.
    """
    key = (spark.sparkContext.applicationId, sf, names, time_res, measures, seasonal)
    if fresh or key not in _INDEX:
        _INDEX[key] = index_functions(dense(spark, sf, names, "world", time_res, measures), None, seasonal)
    return _INDEX[key]


def r6(c: str) -> F.Column:
    return F.round(F.col(c).cast("double"), 6).alias(c)


def _values(fn: DataFrame) -> DataFrame:
    return fn.select("function_id", "region", F.col("t").cast("long").alias("t"), "value")


def _values_sql(ctes: str, of: str = "fn") -> str:
    return O.query(f"SELECT function_id, region, CAST(t AS BIGINT) AS t, value FROM {of}", ctes)


# --- scalar functions -------------------------------------------------------------------------


def _scalar(key: str, names: tuple[str, ...], space_res: str, time_res: str, measures: tuple[str, ...] | None = None) -> None:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return _values(dense(spark, sf, names, space_res, time_res, measures))

    run.__name__ = key
    register(_values_sql(O.functions(names, space_res, time_res, measures)))(run)


for _key, _args in {
    "density_orders_day_world": (("orders",), "world", "day", ("density",)),
    "density_orders_day_nation": (("orders",), "nation", "day", ("density",)),
    "density_events_hour_nation": (("events",), "nation", "hour", ("density",)),
    "unique_orders_cust_week": (("orders",), "world", "week", ("unique(o_custkey)",)),
    "unique_lineitem_supp_month_nation": (("lineitem",), "nation", "month", ("unique(l_suppkey)",)),
    "avg_price_orders_week": (("orders",), "world", "week", ("avg(o_totalprice)",)),
    "avg_lineitem_measures_day": (("lineitem",), "world", "day", ("avg(l_quantity)", "avg(l_extendedprice)", "avg(l_discount)", "avg(l_tax)")),
    "event_value_hour_segment": (("events",), "segment", "hour", ("avg(value)",)),
    "props_k_day": (("events",), "world", "day", ("avg(k)",)),
    "asof_fill_avg_day_nation": (("orders",), "nation", "day", ("avg(o_totalprice)",)),
}.items():
    _scalar(_key, *_args)


@register(_values_sql(O.functions(("orders_F", "orders_O", "orders_P", "lineitem_A", "lineitem_N", "lineitem_R"), "world", "month")))
def functions_of_splits_month(spark: SparkSession, sf: str) -> DataFrame:
    """Six parts of two tables, each table read once."""
    return _values(scalar.all_functions(catalog.splits(spark, sf), ("world",), ("month",)))


@register(f"""SELECT CAST({O.step("o_orderdate", "month")} AS BIGINT) AS t, round(sum(CAST(round(o_totalprice * 100) AS BIGINT)) / 100, 2) AS sum_price, round(median(o_totalprice), 6) AS med_price,
 min(o_totalprice) AS min_price, max(o_totalprice) AS max_price, round(quantile_cont(o_totalprice, 0.9), 6) AS p90 FROM orders GROUP BY ALL""")
def agg_variants_orders_month(spark: SparkSession, sf: str) -> DataFrame:
    o = catalog.orders(spark, sf)
    aggs = {
        "sum_price": lambda c: F.round(F.sum(F.round(c * 100).cast("long")) / 100, 2), "med_price": lambda c: F.round(F.median(c), 6), "min_price": F.min, "max_price": F.max,
        "p90": lambda c: F.round(F.percentile(c, F.lit(0.9)), 6),
    }
    out = None
    for name, how in aggs.items():
        one = scalar.attribute(o, "o_totalprice", "world", "month", how).select(F.col("t").cast("long").alias("t"), F.col("value").alias(name))
        out = one if out is None else out.join(one, "t")
    return out


@register("""SELECT event_id, event_type, dense_rank() OVER (ORDER BY event_type) - 1 AS event_type_code FROM events""")
def category_code_events(spark: SparkSession, sf: str) -> DataFrame:
    return catalog.encode_category(table(spark, sf, "events").select("event_id", "event_type"), "event_type").withColumn("event_type_code", F.col("event_type_code").cast("long"))


_GRAD = """, gn AS (SELECT *, lag(value) OVER w AS a, lead(value) OVER w AS b FROM fn WINDOW w AS (PARTITION BY function_id, region ORDER BY t))"""
_ADJ = """adj AS (SELECT CAST(a.n_nationkey AS VARCHAR) AS a, CAST(b.n_nationkey AS VARCHAR) AS b FROM nation a, nation b
  WHERE abs(a.n_nationkey // 5 - b.n_nationkey // 5) + abs(a.n_nationkey % 5 - b.n_nationkey % 5) = 1)"""


@register(O.query("SELECT 'gradient ' || function_id AS function_id, region, CAST(t AS BIGINT) AS t, coalesce(greatest(abs(value - a), abs(value - b)), 0) AS value FROM gn", O.functions(("orders",), "world", "week", ("density",)), _GRAD))
def gradient_orders_week(spark: SparkSession, sf: str) -> DataFrame:
    return _values(scalar.gradient(dense(spark, sf, ("orders",), "world", "week", ("density",))))


@register(O.query("""SELECT 'gradient ' || g.function_id AS function_id, g.region, CAST(g.t AS BIGINT) AS t, coalesce(greatest(abs(g.value - a), abs(g.value - b), s), 0) AS value
FROM gn g LEFT JOIN (SELECT f.region, f.t, max(abs(f.value - o.value)) AS s FROM fn f JOIN adj ON adj.a = f.region JOIN fn o ON o.region = adj.b AND o.t = f.t GROUP BY ALL) x USING (region, t)""", _ADJ, ", ", O.functions(("events",), "nation", "hour", ("density",)), _GRAD))
def gradient_events_hour_nation(spark: SparkSession, sf: str) -> DataFrame:
    return _values(scalar.gradient(dense(spark, sf, ("events",), "nation", "hour", ("density",)), space.lattice(spark, 5, 5)))


@register(f"""SELECT CAST(t AS BIGINT) AS t, density, round(avg_price, 6) AS avg_price, min_price, max_price FROM (SELECT {O.step("o_orderdate", "month")} AS t, CAST(count(*) AS DOUBLE) AS density,
 sum(CAST(round(o_totalprice * 100) AS BIGINT)) / count(*) / 100 AS avg_price, min(o_totalprice) AS min_price, max(o_totalprice) AS max_price FROM orders GROUP BY ALL)""")
def rollup_day_to_month_equals_direct(spark: SparkSession, sf: str) -> DataFrame:
    o = catalog.orders(spark, sf)
    up = scalar.finish(scalar.roll_up(scalar.states(o, "world", "day"), o, "day", "month"), o)
    return up.select(F.col("t").cast("long").alias("t"), "density", F.round("avg(o_totalprice)", 6).alias("avg_price"), F.col("min(o_totalprice)").alias("min_price"), F.col("max(o_totalprice)").alias("max_price"))


@register(f"""SELECT CAST(m AS BIGINT) AS t, CAST(sum(n) AS BIGINT) AS n FROM (SELECT w, n, CAST((year(d) - 1970) * 12 + month(d) - 1 AS INTEGER) AS m FROM
 (SELECT {O.step("o_orderdate", "week")} AS w, count(*) AS n, DATE '1970-01-05' + CAST({O.step("o_orderdate", "week")} * 7 AS INTEGER) AS d FROM orders GROUP BY ALL)) GROUP BY ALL""")
def week_to_month_lossy(spark: SparkSession, sf: str) -> DataFrame:
    o = catalog.orders(spark, sf)
    return scalar.roll_up(scalar.states(o, "world", "week"), o, "week", "month").select(F.col("t").cast("long").alias("t"), "n")


@register(f"""SELECT CAST(t AS BIGINT) AS t, region, nation, CAST(grouping(t, region, nation) AS BIGINT) AS g, count(*) AS density, round(sum(CAST(round(o_totalprice * 100) AS BIGINT)) / count(*) / 100, 6) AS avg_price
 FROM (SELECT {O.step("o_orderdate", "month")} AS t, c_nationkey % 5 AS region, c_nationkey AS nation, o_totalprice FROM orders JOIN customer ON o_custkey = c_custkey)
 GROUP BY GROUPING SETS ((t), (t, region), (t, nation), (region), (nation), ())""")
def all_resolutions_grouping_sets(spark: SparkSession, sf: str) -> DataFrame:
    o = catalog.orders(spark, sf).df.where("c_nationkey IS NOT NULL")
    o.select(to_step(F.col("o_orderdate"), "month").cast("long").alias("t"), F.col("c_regionkey").alias("region"), F.col("c_nationkey").alias("nation"), "o_totalprice").createOrReplaceTempView("strel_sets")
    return spark.sql("""SELECT t, region, nation, grouping_id(t, region, nation) AS g, count(*) AS density, round(sum(CAST(round(o_totalprice * 100) AS BIGINT)) / count(*) / 100, 6) AS avg_price
      FROM strel_sets GROUP BY GROUPING SETS ((t), (t, region), (t, nation), (region), (nation), ())""")


@register(_values_sql(O.functions(("orders",), "world", "day", ("density", "unique(o_custkey)", "avg(o_totalprice)"))))
def densify_orders_day(spark: SparkSession, sf: str) -> DataFrame:
    return _values(dense(spark, sf, ("orders",), "world", "day"))


@register(O.query("SELECT function_id, count(*) AS n_values, count(*) * 4 AS n_bytes FROM fn GROUP BY function_id", O.functions(WEEK_SETS, "world", "week")))
def footprint_bytes(spark: SparkSession, sf: str) -> DataFrame:
    return scalar.footprint(dense(spark, sf, WEEK_SETS, "world", "week")).select("function_id", "n_values", "n_bytes")


# --- space ------------------------------------------------------------------------------------


def nations(spark: SparkSession, sf: str) -> DataFrame:
    """The numbers of the nations, as regions of a lattice."""
    return table(spark, sf, "nation").select(F.col("n_nationkey").alias("region"))


@register(O.query("SELECT a, b FROM adj", _ADJ))
def adjacency_nation_lattice(spark: SparkSession, sf: str) -> DataFrame:
    return space.lattice_of(nations(spark, sf), 5)


@register(O.query("SELECT DISTINCT CAST(CAST(a AS INT) % 5 AS VARCHAR) AS a, CAST(CAST(b AS INT) % 5 AS VARCHAR) AS b FROM adj WHERE CAST(a AS INT) % 5 <> CAST(b AS INT) % 5", _ADJ))
def adjacency_region_quotient(spark: SparkSession, sf: str) -> DataFrame:
    m = table(spark, sf, "nation").select(F.col("n_nationkey").cast("string").alias("region"), F.col("n_regionkey").cast("string").alias("to_region"))
    return space.quotient(space.lattice(spark, 5, 5), m)


@register("""SELECT CAST(least(greatest(floor((embedding[2] + 0.5) / 1.0 * 8), 0), 7) * 8 + least(greatest(floor((embedding[1] + 0.5) / 1.0 * 8), 0), 7) AS BIGINT) AS cell, count(*) AS n FROM embeddings GROUP BY ALL""")
def grid_cells_embeddings(spark: SparkSession, sf: str) -> DataFrame:
    e = table(spark, sf, "embeddings")
    return e.select(space.cell_of(F.col("embedding")[0], F.col("embedding")[1], -0.5, 0.5, 8).cast("long").alias("cell")).groupBy("cell").agg(F.count(F.lit(1)).alias("n"))


@register("""SELECT vec_id AS id, CAST(floor((embedding[2] + 0.5) / 0.25) * 4 + floor((embedding[1] + 0.5) / 0.25) AS BIGINT) AS region FROM embeddings
 WHERE embedding[1] BETWEEN -0.5 AND 0.4999999 AND embedding[2] BETWEEN -0.5 AND 0.4999999""")
def points_in_polygons(spark: SparkSession, sf: str) -> DataFrame:
    cells = spark.range(16).select(F.col("id").alias("region"), F.expr("-0.5D + (id % 4) * 0.25D").alias("a"), F.expr("-0.5D + (id div 4) * 0.25D").alias("b"))
    corner = lambda i, x, y: F.struct(F.lit(i).alias("i"), x.alias("x"), y.alias("y"))
    a, b = F.col("a"), F.col("b")
    ring = F.array(corner(0, a, b), corner(1, a + 0.25, b), corner(2, a + 0.25, b + 0.25), corner(3, a, b + 0.25))
    polygons = cells.select("region", F.explode(ring).alias("c")).select("region", "c.i", "c.x", "c.y")
    pts = table(spark, sf, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"))
    return space.in_polygon(pts, polygons, 0.25)


_AXIS = "least(greatest(floor((CAST(embedding[{k}] AS DOUBLE) + 0.25) / 0.5 * 4), 0), 3)"


@register(f"""WITH c AS (SELECT DISTINCT CAST({_AXIS.replace("{k}", "1")} * 16 + {_AXIS.replace("{k}", "2")} * 4 + {_AXIS.replace("{k}", "3")} AS BIGINT) AS i FROM embeddings
  WHERE isfinite(embedding[1]) AND isfinite(embedding[2]) AND isfinite(embedding[3]))
SELECT x.i AS a, y.i AS b FROM c x, c y WHERE abs(x.i // 16 - y.i // 16) + abs((x.i // 4) % 4 - (y.i // 4) % 4) + abs(x.i % 4 - y.i % 4) = 1""")
def grid3d_adjacency(spark: SparkSession, sf: str) -> DataFrame:
    """Cells in three dimensions that hold embeddings, and which of them touch."""
    cells = table(spark, sf, "embeddings").select(space.cell3d_of(F.col("embedding"), -0.25, 0.25, 4).alias("a")).where("a IS NOT NULL")
    return space.cube_cells(spark, 4, cells).select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"))


@register("""SELECT n_nationkey AS region, n_regionkey AS to_region, r_name AS to_name FROM nation JOIN region ON n_regionkey = r_regionkey""")
def space_map_closure(spark: SparkSession, sf: str) -> DataFrame:
    n, r = table(spark, sf, "nation"), table(spark, sf, "region")
    return n.join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"]).select(F.col("n_nationkey").alias("region"), F.col("n_regionkey").alias("to_region"), F.col("r_name").alias("to_name"))


# --- topology ---------------------------------------------------------------------------------


@register(O.query("SELECT function_id, CASE side WHEN 'join' THEN 'max' ELSE 'min' END AS kind, CAST(t AS BIGINT) AS t, value FROM pk", O.functions(("orders",), "world", "week"), O.PAIRS))
def extrema_orders_week(spark: SparkSession, sf: str) -> DataFrame:
    return topology.extrema(dense(spark, sf, ("orders",), "world", "week")).select("function_id", "kind", F.col("t").cast("long").alias("t"), "value")


@register(O.query("""SELECT region, CAST(t AS BIGINT) AS t, kind FROM (SELECT f.region, f.t, 'max' AS kind, count(o.t) FILTER (o.value > f.value OR o.value = f.value AND (o.t < f.t OR o.t = f.t AND CAST(o.region AS INT) < CAST(f.region AS INT))) AS higher FROM fn f LEFT JOIN nb o ON o.r1 = f.region AND o.t1 = f.t GROUP BY ALL
 UNION ALL SELECT f.region, f.t, 'min', count(o.t) FILTER (o.value < f.value OR o.value = f.value AND (o.t < f.t OR o.t = f.t AND CAST(o.region AS INT) < CAST(f.region AS INT))) FROM fn f LEFT JOIN nb o ON o.r1 = f.region AND o.t1 = f.t GROUP BY ALL) WHERE higher = 0""",
    _ADJ, ", ", O.functions(("events",), "nation", "hour", ("density",)), ", nb AS (SELECT f.region AS r1, f.t AS t1, o.region, o.t, o.value FROM fn f JOIN fn o ON o.region = f.region AND o.t = f.t - 1 UNION ALL SELECT f.region, f.t, o.region, o.t, o.value FROM fn f JOIN fn o ON o.region = f.region AND o.t = f.t + 1 UNION ALL SELECT f.region, f.t, o.region, o.t, o.value FROM fn f JOIN adj ON adj.a = f.region JOIN fn o ON o.region = adj.b AND o.t = f.t)"))
def extrema_events_hour_nation(spark: SparkSession, sf: str) -> DataFrame:
    found = topology.extrema(dense(spark, sf, ("events",), "nation", "hour", ("density",)), space.lattice(spark, 5, 5))
    return found.select("region", F.col("t").cast("long").alias("t"), "kind")


def _pairs(p: DataFrame) -> DataFrame:
    return p.select("function_id", "side", F.col("creator_t").cast("long").alias("creator_t"), "birth", "death", "persistence", "essential")


_PAIR_SELECT = "SELECT function_id, side, CAST(creator_t AS BIGINT) AS creator_t, birth, death, persistence, essential FROM pairs"


@register(O.query(_PAIR_SELECT, O.functions(("orders",), "world", "week"), O.PAIRS))
def persistence_orders_week(spark: SparkSession, sf: str) -> DataFrame:
    return _pairs(topology.persistence_1d(dense(spark, sf, ("orders",), "world", "week")))


@register(O.query(_PAIR_SELECT, O.functions(("orders",), "world", "day", ("density",)), O.PAIRS))
def persistence_orders_day(spark: SparkSession, sf: str) -> DataFrame:
    return _pairs(topology.persistence(dense(spark, sf, ("orders",), "world", "day", ("density",))))


@register(O.query(_PAIR_SELECT + " WHERE side = 'split'", O.functions(("orders",), "world", "week"), O.PAIRS))
def persistence_min_orders_week(spark: SparkSession, sf: str) -> DataFrame:
    return _pairs(topology.persistence(dense(spark, sf, ("orders",), "world", "week")).where("side = 'split'"))


@register(O.query("""SELECT theta, count(*) FILTER (v >= theta AND NOT coalesce(pv >= theta, false)) AS n_components
 FROM (SELECT t, value AS v, lag(value) OVER (ORDER BY t) AS pv FROM fn) , (SELECT unnest([20.0, 30.0, 40.0, 45.0, 50.0, 60.0]) AS theta) GROUP BY theta""", O.functions(("orders",), "world", "week", ("density",))))
def component_count_sweep(spark: SparkSession, sf: str) -> DataFrame:
    thetas = spark.createDataFrame([(x,) for x in (20.0, 30.0, 40.0, 45.0, 50.0, 60.0)], "theta double")
    p = topology.persistence(dense(spark, sf, ("orders",), "world", "week", ("density",)))
    return topology.component_count(p, thetas).select("theta", "n_components")


@register()
def persistence_events_hour_nation(spark: SparkSession, sf: str) -> DataFrame:
    return topology.persistence(dense(spark, sf, ("events",), "nation", "hour", ("density",)), space.lattice(spark, 5, 5))


@register(O.query(f"SELECT {O.SEASON['day'].replace('{t}', 'creator_t')} AS season, side, birth, death FROM pairs", O.functions(("orders",), "world", "day", ("density",)), O.PAIRS))
def persistence_diagram_quarter(spark: SparkSession, sf: str) -> DataFrame:
    p = topology.persistence(dense(spark, sf, ("orders",), "world", "day", ("density",)))
    return features.with_season(p, "creator_t").select("season", "side", "birth", "death")


@register(O.query("SELECT function_id, CAST(t AS BIGINT) AS t, value FROM fn WHERE value >= 45", O.functions(("orders",), "world", "week", ("density",))))
def superlevel_user_theta(spark: SparkSession, sf: str) -> DataFrame:
    return topology.level_set(dense(spark, sf, ("orders",), "world", "week", ("density",)), 45.0).select("function_id", F.col("t").cast("long").alias("t"), "value")


@register(O.query("SELECT function_id, CAST(t AS BIGINT) AS t, value FROM fn WHERE value <= 34", O.functions(("orders",), "world", "week", ("density",))))
def sublevel_user_theta(spark: SparkSession, sf: str) -> DataFrame:
    return topology.level_set(dense(spark, sf, ("orders",), "world", "week", ("density",)), 34.0, "split").select("function_id", F.col("t").cast("long").alias("t"), "value")


@register(O.query("SELECT function_id, count(*) AS n_points FROM fn WHERE value >= 45 GROUP BY function_id", O.functions(("orders",), "world", "week", ("density",))))
def superlevel_by_flood(spark: SparkSession, sf: str) -> DataFrame:
    return topology.flood(dense(spark, sf, ("orders",), "world", "week", ("density",)), 45.0).select("function_id", "n_points")


@register(O.query("""SELECT component, min(t) AS first_t, max(t) AS last_t, count(*) AS n FROM (SELECT CAST(t AS BIGINT) AS t, CAST(sum(CASE WHEN t - lt = 1 THEN 0 ELSE 1 END) OVER (ORDER BY t) AS BIGINT) AS component
 FROM (SELECT t, lag(t) OVER (ORDER BY t) AS lt FROM fn WHERE value >= 45)) GROUP BY component""", O.functions(("orders",), "world", "week", ("density",))))
def components_1d_islands(spark: SparkSession, sf: str) -> DataFrame:
    pts = topology.islands(topology.level_set(dense(spark, sf, ("orders",), "world", "week", ("density",)), 45.0))
    return pts.groupBy("component").agg(F.min("t").cast("long").alias("first_t"), F.max("t").cast("long").alias("last_t"), F.count(F.lit(1)).alias("n"))


# --- thresholds and features ------------------------------------------------------------------

_WEEK = O.functions(WEEK_SETS, "world", "week", WEEK_MEASURES)
_DAY = O.functions(("orders",), "world", "day", ("density", "avg(o_totalprice)"))
_DAY_MEASURES = ("density", "avg(o_totalprice)")


def _week(spark: SparkSession, sf: str, fresh: bool = False) -> Index:
    return index(spark, sf, WEEK_SETS, "week", WEEK_MEASURES, fresh=fresh)


def _day(spark: SparkSession, sf: str) -> Index:
    return index(spark, sf, ("orders",), "day", _DAY_MEASURES)


@register(O.query("SELECT function_id, side, CAST(creator_t AS BIGINT) AS creator_t, round(persistence, 6) AS persistence, high FROM high", _WEEK, O.PAIRS, O.thresholds("week")))
def two_means_orders_week(spark: SparkSession, sf: str) -> DataFrame:
    return features.two_means(features.with_season(_week(spark, sf).pairs, "creator_t")).select("function_id", "side", F.col("creator_t").cast("long").alias("creator_t"), r6("persistence"), "high")


@register(O.query("SELECT function_id, season, side, round(theta, 6) AS theta FROM salient", _WEEK, O.PAIRS, O.thresholds("week")))
def salient_thresholds_week(spark: SparkSession, sf: str) -> DataFrame:
    return _week(spark, sf).salient.select("function_id", "season", "side", r6("theta"))


@register(O.query("SELECT function_id, season, side, round(theta, 6) AS theta FROM salient", _DAY, O.PAIRS, O.thresholds("day")))
def salient_thresholds_day_seasonal(spark: SparkSession, sf: str) -> DataFrame:
    return _day(spark, sf).salient.select("function_id", "season", "side", r6("theta"))


@register(O.query("SELECT function_id, side, round(theta, 6) AS theta FROM extreme", _DAY, O.PAIRS, O.thresholds("day")))
def extreme_thresholds_day(spark: SparkSession, sf: str) -> DataFrame:
    return _day(spark, sf).extreme.select("function_id", "side", r6("theta"))


_POINT_SELECT = "SELECT function_id, feature_type, CAST(t AS BIGINT) AS t, pos, neg FROM pts"


def _pts(df: DataFrame) -> DataFrame:
    return df.select("function_id", "feature_type", F.col("t").cast("long").alias("t"), "pos", "neg")


@register(O.query(_POINT_SELECT + " WHERE feature_type = 'salient'", _WEEK, O.PAIRS, O.thresholds("week"), O.points("week")))
def salient_features_week(spark: SparkSession, sf: str) -> DataFrame:
    return _pts(_week(spark, sf).points.where("feature_type = 'salient'"))


@register(O.query(_POINT_SELECT + " WHERE feature_type = 'extreme'", _DAY, O.PAIRS, O.thresholds("day"), O.points("day")))
def extreme_features_day(spark: SparkSession, sf: str) -> DataFrame:
    return _pts(_day(spark, sf).points.where("feature_type = 'extreme'"))


@register(O.query("SELECT function_id, feature_type, count(*) FILTER (pos) AS n_pos, count(*) FILTER (neg) AS n_neg, count(*) AS n_points FROM pts GROUP BY ALL", _WEEK, O.PAIRS, O.thresholds("week"), O.points("week")))
def feature_counts_all(spark: SparkSession, sf: str) -> DataFrame:
    return features.feature_counts(_week(spark, sf, True).bits).select("function_id", "feature_type", "n_pos", "n_neg", "n_points")


@register(O.query(_POINT_SELECT, _WEEK, O.PAIRS, O.thresholds("week"), O.points("week")))
def feature_bits_roundtrip(spark: SparkSession, sf: str) -> DataFrame:
    return _pts(features.from_bits(_week(spark, sf, True).bits))


@register(O.query("""SELECT theta, round(sum(tp) OVER w / sum(tp) OVER (), 6) AS tpr, round(sum(fp) OVER w / sum(fp) OVER (), 6) AS fpr FROM (SELECT value AS theta, count(*) FILTER (h) AS tp, count(*) FILTER (NOT h) AS fp
 FROM (SELECT f.value, f.t IN (SELECT t FROM pts WHERE function_id = 'lineitem.density' AND feature_type = 'salient' AND pos) AS h FROM fn f WHERE f.function_id = 'orders.density') GROUP BY value) WINDOW w AS (ORDER BY theta DESC ROWS UNBOUNDED PRECEDING)""",
    _WEEK, O.PAIRS, O.thresholds("week"), O.points("week")))
def roc_points(spark: SparkSession, sf: str) -> DataFrame:
    ix = _week(spark, sf)
    truth = ix.points.where("function_id = 'lineitem.density' AND feature_type = 'salient' AND pos")
    return features.roc(ix.functions.where("function_id = 'orders.density'"), truth).select("theta", r6("tpr"), r6("fpr"))


@register(O.query("""SELECT function_id, CAST(t AS BIGINT) AS t, round(value, 6) AS value, value > m AS pos FROM (SELECT *, avg(value) OVER w AS m, stddev_pop(value) OVER w AS s, count(*) OVER w AS n FROM fn WINDOW w AS (PARTITION BY function_id, region ORDER BY t ROWS BETWEEN 24 PRECEDING AND 1 PRECEDING))
 WHERE n = 24 AND abs(value - m) > 2.5 * s""", O.functions(("events",), "world", "hour", ("density",))))
def zscore_events(spark: SparkSession, sf: str) -> DataFrame:
    return features.zscore_events(dense(spark, sf, ("events",), "world", "hour", ("density",)), 24, 2.5).select("function_id", F.col("t").cast("long").alias("t"), r6("value"), "pos")


# --- relations and tests ----------------------------------------------------------------------

_REL = (_WEEK, O.PAIRS, O.thresholds("week"), O.points("week"), O.RELATION)
_REL_COLS = ["left_fn", "right_fn", "feature_type", "n1", "n2", "n_common", "n_pos", "n_neg"]
_REL_SELECT = "r.left_fn, r.right_fn, r.feature_type, r.n1, r.n2, r.n_common, r.n_pos, r.n_neg, round(r.score, 6) AS score, round(r.strength, 6) AS strength"


@register(O.query("SELECT CAST(t AS BIGINT) AS t, CAST((a.pos AND b.pos OR a.neg AND b.neg) AS INT) - CAST((a.pos AND b.neg OR a.neg AND b.pos) AS INT) AS rel FROM pts a JOIN pts b USING (feature_type, region, t) WHERE feature_type = 'salient' AND a.function_id = 'orders.density' AND b.function_id = 'lineitem.density'", *_REL))
def related_points_week(spark: SparkSession, sf: str) -> DataFrame:
    return explain(_week(spark, sf), "orders.density", "lineitem.density").select(F.col("t").cast("long").alias("t"), "rel")


@register(O.query(f"SELECT {_REL_SELECT}, round(precision, 6) AS precision, round(recall, 6) AS recall FROM rel r", *_REL))
def score_strength_week_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return RelationshipQuery(_week(spark, sf)).evaluate().select(*_REL_COLS, r6("score"), r6("strength"), r6("precision"), r6("recall"))


_TESTED = f"SELECT {_REL_SELECT}, CAST(n_perm AS BIGINT) AS n_perm, round(p_value, 6) AS p_value, coalesce(p_value <= 0.05, false) AS significant FROM rel r LEFT JOIN test USING (left_fn, right_fn, feature_type)"


def _tested(df: DataFrame) -> DataFrame:
    return df.select(*_REL_COLS, r6("score"), r6("strength"), "n_perm", r6("p_value"), "significant")


@register(O.query(_TESTED + " WHERE n_common > 0", *_REL, O.ROTATION))
def relation_orders_lineitem_week(spark: SparkSession, sf: str) -> DataFrame:
    return _tested(RelationshipQuery(_week(spark, sf), ("orders",), ("lineitem",)).run(False))


@register(O.query(_TESTED + " WHERE n_common > 0 AND p_value <= 0.05", *_REL, O.ROTATION))
def query_related_to_orders(spark: SparkSession, sf: str) -> DataFrame:
    return _tested(RelationshipQuery(_week(spark, sf), ("orders",)).run())


@register(O.query(_TESTED + " WHERE n_common > 0 AND abs(r.score) >= 0.05 AND r.strength >= 0.3 AND r.feature_type = 'salient'", *_REL, O.ROTATION))
def query_with_clause(spark: SparkSession, sf: str) -> DataFrame:
    return _tested(RelationshipQuery(_week(spark, sf), clause=Clause(min_abs_score=0.05, min_strength=0.3, feature_types=("salient",))).run(False))


_SPLITS = ("orders_F", "orders_O", "orders_P", "lineitem_A", "lineitem_N", "lineitem_R")
_SPLIT = O.functions(_SPLITS, "world", "week")
_SPLIT_CTES = (_SPLIT, O.PAIRS, O.thresholds("week"), O.points("week"), O.RELATION, O.ROTATION)


def _splits(spark: SparkSession, sf: str) -> Index:
    """All measures of both tables by status and flag, at (week, world): one scan a table."""
    key = (spark.sparkContext.applicationId, sf, "splits")
    if key not in _INDEX:
        _INDEX[key] = index_corpus(catalog.splits(spark, sf), spaces=("world",), times=("week",))
    return _INDEX[key]


def forget_indexes() -> None:
    """Lets the next query build its index anew."""
    _INDEX.clear()


@register(O.query("SELECT d AS dataset, count(DISTINCT o) AS degree FROM (SELECT left_dataset AS d, right_dataset AS o, left_fn, right_fn, feature_type FROM rel UNION ALL SELECT right_dataset, left_dataset, left_fn, right_fn, feature_type FROM rel) JOIN test USING (left_fn, right_fn, feature_type) WHERE p_value <= 0.05 GROUP BY d", *_SPLIT_CTES))
def dataset_degree_splits(spark: SparkSession, sf: str) -> DataFrame:
    return dataset_degree(RelationshipQuery(_splits(spark, sf)).run())


@register(O.query("SELECT feature_type, count(*) AS candidates, count(*) FILTER (p_value <= 0.05) AS significant, count(*) FILTER (p_value <= 0.05 AND abs(r.score) >= 0.6) AS strong, count(*) FILTER (p_value <= 0.05 AND abs(r.score) >= 0.8) AS stronger FROM rel r LEFT JOIN test USING (left_fn, right_fn, feature_type) GROUP BY feature_type", *_SPLIT_CTES))
def pruning_week_world(spark: SparkSession, sf: str) -> DataFrame:
    q = RelationshipQuery(_splits(spark, sf))
    every = q.evaluate().groupBy("feature_type").agg(F.count(F.lit(1)).alias("candidates"))
    n = lambda c: F.sum(c.cast("int"))
    found = q.run().groupBy("feature_type").agg(F.count(F.lit(1)).alias("significant"), n(F.abs("score") >= 0.6).alias("strong"), n(F.abs("score") >= 0.8).alias("stronger"))
    return every.join(found, "feature_type", "left").fillna(0)


@register(O.query("SELECT r.left_dataset, r.left_fn, r.right_fn, r.feature_type, row_number() OVER (PARTITION BY r.left_dataset ORDER BY abs(r.score) DESC, r.strength DESC, r.left_fn, r.right_fn, r.feature_type) AS rank FROM rel r WHERE n_common > 0 QUALIFY rank <= 5", *_REL))
def topk_pairs_per_dataset(spark: SparkSession, sf: str) -> DataFrame:
    return rank_relationships(RelationshipQuery(_week(spark, sf)).evaluate().where("n_common > 0"), 5).select("left_dataset", "left_fn", "right_fn", "feature_type", F.col("rank").cast("long").alias("rank"))


@register(f"""SELECT count(*) AS n FROM (SELECT min({O.step("ts", "day")}) AS a, max({O.step("ts", "day")}) AS b FROM events), (SELECT min({O.step("o_orderdate", "day")}) AS c, max({O.step("o_orderdate", "day")}) AS d FROM orders) WHERE a <= d AND c <= b""")
def no_overlap_events_orders(spark: SparkSession, sf: str) -> DataFrame:
    fn = dense(spark, sf, ("orders", "events"), "world", "day", ("density",))
    return relate.candidate_pairs(relate.spans(fn)).agg(F.count(F.lit(1)).alias("n"))


@register(O.query("SELECT left_fn, right_fn, feature_type, CAST(lag AS BIGINT) AS lag, n_common, n_pos, n_neg FROM lg", *_REL, O.ROTATION))
def rotation_null_week(spark: SparkSession, sf: str) -> DataFrame:
    ix = _week(spark, sf)
    return relate.lag_histogram(relate.candidate_pairs(ix.meta), ix.points).select("left_fn", "right_fn", "feature_type", F.col("lag").cast("long").alias("lag"), "n_common", "n_pos", "n_neg")


@register(O.query("SELECT left_fn, right_fn, feature_type, CAST(n_perm AS BIGINT) AS n_perm, round(p_value, 6) AS p_value FROM test", *_REL, O.ROTATION))
def rotation_pvalues_week(spark: SparkSession, sf: str) -> DataFrame:
    ix = _week(spark, sf)
    return relate.rotation_test_words(relate.candidate_pairs(ix.meta), ix.bits).select("left_fn", "right_fn", "feature_type", "n_perm", r6("p_value"))


@register(O.query("""SELECT o.left_fn, o.right_fn, o.feature_type, round((le + CASE WHEN obs >= 0 THEN n_perm - present ELSE 0 END) / n_perm, 6) AS p_lower, round((ge + CASE WHEN obs <= 0 THEN n_perm - present ELSE 0 END) / n_perm, 6) AS p_upper
 FROM ob o JOIN nl USING (left_fn, right_fn, feature_type)""", *_REL, O.ROTATION))
def pvalue_tails(spark: SparkSession, sf: str) -> DataFrame:
    ix = _week(spark, sf)
    pairs = relate.candidate_pairs(ix.meta)
    key = ["left_fn", "right_fn", "feature_type"]
    a = relate.rotation_test_words(pairs, ix.bits, tail="lower").select(*key, F.round("p_value", 6).alias("p_lower"))
    b = relate.rotation_test_words(pairs, ix.bits, tail="upper").select(*key, F.round("p_value", 6).alias("p_upper"))
    return a.join(b, key)


_LOCAL = """, loc AS (SELECT function_id, region, t, value >= 2 AS pos, value <= 0 AS neg FROM fn WHERE value >= 2 OR value <= 0),
ev AS (SELECT * FROM loc)"""


def _typed(spark: SparkSession, sf: str) -> DataFrame:
    """Densities of two event types on hour x nation, with fixed thresholds."""
    ev = catalog.events(spark, sf)
    out = None
    for kind in ("click", "purchase"):
        s = ev.where(kind, f"event_type = '{kind}'")
        fn = scalar.long(scalar.wide(s, "nation", "hour", (), ()), kind, "nation", "hour")
        out = fn if out is None else out.unionByName(fn)
    return scalar.densify(out)


def _typed_sql() -> str:
    src, when, _, _, _ = O.SETS["events"]
    parts = [f"SELECT '{k}.density' AS function_id, CAST(c_nationkey AS VARCHAR) AS region, {O.step(when, 'hour')} AS t, CAST(count(*) AS DOUBLE) AS value FROM {src} AS s WHERE event_type = '{k}' GROUP BY ALL" for k in ("click", "purchase")]
    return O.functions(("orders",), "world", "week", ("density",)).replace(O.raw("orders", "world", "week", ("density",)), " UNION ALL ".join(parts))


@register(O.query("""SELECT round(obs, 6) AS score, CAST(24 AS BIGINT) AS n_perm, round(count(*) FILTER (k <> 0 AND CASE WHEN obs < 0 THEN s <= obs ELSE s >= obs END) / 24, 6) AS p_value FROM
 (SELECT k, round((sum(np) - sum(nn)) / sum(nc), 9) AS s, max(CASE WHEN k = 0 THEN round((sum(np) - sum(nn)) / sum(nc), 9) END) OVER () AS obs FROM
  (SELECT r1, r2, nc, np, nn, ((CAST(r1 AS INT) // 5 - CAST(r2 AS INT) // 5 + 5) % 5) * 5 + (CAST(r1 AS INT) % 5 - CAST(r2 AS INT) % 5 + 5) % 5 AS k FROM
   (SELECT a.region AS r1, b.region AS r2, count(*) AS nc, count(*) FILTER (a.pos AND b.pos OR a.neg AND b.neg) AS np, count(*) FILTER (a.pos AND b.neg OR a.neg AND b.pos) AS nn
    FROM loc a JOIN loc b USING (t) WHERE a.function_id = 'click.density' AND b.function_id = 'purchase.density' AND t BETWEEN (SELECT max(lo) FROM sp) AND (SELECT min(hi) FROM sp) GROUP BY ALL)) GROUP BY k) GROUP BY obs""", _typed_sql(), _LOCAL))
def lattice_shift_pvalues_hour_nation(spark: SparkSession, sf: str) -> DataFrame:
    fn = _typed(spark, sf)
    pts = features.from_user(fn, {"click.density": (0.0, 2.0), "purchase.density": (0.0, 2.0)})
    pairs = relate.candidate_pairs(relate.spans(fn))
    test = relate.spatial_test(pairs, pts, permute.lattice_maps(spark, 5, 5))
    seen = relate.co_occurrence(pairs, pts).where("r1 = r2").agg(((F.sum("n_pos") - F.sum("n_neg")) / F.sum("n_common")).alias("score"))
    return test.crossJoin(F.broadcast(seen)).select(r6("score"), "n_perm", r6("p_value"))


@register()
def graph_shift_pvalues_hour_nation(spark: SparkSession, sf: str) -> DataFrame:
    fn = _typed(spark, sf)
    pts = features.from_user(fn, {"click.density": (0.0, 2.0), "purchase.density": (0.0, 2.0)})
    return relate.spatial_test(relate.candidate_pairs(relate.spans(fn)), pts, permute.graph_maps(space.lattice(spark, 5, 5), 1000))


@register(O.query("SELECT left_fn, right_fn, feature_type, round(least(1.0, min(p_value * m / rk) OVER (ORDER BY p_value DESC RANGE UNBOUNDED PRECEDING)), 6) AS p_adjusted FROM (SELECT *, count(*) OVER (ORDER BY p_value RANGE UNBOUNDED PRECEDING) AS rk, count(*) OVER () AS m FROM test)", *_REL, O.ROTATION))
def adjusted_pvalues_week(spark: SparkSession, sf: str) -> DataFrame:
    ix = _week(spark, sf)
    t = permute.adjust_bh(relate.rotation_test_words(relate.candidate_pairs(ix.meta), ix.bits))
    return t.select("left_fn", "right_fn", "feature_type", r6("p_adjusted"))



# --- baselines --------------------------------------------------------------------------------

_ALIGNED = (_WEEK, O.PAIRS, O.thresholds("week"), O.points("week"), O.RELATION, ", al AS (SELECT left_fn, right_fn, a.value AS x, b.value AS y FROM cand JOIN fn a ON a.function_id = left_fn AND a.t BETWEEN lo AND hi JOIN fn b ON b.function_id = right_fn AND b.t = a.t)")


def _base(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    ix = _week(spark, sf)
    return relate.candidate_pairs(ix.meta), ix.functions


@register(O.query("SELECT left_fn, right_fn, round(corr(x, y), 6) AS pcc FROM al GROUP BY ALL", *_ALIGNED))
def pcc_week_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.pearson(*_base(spark, sf)).select("left_fn", "right_fn", r6("pcc"))


@register(O.query("""SELECT left_fn, right_fn, round(any_value(mi) / sqrt(any_value(hx) * any_value(hy)), 6) AS nmi FROM (SELECT left_fn, right_fn, sum(c / n * ln(c * n / (cx * cy))) AS mi, sum(-c / n * ln(cx / n)) AS hx, sum(-c / n * ln(cy / n)) AS hy FROM
 (SELECT *, sum(c) OVER (PARTITION BY left_fn, right_fn, bx) AS cx, sum(c) OVER (PARTITION BY left_fn, right_fn, by_) AS cy FROM (SELECT left_fn, right_fn, n, least(floor((x - x0) / (x1 - x0) * k), k - 1) AS bx, least(floor((y - y0) / (y1 - y0) * k), k - 1) AS by_, CAST(count(*) AS DOUBLE) AS c FROM
  (SELECT *, count(*) OVER w AS n, least(greatest(ceil(sqrt(count(*) OVER w / 5)), 2), 64) AS k, min(x) OVER w AS x0, max(x) OVER w AS x1, min(y) OVER w AS y0, max(y) OVER w AS y1 FROM al WINDOW w AS (PARTITION BY left_fn, right_fn)) GROUP BY ALL)) GROUP BY ALL) GROUP BY left_fn, right_fn""", *_ALIGNED))
def nmi_week_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.mutual_information(*_base(spark, sf)).select("left_fn", "right_fn", r6("nmi"))


@register(O.query("SELECT left_fn, right_fn, round(regr_slope(y, x), 6) AS slope, round(regr_intercept(y, x), 6) AS intercept, round(regr_r2(y, x), 6) AS r2 FROM al GROUP BY ALL", *_ALIGNED))
def ols_week_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.least_squares(*_base(spark, sf)).select("left_fn", "right_fn", r6("slope"), r6("intercept"), r6("r2"))


@register(O.query("SELECT left_fn, right_fn, round(regr_slope(y, CASE WHEN x > m THEN 1.0 ELSE 0.0 END), 6) AS slope FROM (SELECT *, avg(x) OVER (PARTITION BY left_fn, right_fn) AS m FROM al) GROUP BY ALL", *_ALIGNED))
def ols_binary_week_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.least_squares(*_base(spark, sf), binary=True).select("left_fn", "right_fn", r6("slope"))


@register(O.query("""SELECT left_fn, right_fn, ours, theirs, CASE WHEN ours AND theirs THEN 'both' WHEN ours THEN 'only ours' WHEN theirs THEN 'only pcc' ELSE 'none' END AS verdict FROM
 (SELECT c.left_fn, c.right_fn, coalesce(bool_or(p_value <= 0.05), false) AS ours, any_value(abs(pcc) >= 0.1) AS theirs FROM (SELECT left_fn, right_fn, corr(x, y) AS pcc FROM al GROUP BY ALL) c LEFT JOIN test USING (left_fn, right_fn) GROUP BY ALL)""", *_ALIGNED, O.ROTATION))
def method_comparison(spark: SparkSession, sf: str) -> DataFrame:
    ix = _week(spark, sf)
    found = RelationshipQuery(ix).run(False)
    return baselines.compare_methods(found, baselines.pearson(*_base(spark, sf)), "pcc", 0.1).select("left_fn", "right_fn", "ours", "theirs", "verdict")
