"""Registered queries: merge trees and relations over regions, every resolution at once, permutation
tests with given moves, planted case studies, and whole corpora."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strel import oracle as O
from strel import oracle_space as S
from strel.operators import baselines, features, permute, relate, scalar, space, topology
from strel.plans import workloads as W
from strel.plans.query import Clause, Index, RelationshipQuery, features_through_index, index_corpus, index_functions
from strel.queries import _ALIGNED, _INDEX, _REL, _REL_COLS, WEEK_SETS, _base, _tested, _week, dense, index, nations, r6, register
from strel.queries_more import _TEST, _all, _fill, u
from strel.runtime import materialize, table
from strel.sources import catalog

_LONG = lambda *cs: [F.col(c).cast("long").alias(c) for c in cs]


def _regions(spark: SparkSession, sf: str) -> DataFrame:
    return catalog.space_maps(spark, sf)["region"]


# --- trees over regions -----------------------------------------------------------------------

_SPACE_PAIR = "SELECT function_id, side, creator_region, CAST(creator_t AS BIGINT) AS creator_t, destroyer_region, CAST(destroyer_t AS BIGINT) AS destroyer_t, birth, death, persistence, essential FROM pairs"
_OM = O.functions(("orders",), "region", "month")
_OMD = O.functions(("orders",), "region", "month", ("density",))
_ED = O.functions(("events",), "nation", "day", ("density",))


def _space_pairs(p: DataFrame) -> DataFrame:
    return p.select("function_id", "side", "creator_region", *_LONG("creator_t"), "destroyer_region", *_LONG("destroyer_t"), "birth", "death", "persistence", "essential")


@register(O.query(_SPACE_PAIR, _OM, S.graph(S.REGIONS)))
def persistence_orders_month_region(spark: SparkSession, sf: str) -> DataFrame:
    return _space_pairs(topology.persistence(dense(spark, sf, ("orders",), "region", "month"), _regions(spark, sf)))


@register(O.query(_SPACE_PAIR, _OMD, S.graph(S.REGIONS)))
def persistence_large_orders_month_region(spark: SparkSession, sf: str) -> DataFrame:
    """The same for one function spread over tasks."""
    return _space_pairs(topology.persistence_large(dense(spark, sf, ("orders",), "region", "month", ("density",)), _regions(spark, sf), 50))


@register(O.query(_SPACE_PAIR, _ED, S.graph(S.NATIONS)))
def persistence_events_day_nation(spark: SparkSession, sf: str) -> DataFrame:
    return _space_pairs(topology.persistence(dense(spark, sf, ("events",), "nation", "day", ("density",)), space.lattice(spark, 5, 5)))


_TREE = "SELECT function_id, side, upper_region, CAST(upper_t AS BIGINT) AS upper_t, lower_region, CAST(lower_t AS BIGINT) AS lower_t FROM tree"


def _edges(d: DataFrame) -> DataFrame:
    return d.select("function_id", "side", "upper_region", *_LONG("upper_t"), "lower_region", *_LONG("lower_t"))


@register(O.query(_TREE, _OMD, S.graph(S.REGIONS)))
def merge_trees_orders_month_region(spark: SparkSession, sf: str) -> DataFrame:
    return _edges(topology.merge_tree(dense(spark, sf, ("orders",), "region", "month", ("density",)), _regions(spark, sf)))


@register(O.query(_TREE, O.functions(WEEK_SETS, "world", "week", ("density",)), S.graph(S.NOWHERE)))
def join_tree_edges_week(spark: SparkSession, sf: str) -> DataFrame:
    return _edges(topology.merge_tree(dense(spark, sf, WEEK_SETS, "world", "week", ("density",))))


_LEAF = "SELECT p.function_id, p.region, CAST(p.t AS BIGINT) AS t, q.region AS leaf_region, CAST(q.t AS BIGINT) AS leaf_t FROM px p LEFT JOIN (SELECT DISTINCT function_id, side, k, oldest FROM meet) m USING (function_id, side, k) JOIN px q ON q.function_id = p.function_id AND q.side = p.side AND q.k = coalesce(m.oldest, p.k) WHERE p.side = 'join'"


def _leaves(d: DataFrame) -> DataFrame:
    return d.select("function_id", "region", *_LONG("t"), "leaf_region", *_LONG("leaf_t"))


@register(O.query(_LEAF, _OMD, S.graph(S.REGIONS)))
def segmentation_orders_month_region(spark: SparkSession, sf: str) -> DataFrame:
    return _leaves(topology.segmentation(dense(spark, sf, ("orders",), "region", "month", ("density",)), _regions(spark, sf)))


@register(O.query(_LEAF, O.functions(("orders",), "world", "week", ("density",)), S.graph(S.NOWHERE)))
def segmentation_orders_week(spark: SparkSession, sf: str) -> DataFrame:
    return _leaves(topology.segmentation(dense(spark, sf, ("orders",), "world", "week", ("density",))))


_DEGREES = """, deg AS (SELECT p.function_id, p.region, p.t, count(n.u) FILTER (n.u < p.k) AS up, count(n.u) FILTER (n.u > p.k) AS down FROM px p LEFT JOIN touch n USING (function_id, side, k) WHERE p.side = 'join' GROUP BY ALL),
dual AS (SELECT p.function_id, p.region, p.t, count(n.u) FILTER (n.u < p.k) AS low FROM px p LEFT JOIN touch n USING (function_id, side, k) WHERE p.side = 'split' GROUP BY ALL),
kinds AS (SELECT function_id, region, t, CASE WHEN up = 0 AND down > 0 THEN 'max' WHEN down = 0 THEN 'min' WHEN up = 1 AND down = 1 THEN 'regular' WHEN greatest(up, down) = 2 THEN 'saddle' ELSE 'degenerate' END AS kind FROM deg)"""


def _graph_of_touch(fn: str, links: str) -> str:
    """``px`` and ``touch`` alone."""
    whole = S.graph(links)
    return fn + whole[: whole.index(",\nreach AS")]


@register(O.query("SELECT function_id, region, CAST(t AS BIGINT) AS t, kind FROM kinds", _graph_of_touch(O.functions(("events",), "nation", "hour", ("density",)), S.NATIONS), _DEGREES))
def classify_points_hour_nation(spark: SparkSession, sf: str) -> DataFrame:
    """No two neighbours of a point of this lattice are adjacent, so links fall apart into points."""
    return topology.classify(dense(spark, sf, ("events",), "nation", "hour", ("density",)), space.lattice(spark, 5, 5)).select("function_id", "region", *_LONG("t"), "kind")


@register(O.query("SELECT kind, count(*) AS n FROM kinds GROUP BY kind", _graph_of_touch(O.functions(("events",), "nation", "hour", ("density",)), S.NATIONS), _DEGREES))
def classify_events_hour_nation(spark: SparkSession, sf: str) -> DataFrame:
    return topology.classify(dense(spark, sf, ("events",), "nation", "hour", ("density",)), space.lattice(spark, 5, 5)).groupBy("kind").agg(F.count(F.lit(1)).alias("n"))


@register(O.query("SELECT function_id, side, creator_region, CAST(creator_t AS BIGINT) AS creator_t, persistence FROM pairs WHERE persistence >= 4 OR essential", _OMD, S.graph(S.REGIONS)))
def simplified_orders_month_region(spark: SparkSession, sf: str) -> DataFrame:
    p = topology.persistence(dense(spark, sf, ("orders",), "region", "month", ("density",)), _regions(spark, sf))
    return topology.simplify(p, 4.0).select("function_id", "side", "creator_region", *_LONG("creator_t"), "persistence")


_RIM = """, hot AS (SELECT * FROM px WHERE side = 'join' AND value >= 45)"""


@register(O.query("""SELECT h.function_id, count(*) AS n_points, CAST(sum(2 + (SELECT count(*) FROM adj WHERE a = h.region)) AS BIGINT) AS touched FROM hot h GROUP BY h.function_id""", _graph_of_touch(_OMD, S.REGIONS), _RIM))
def flood_touched_month_region(spark: SparkSession, sf: str) -> DataFrame:
    """Points looked at by a feature query: those of the level set and their rim, not all."""
    fn = dense(spark, sf, ("orders",), "region", "month", ("density",))
    near = _regions(spark, sf)
    leaves = topology.leaves_past(topology.persistence(fn, near), 45.0)
    return topology.flood(fn, 45.0, near, leaves).select("function_id", "n_points", "touched")


@register(O.query("SELECT function_id, side, creator_region, CAST(creator_t AS BIGINT) AS creator_t FROM pairs WHERE side = 'join' AND birth >= 45", _OMD, S.graph(S.REGIONS)))
def valid_extrema_month_region(spark: SparkSession, sf: str) -> DataFrame:
    p = topology.persistence(dense(spark, sf, ("orders",), "region", "month", ("density",)), _regions(spark, sf))
    return topology.leaves_past(p, 45.0).select("function_id", F.lit("join").alias("side"), F.col("region").alias("creator_region"), F.col("t").cast("long").alias("creator_t"))


@register(O.query("SELECT function_id, region, CAST(t AS BIGINT) AS t, value >= 45 AS pos, value <= 30 AS neg FROM fn WHERE value >= 45 OR value <= 30", _OMD))
def features_through_index_month_region(spark: SparkSession, sf: str) -> DataFrame:
    near = {"region": _regions(spark, sf)}
    ix = index_functions(dense(spark, sf, ("orders",), "region", "month", ("density",)), near)
    return features_through_index(ix, {"orders.density": (30.0, 45.0)}).select("function_id", "region", *_LONG("t"), "pos", "neg")


_LEVEL = """, lv AS (SELECT function_id, k FROM px WHERE side = 'join' AND value >= 42),
cl AS (WITH RECURSIVE r AS (SELECT function_id, k, k AS w FROM lv UNION SELECT r.function_id, r.k, n.u FROM r JOIN touch n ON n.function_id = r.function_id AND n.side = 'join' AND n.k = r.w JOIN lv ON lv.function_id = r.function_id AND lv.k = n.u) SELECT * FROM r)"""


@register(O.query("""SELECT c.function_id, p.region AS leaf_region, CAST(p.t AS BIGINT) AS leaf_t, count(*) AS n_points FROM (SELECT function_id, k, min(w) AS top FROM cl GROUP BY ALL) c
 JOIN px p ON p.function_id = c.function_id AND p.side = 'join' AND p.k = c.top GROUP BY ALL""", _graph_of_touch(_OMD, S.REGIONS), _LEVEL))
def level_components_month_region(spark: SparkSession, sf: str) -> DataFrame:
    """Components of a super-level set over regions and months, by size."""
    found = topology.level_components(dense(spark, sf, ("orders",), "region", "month", ("density",)), 42.0, _regions(spark, sf))
    return found.groupBy("function_id", "leaf_region", F.col("leaf_t").cast("long").alias("leaf_t")).agg(F.count(F.lit(1)).alias("n_points"))


# --- thresholds, features and relations over regions ------------------------------------------

_RM = O.functions(WEEK_SETS, "region", "month")
_SPACE = (_RM, S.graph(S.REGIONS), O.thresholds("month"), O.points("month"))


def _space_index(spark: SparkSession, sf: str) -> Index:
    key = (spark.sparkContext.applicationId, sf, "region", "month")
    if key not in _INDEX:
        _INDEX[key] = index_functions(dense(spark, sf, WEEK_SETS, "region", "month"), {"region": _regions(spark, sf)})
    return _INDEX[key]


@register(O.query("SELECT function_id, side, round(theta, 6) AS theta FROM salient", *_SPACE))
def salient_thresholds_month_region(spark: SparkSession, sf: str) -> DataFrame:
    return _space_index(spark, sf).salient.select("function_id", "side", r6("theta"))


@register(O.query("SELECT function_id, side, round(theta, 6) AS theta FROM extreme", *_SPACE))
def extreme_thresholds_month_region(spark: SparkSession, sf: str) -> DataFrame:
    return _space_index(spark, sf).extreme.select("function_id", "side", r6("theta"))


@register(O.query("SELECT function_id, feature_type, region, CAST(t AS BIGINT) AS t, pos, neg FROM pts", *_SPACE))
def features_month_region(spark: SparkSession, sf: str) -> DataFrame:
    return _space_index(spark, sf).points.select("function_id", "feature_type", "region", *_LONG("t"), "pos", "neg")


@register(O.query(_TEST, *_SPACE, O.RELATION, S.grown_maps(S.lattice_links(1, 5), 40), S.MAP_TEST))
def relation_month_region(spark: SparkSession, sf: str) -> DataFrame:
    """All relationships at (month, region), tested with 40 grown maps of the regions."""
    return _tested(RelationshipQuery(_space_index(spark, sf), n_maps=40).run(False))


@register(O.query("SELECT left_fn, right_fn, feature_type, CAST(n_perm AS BIGINT) AS n_perm, round(p_value, 6) AS p_value FROM test", *_SPACE, O.RELATION, S.grown_maps(S.lattice_links(1, 5), 8), S.TORUS_TEST))
def space_time_pvalues_month_region(spark: SparkSession, sf: str) -> DataFrame:
    """Regions and steps moved at once."""
    ix = _space_index(spark, sf)
    test = relate.space_time_test(relate.candidate_pairs(ix.meta), ix.points, permute.graph_maps(_regions(spark, sf), 8))
    return test.select("left_fn", "right_fn", "feature_type", "n_perm", r6("p_value"))


_NEAR_ED = S.lattice_links(5, 5)
_TYPES = ("click", "purchase", "view")


def _by_type(spark: SparkSession, sf: str) -> DataFrame:
    """Daily densities of three event types by nation."""
    ev = catalog.events(spark, sf).family("events", F.when(F.col("event_type").isin(*_TYPES), F.col("event_type")))
    return scalar.all_functions([ev], ("nation",), ("day",)).where("function_id LIKE '%.density'")


_by_type_sql = _fill(" UNION ALL ".join(f"SELECT '{k}.density' AS function_id, CAST(c_nationkey AS VARCHAR) AS region, {O.step('ts', 'day')} AS t, CAST(count(*) AS DOUBLE) AS value FROM {O.SETS['events'][0]} AS s WHERE event_type = '{k}' AND c_nationkey IS NOT NULL GROUP BY ALL" for k in _TYPES))


@register(O.query(_TEST, *S.related(_by_type_sql, "day", S.NATIONS, S.grown_maps(_NEAR_ED, 60) + S.MAP_TEST)))
def relation_types_day_nation(spark: SparkSession, sf: str) -> DataFrame:
    """Event types over the lattice of nations, tested with 60 grown maps."""
    ix = index_functions(_by_type(spark, sf), {"nation": space.lattice(spark, 5, 5)})
    return _tested(RelationshipQuery(ix, n_maps=60).run(False))


@register("SELECT CAST(k AS BIGINT) AS k, region, image FROM " + S.grown_maps(_NEAR_ED, 200).replace(",\nmaps AS ", "").strip() + " m")
def graph_shift_maps(spark: SparkSession, sf: str) -> DataFrame:
    return permute.graph_maps(space.lattice_of(nations(spark, sf), 5), 200).select(*_LONG("k"), "region", "image")


@register(O.query("""SELECT CAST(m.k AS BIGINT) AS k, round(count(x.a) / count(*), 6) AS fidelity FROM adj JOIN maps m ON m.region = adj.a JOIN maps n ON n.region = adj.b AND n.k = m.k
 LEFT JOIN adj x ON x.a = m.image AND x.b = n.image GROUP BY m.k""", f"adj AS ({S.NATIONS})", S.grown_maps(_NEAR_ED, 200)))
def map_fidelity(spark: SparkSession, sf: str) -> DataFrame:
    a = space.lattice_of(nations(spark, sf), 5)
    return permute.fidelity(permute.graph_maps(a, 200), a).select(*_LONG("k"), r6("fidelity"))


# --- every resolution at once -----------------------------------------------------------------

_RES_COLS = ["space_res", "time_res", *_REL_COLS]


def _resolved(d: DataFrame) -> DataFrame:
    return d.select(*_RES_COLS, r6("score"), r6("strength"), "n_perm", r6("p_value"), "significant")


def _at(space_res: str, time_res: str, select: str, *ctes: str) -> str:
    return O.query(select.replace("SELECT ", f"SELECT '{space_res}' AS space_res, '{time_res}' AS time_res, ", 1), *ctes)


def _parts_sql(select: str) -> str:
    parts = [_at("world", t, select, *_all(t, O.functions(WEEK_SETS, "world", t))) for t in ("day", "week", "month")]
    parts.append(_at("region", "month", select, *_SPACE, O.RELATION, S.grown_maps(S.lattice_links(1, 5), 40), S.MAP_TEST))
    return S.both(*parts)


def _every(spark: SparkSession, sf: str) -> Index:
    """Orders and lineitem at day, week and month over the world, and at month by region: one scan a table."""
    key = (spark.sparkContext.applicationId, sf, "every")
    if key not in _INDEX:
        specs = [catalog.orders(spark, sf), catalog.lineitem(spark, sf)]
        near = {"region": _regions(spark, sf)}
        fn = scalar.all_functions(specs, ("world", "region"), ("day", "week", "month")).where("space_res = 'world' OR time_res = 'month'")
        _INDEX[key] = index_functions(fn, near)
    return _INDEX[key]


@register(_parts_sql(_TEST))
def query_all_resolutions(spark: SparkSession, sf: str) -> DataFrame:
    """Every relationship of orders and lineitem at every resolution that they are indexed at."""
    return _resolved(RelationshipQuery(_every(spark, sf), ("orders",), ("lineitem",), n_maps=40).run(False))


@register(_parts_sql(_TEST + " AND p_value <= 0.05"))
def query_significant_all_resolutions(spark: SparkSession, sf: str) -> DataFrame:
    return _resolved(RelationshipQuery(_every(spark, sf), ("orders",), n_maps=40).run())


@register(S.both(*[_at("world", t, _TEST + " AND abs(r.score) >= 0.1 AND r.strength >= 0.5 AND r.feature_type = 'salient'", *_all(t, O.functions(WEEK_SETS, "world", t))) for t in ("week", "month")]))
def query_clause_with_resolutions(spark: SparkSession, sf: str) -> DataFrame:
    """A clause on score, strength, feature type and resolution; pairs too unlike in size never meet."""
    c = Clause(min_abs_score=0.1, min_strength=0.5, feature_types=("salient",), space_res=("world",), time_res=("week", "month"))
    return _resolved(RelationshipQuery(_every(spark, sf), clause=c).run(False))


@register(S.both(*[_at(sp, t, "SELECT function_id, count(*) AS n_values, CAST(round(sum(value) * 100) AS BIGINT) AS total FROM fn GROUP BY function_id", O.functions(WEEK_SETS, sp, t)) for sp in ("world", "region") for t in ("day", "week", "month")]))
def all_viable_functions(spark: SparkSession, sf: str) -> DataFrame:
    """Functions of both tables at six resolutions, from one scan each."""
    fn = scalar.all_functions([catalog.orders(spark, sf), catalog.lineitem(spark, sf)], ("world", "region"), ("day", "week", "month"))
    return fn.groupBy("space_res", "time_res", "function_id").agg(F.count(F.lit(1)).alias("n_values"), F.round(F.sum("value") * 100).cast("long").alias("total"))


@register("""SELECT * FROM (VALUES ('events', 'nation', 'day'), ('events', 'nation', 'hour'), ('events', 'nation', 'month'), ('events', 'nation', 'week'), ('events', 'region', 'day'), ('events', 'region', 'hour'), ('events', 'region', 'month'),
 ('events', 'region', 'week'), ('events', 'segment', 'day'), ('events', 'segment', 'hour'), ('events', 'segment', 'month'), ('events', 'segment', 'week'), ('events', 'world', 'day'), ('events', 'world', 'hour'), ('events', 'world', 'month'), ('events', 'world', 'week'),
 ('lineitem', 'nation', 'day'), ('lineitem', 'nation', 'month'), ('lineitem', 'nation', 'week'), ('lineitem', 'region', 'day'), ('lineitem', 'region', 'month'), ('lineitem', 'region', 'week'), ('lineitem', 'world', 'day'), ('lineitem', 'world', 'month'), ('lineitem', 'world', 'week')) v(dataset, space_res, time_res)""")
def viable_resolutions(spark: SparkSession, sf: str) -> DataFrame:
    """Resolutions at which functions of two tables come out of the index: no finer than their own."""
    out = None
    for s in (catalog.events(spark, sf), catalog.lineitem(spark, sf)):
        found = scalar.viable(s)
        one = scalar.from_observed(*scalar.observe(s, found), s, found)
        out = one if out is None else out.unionByName(one)
    return out.select(F.substring_index("function_id", ".", 1).alias("dataset"), "space_res", "time_res").distinct()


@register(O.query("SELECT time_res, count(*) AS n FROM (SELECT unnest(['day', 'week', 'month']) AS time_res), cand GROUP BY time_res", O.functions(WEEK_SETS, "world", "month"), ", " + O.RELATION[O.RELATION.index("mt AS"): O.RELATION.index(",\nft AS")]))
def common_resolution_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """Candidate pairs by common resolution, from the stored index."""
    pairs = relate.candidate_pairs(_every(spark, sf).meta).where("space_res = 'world'")
    return pairs.groupBy("time_res").agg(F.count(F.lit(1)).alias("n"))


@register(f"SELECT space_res, time_res, feature_type, count(*) AS tested, round(avg(CAST(p_value <= 0.05 AS INT)), 6) AS share FROM ({_parts_sql(_TEST)}) WHERE p_value IS NOT NULL GROUP BY ALL")
def calibration_by_resolution(spark: SparkSession, sf: str) -> DataFrame:
    """Share of accepted pairs of unrelated tables, by resolution and feature type."""
    r = RelationshipQuery(_every(spark, sf), ("orders",), ("lineitem",), n_maps=40).run(False).where("p_value IS NOT NULL")
    return r.groupBy("space_res", "time_res", "feature_type").agg(F.count(F.lit(1)).alias("tested"), F.round(F.avg((F.col("p_value") <= 0.05).cast("int")), 6).alias("share"))


@register(S.both(*[_at("world", t, "SELECT f.function_id, n_values, n_pairs FROM (SELECT function_id, count(*) AS n_values FROM fn GROUP BY ALL) f JOIN (SELECT function_id, count(*) AS n_pairs FROM pairs GROUP BY ALL) p USING (function_id)", O.functions(WEEK_SETS, "world", t), O.PAIRS) for t in ("day", "week", "month")]))
def extrema_against_points(spark: SparkSession, sf: str) -> DataFrame:
    """Size of the index beside that of its function: extrema and points."""
    ix = _every(spark, sf)
    n = ix.pairs.where("space_res = 'world'").groupBy("function_id", "space_res", "time_res").agg(F.count(F.lit(1)).alias("n_pairs"))
    return n.join(ix.meta.select("function_id", "space_res", "time_res", "n_values"), ["function_id", "space_res", "time_res"])


@register(O.query("SELECT function_id, season, side, round(theta, 6) AS theta FROM salient", O.functions(("orders",), "world", "day", ("density",)), O.PAIRS, O.thresholds("day", False)))
def salient_thresholds_whole_range(spark: SparkSession, sf: str) -> DataFrame:
    """Thresholds of daily functions without seasons."""
    ix = index(spark, sf, ("orders",), "day", ("density",), False)
    return ix.salient.select("function_id", "season", "side", r6("theta"))


_HALVES = O.functions(("orders",), "region", "month").replace("fn AS (", "fn0 AS (") + """, z AS (SELECT min(t) AS lo FROM fn0),
fn AS (SELECT h || '.' || split_part(function_id, '.', 2) AS function_id, region, CAST(t - lo - s AS INTEGER) AS t, value FROM fn0, z, (VALUES ('first', 0), ('second', 36)) v(h, s) WHERE t BETWEEN lo + s AND lo + s + 35)"""


@register(O.query(_TEST, *S.related(_HALVES, "month", S.REGIONS, S.grown_maps(S.lattice_links(1, 5), 40) + S.MAP_TEST)))
def relation_two_ranges_month_region(spark: SparkSession, sf: str) -> DataFrame:
    """A table against itself: three years and the three after them, by region."""
    fn = dense(spark, sf, ("orders",), "region", "month")
    lo = fn.agg(F.min("t")).first()[0]
    near = {"region": _regions(spark, sf)}
    return _tested(RelationshipQuery(index_functions(W.align_ranges(fn, "first", lo, "second", lo + 36, 36), near), n_maps=40).run(False))


_SAMPLE = u("'sample:' || o_orderkey") + " < 0.25"


@register(f"SELECT CAST({O.step('o_orderdate', 'month')} AS BIGINT) AS t, count(*) AS n FROM orders WHERE {_SAMPLE} GROUP BY 1")
def density_of_sample(spark: SparkSession, sf: str) -> DataFrame:
    """A quarter of the rows, chosen by key, for a preview of a function."""
    rows = W.sampled(table(spark, sf, "orders"), "o_orderkey", 0.25)
    spec = catalog.DatasetSpec("sample", rows, "o_orderdate", "day")
    return scalar.wide(spec, "world", "month").select(F.col("t").cast("long").alias("t"), F.col("density").cast("long").alias("n"))


@register("SELECT kind, count(*) AS n, count(DISTINCT o_custkey) AS customers, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) AS cents, max(CAST(o_orderdate AS DATE)) AS last FROM orders, (SELECT unnest(['csv', 'json', 'orc', 'parquet']) AS kind) GROUP BY kind")
def tables_in_every_format(spark: SparkSession, sf: str) -> DataFrame:
    """One table written and read again in every format of the library."""
    from strel.runtime import shared_dir
    from strel.sources import files

    rows = table(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_totalprice", "o_orderdate", "o_orderstatus")
    out = None
    for kind in files.FORMATS:
        path = f"{shared_dir(spark)}/strel/orders-{kind}"
        files.write(rows, path, kind, ("o_orderstatus",))
        d = files.read(spark, path, kind, rows.schema if kind in ("csv", "json") else None)
        one = d.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("o_custkey").alias("customers"), F.sum(F.round(F.col("o_totalprice") * 100).cast("long")).alias("cents"), F.max(F.to_date("o_orderdate")).alias("last"))
        one = one.select(F.lit(kind).alias("kind"), "*")
        out = one if out is None else out.unionByName(one)
    return out


# --- permutations that are given --------------------------------------------------------------


def _moved(spark: SparkSession, sf: str, block: int) -> DataFrame:
    ix = _week(spark, sf)
    pairs = relate.candidate_pairs(ix.meta)
    maps = materialize(permute.step_maps(pairs, 50, block), "moves")
    return relate.step_map_test(pairs, ix.points, maps).select("left_fn", "right_fn", "feature_type", "n_perm", r6("p_value"))


_MOVED = "SELECT left_fn, right_fn, feature_type, CAST(n_perm AS BIGINT) AS n_perm, round(p_value, 6) AS p_value FROM test"


@register(O.query(_MOVED, *_REL, S.step_test(50, 1)))
def free_permutation_pvalues(spark: SparkSession, sf: str) -> DataFrame:
    """Unrestricted Monte Carlo: steps dealt anew one by one."""
    return _moved(spark, sf, 1)


@register(O.query(_MOVED, *_REL, S.step_test(50, 13)))
def block_permutation_pvalues(spark: SparkSession, sf: str) -> DataFrame:
    """Blocks of a quarter of a year dealt anew."""
    return _moved(spark, sf, 13)


def _tests_of(name: str) -> str:
    return f"SELECT left_fn, right_fn, feature_type, p_value <= 0.05 AS {name} FROM test"


@register(f"SELECT restricted, free, count(*) AS n FROM ({O.query(_tests_of('restricted'), *_REL, O.ROTATION)}) a JOIN ({O.query(_tests_of('free'), *_REL, S.step_test(50, 1))}) b USING (left_fn, right_fn, feature_type) GROUP BY ALL")
def verdicts_restricted_and_free(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs that tests with and without dependence in time accept."""
    ix = _week(spark, sf)
    pairs = relate.candidate_pairs(ix.meta)
    key = ["left_fn", "right_fn", "feature_type"]
    a = relate.rotation_test_words(pairs, ix.bits).select(*key, (F.col("p_value") <= 0.05).alias("restricted"))
    b = _moved(spark, sf, 1).select(*key, (F.col("p_value") <= 0.05).alias("free"))
    return a.join(b, key).groupBy("restricted", "free").agg(F.count(F.lit(1)).alias("n"))


@register(O.query(_MOVED, *_REL, O.ROTATION))
def rotation_pvalues_by_points(spark: SparkSession, sf: str) -> DataFrame:
    """The rotation test from joins of points: the same p-values as from words."""
    ix = _week(spark, sf)
    return relate.rotation_test(relate.candidate_pairs(ix.meta), ix.points).select("left_fn", "right_fn", "feature_type", "n_perm", r6("p_value"))


# --- methods compared with --------------------------------------------------------------------

_AL_T = (*_ALIGNED[:-1], _ALIGNED[-1].replace("a.value AS x", "a.t, a.value AS x"))


@register(O.query("SELECT left_fn, right_fn, round(dtw, 6) AS dtw FROM dtw", *_AL_T, S.WARP))
def dtw_week_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return baselines.time_warping(*_base(spark, sf)).select("left_fn", "right_fn", r6("dtw"))


_NMI = """, mi0 AS (SELECT left_fn, right_fn, n, least(floor((x - x0) / (x1 - x0) * k), k - 1) AS bx, least(floor((y - y0) / (y1 - y0) * k), k - 1) AS by_, CAST(count(*) AS DOUBLE) AS c FROM
  (SELECT *, count(*) OVER w AS n, least(greatest(ceil(sqrt(count(*) OVER w / 5)), 2), 64) AS k, min(x) OVER w AS x0, max(x) OVER w AS x1, min(y) OVER w AS y0, max(y) OVER w AS y1 FROM al WINDOW w AS (PARTITION BY left_fn, right_fn)) GROUP BY ALL),
mi1 AS (SELECT *, sum(c) OVER (PARTITION BY left_fn, right_fn, bx) AS cx, sum(c) OVER (PARTITION BY left_fn, right_fn, by_) AS cy FROM mi0),
nmi AS (SELECT left_fn, right_fn, sum(c / n * ln(c * n / (cx * cy))) / sqrt(sum(-c / n * ln(cx / n)) * sum(-c / n * ln(cy / n))) AS nmi FROM mi1 GROUP BY left_fn, right_fn)"""
_COMPARE = "SELECT p.left_fn, p.right_fn, coalesce(ours, false) AS ours, round(pcc, 6) AS pcc, round(nmi, 6) AS nmi, round(dtw, 6) AS dtw FROM (SELECT left_fn, right_fn, corr(x, y) AS pcc FROM al GROUP BY ALL) p JOIN nmi USING (left_fn, right_fn) JOIN dtw USING (left_fn, right_fn) LEFT JOIN (SELECT left_fn, right_fn, bool_or(p_value <= 0.05) AS ours FROM test GROUP BY ALL) q USING (left_fn, right_fn)"


def _compared(ix: Index) -> DataFrame:
    """What each method says about every pair."""
    pairs, fn = materialize(relate.candidate_pairs(ix.meta), "pairs"), ix.functions
    key = ["left_fn", "right_fn"]
    found = RelationshipQuery(ix).run().select(*key).distinct().withColumn("ours", F.lit(True))
    out = baselines.pearson(pairs, fn).select(*key, r6("pcc")).join(baselines.mutual_information(pairs, fn).select(*key, r6("nmi")), key)
    out = out.join(baselines.time_warping(pairs, fn).select(*key, r6("dtw")), key).join(found, key, "left")
    return out.withColumn("ours", F.coalesce("ours", F.lit(False)))


_ALIGN = _ALIGNED[-1].replace("a.value AS x", "a.t, a.value AS x")


@register(O.query(_COMPARE, *_all("week", O.functions(WEEK_SETS, "world", "week")), _ALIGN, _NMI, S.WARP))
def methods_on_week_pairs(spark: SparkSession, sf: str) -> DataFrame:
    return _compared(_week(spark, sf))


# --- planted case studies ---------------------------------------------------------------------

_DAY_L, _DAY_O = O.step("l_shipdate", "day"), O.step("o_orderdate", "day")
_RAIN = u("'rain:' || t") + " < 0.1"
_DROP = u("'drop:' || l_orderkey || ':' || l_linenumber") + " < 0.6"
_rain_fn = _fill(f"""SELECT 'taxi.' || m AS function_id, '0' AS region, t, v AS value FROM (SELECT t, unnest(['density', 'unique', 'avg']) AS m, unnest([CAST(count(*) AS DOUBLE), CAST(count(DISTINCT l_suppkey) AS DOUBLE), sum(CAST(round(l_extendedprice * 100) AS BIGINT)) / count(*) / 100 * CAST(CASE WHEN {_RAIN} THEN 1.6 ELSE 1.0 END AS DOUBLE)]) AS v
   FROM (SELECT {_DAY_L} AS t, * FROM lineitem) WHERE NOT ({_RAIN} AND {_DROP}) GROUP BY t)
 UNION ALL SELECT 'weather.rain', '0', t, sum(CAST(round(o_totalprice * 100) AS BIGINT)) / count(*) / 100 / 10000 + CASE WHEN {_RAIN} THEN 40 ELSE 0 END FROM (SELECT {_DAY_O} AS t, o_totalprice FROM orders) GROUP BY t""")


@register(O.query(_TEST, *_all("day", _rain_fn)))
def planted_rain_day(spark: SparkSession, sf: str) -> DataFrame:
    """Fewer and dearer trips on rain days: rain is related to their number and to their price."""
    return _tested(RelationshipQuery(index_functions(W.rain(spark, sf))).run(False))


@register(O.query(_COMPARE, *_all("day", _rain_fn), _ALIGN, _NMI, S.WARP))
def methods_on_planted_rain(spark: SparkSession, sf: str) -> DataFrame:
    return _compared(index_functions(W.rain(spark, sf)))


_WK_O, _WK_L = O.step("o_orderdate", "week"), O.step("l_shipdate", "week")
_SNOW = u("'snow:' || ((t - 4) // 7)") + " < 0.12"
_SNOW_DAY = f"(t - 4) % 7 = CAST(floor({u(chr(39) + 'snowday:' + chr(39) + ' || ((t - 4) // 7)')} * 7) AS INTEGER)"
_snow_days = f"""SELECT 'bikes.density' AS function_id, '0' AS region, t, CAST(count(*) AS DOUBLE) AS value FROM (SELECT {_DAY_O} AS t, o_orderkey FROM orders) WHERE NOT ({_SNOW} AND NOT {_SNOW_DAY} AND {u("'stay:' || o_orderkey")} < 0.5) GROUP BY t
 UNION ALL SELECT 'weather.snow', '0', t, CAST(count(*) AS DOUBLE) + CASE WHEN {_SNOW} AND {_SNOW_DAY} THEN 200 ELSE 0 END FROM (SELECT {_DAY_L} AS t FROM lineitem) GROUP BY t"""
_snow_weeks = f"SELECT function_id, region, CAST(floor((t - 4) / 7.0) AS INTEGER) AS t, sum(value) AS value FROM ({_snow_days}) GROUP BY ALL"


@register(S.both(_at("world", "day", _TEST, *_all("day", _fill(_snow_days))), _at("world", "week", _TEST, *_all("week", _fill(_snow_weeks)))))
def planted_snow_day_and_week(spark: SparkSession, sf: str) -> DataFrame:
    """Snow of one day keeps riders away on the other days of the week: seen by week, not by day."""
    return _resolved(RelationshipQuery(index_functions(W.snow(spark, sf))).run(False))


_BURST, _FLOOD = "region = CAST(CAST(floor(" + u("'burst:' || t") + " * 5) AS INTEGER) AS VARCHAR)", u("'flood:' || t") + " < 0.06"
_signs = f"""SELECT 'fares.density' AS function_id, region, t, CAST(n * CASE WHEN {_BURST} THEN 4 ELSE 1 END * CASE WHEN {_FLOOD} THEN 2 ELSE 1 END AS DOUBLE) AS value FROM (SELECT CAST(c_nationkey % 5 AS VARCHAR) AS region, {O.step("o_orderdate", "month")} AS t, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_nationkey IS NOT NULL GROUP BY ALL)
 UNION ALL SELECT 'speed.density', region, t, CAST(n * CASE WHEN {_BURST} THEN 4 ELSE 1 END * CASE WHEN {_FLOOD} THEN 1 ELSE 2 END AS DOUBLE) FROM (SELECT CAST(s_nationkey % 5 AS VARCHAR) AS region, {O.step("l_shipdate", "month")} AS t, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey IS NOT NULL GROUP BY ALL)"""


@register(S.both(
    _at("region", "month", _TEST, *S.related(_fill(_signs), "month", S.REGIONS, S.grown_maps(S.lattice_links(1, 5), 40) + S.MAP_TEST)),
    _at("world", "month", _TEST, *_all("month", _fill(f"SELECT function_id, '0' AS region, t, sum(value) AS value FROM ({_signs}) GROUP BY function_id, t"))),
))
def planted_sign_by_resolution(spark: SparkSession, sf: str) -> DataFrame:
    """A relation that is positive by region and negative over the world."""
    ix = index_functions(W.signs(spark, sf), {"region": _regions(spark, sf)})
    return _resolved(RelationshipQuery(ix, n_maps=40).run(False))


_DAYS = O.functions(WEEK_SETS, "world", "day", ("density", "avg(o_totalprice)", "avg(l_quantity)"))


@register(O.query("SELECT count(*) AS candidates, count(*) FILTER (p_value <= 0.05) AS accepted, count(*) FILTER (abs(r.score) >= 0.5) AS strong, count(*) FILTER (abs(r.score) >= 0.5 AND p_value > 0.05) AS strong_rejected FROM rel r JOIN test USING (left_fn, right_fn, feature_type) WHERE n_common > 0", *_all("day", _DAYS)))
def spurious_pairs_day(spark: SparkSession, sf: str) -> DataFrame:
    """Unrelated tables: pairs whose score is high by chance, and how many of them the test rejects."""
    ix = index(spark, sf, WEEK_SETS, "day", ("density", "avg(o_totalprice)", "avg(l_quantity)"))
    r = RelationshipQuery(ix).run(False).where("p_value IS NOT NULL")
    n = lambda c: F.coalesce(F.sum(c.cast("int")), F.lit(0)).cast("long")
    strong, ok = F.abs("score") >= 0.5, F.col("p_value") <= 0.05
    return r.agg(F.count(F.lit(1)).alias("candidates"), n(ok).alias("accepted"), n(strong).alias("strong"), n(strong & ~ok).alias("strong_rejected"))


def _noise_sql() -> str:
    fn = O.functions(("orders",), "world", "week", ("density",)).replace("fn AS (", "fn0 AS (")
    z = " + ".join(u(f"'z:' || t || ':{k}'") for k in range(12))
    return fn + f""", iq AS (SELECT function_id, quantile_cont(value, 0.75) - quantile_cont(value, 0.25) AS iqr FROM fn0 GROUP BY function_id),
nz AS (SELECT f.*, {z} - 6.0 AS z, iqr, unnest([0.0, 0.01, 0.02, 0.05, 0.10]) AS lv FROM fn0 f JOIN iq USING (function_id)),
fn AS (SELECT function_id, region, t, value FROM fn0 UNION ALL SELECT 'noise' || CAST(round(lv * 100) AS INTEGER) || '.density', region, t, value + greatest(-lv * iqr, least(lv * iqr, z * lv * iqr / 2)) FROM nz)"""


_NOISE = "SELECT r.left_fn, r.right_fn, r.feature_type, r.n1, r.n2, r.n_common, round(r.score, 6) AS score, round(r.strength, 6) AS strength FROM rel r WHERE n_common > 0 AND (left_dataset = 'orders' OR right_dataset = 'orders')"


@register(O.query(_NOISE, _noise_sql(), O.PAIRS, O.thresholds("week"), O.points("week"), O.RELATION))
def robustness_noise_levels(spark: SparkSession, sf: str) -> DataFrame:
    """Score and strength of a function and copies of it under growing noise."""
    fn = W.noisy(dense(spark, sf, ("orders",), "world", "week", ("density",)))
    q = RelationshipQuery(index_functions(fn), ("orders",)).evaluate().where("n_common > 0")
    return q.select("left_fn", "right_fn", "feature_type", "n1", "n2", "n_common", r6("score"), r6("strength"))


# --- whole corpora ----------------------------------------------------------------------------


@register(f"""SELECT 'lineitem_' || (l_suppkey % 34) || '_' || l_returnflag AS dataset, count(*) AS n_rows, count(DISTINCT {_WK_L}) AS n_steps FROM lineitem GROUP BY 1
 UNION ALL SELECT 'orders_' || c_mktsegment || '_' || substr(o_orderpriority, 1, 1) || '_' || o_orderstatus, count(*), count(DISTINCT {_WK_O}) FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1
 UNION ALL SELECT 'events_' || event_type || '_' || (user_id % 25), count(*), count(DISTINCT {O.step('ts', 'week')}) FROM events GROUP BY 1""")
def corpus_of_300_tables(spark: SparkSession, sf: str) -> DataFrame:
    """Rows and steps of the 302 data sets of the large corpus, from three scans."""
    out = None
    for s in catalog.many(spark, sf):
        seen, _ = scalar.observe(s, [("world", "week")])
        one = seen.where("kind = ''").groupBy("dataset").agg(F.sum("n").alias("n_rows"), F.count_distinct("t").alias("n_steps"))
        out = one if out is None else out.unionByName(one)
    return out.where("dataset IS NOT NULL")


def _many(spark: SparkSession, sf: str) -> Index:
    key = (spark.sparkContext.applicationId, sf, "many")
    if key not in _INDEX:
        _INDEX[key] = index_corpus(catalog.many(spark, sf), spaces=("world",), times=("week",))
    return _INDEX[key]


@register()
def relations_of_300_tables(spark: SparkSession, sf: str) -> DataFrame:
    """All relationships of the large corpus at (week, world): candidates, tested, significant."""
    r = RelationshipQuery(_many(spark, sf)).run(False)
    n = lambda c: F.coalesce(F.sum(c.cast("int")), F.lit(0)).cast("long")
    return r.groupBy("feature_type").agg(F.count(F.lit(1)).alias("related"), n(F.col("p_value").isNotNull()).alias("tested"), n(F.col("significant")).alias("significant"))


@register()
def relations_of_300_tables_clause(spark: SparkSession, sf: str) -> DataFrame:
    """The same with a clause, which spares the test for pairs that do not meet it."""
    r = RelationshipQuery(_many(spark, sf), clause=Clause(min_abs_score=0.6, min_strength=0.3)).run(False)
    return r.groupBy("feature_type").agg(F.count(F.lit(1)).alias("tested"), F.coalesce(F.sum(F.col("significant").cast("int")), F.lit(0)).cast("long").alias("significant"))


_GROW = ("orders", "lineitem", "orders_F", "orders_O", "orders_P", "lineitem_A", "lineitem_N", "lineitem_R")


@register(" UNION ALL ".join(f"SELECT {k} AS n_datasets, count(DISTINCT left_fn || right_fn) AS n_pairs FROM ({O.query('SELECT left_fn, right_fn FROM cand', O.functions(_GROW[:k], 'world', 'month', ('density', 'avg(o_totalprice)', 'avg(l_quantity)')), ', ' + O.RELATION[O.RELATION.index('mt AS'): O.RELATION.index(chr(10) + 'ft AS') - 1])})" for k in range(2, 9)))
def growing_collection_pairs(spark: SparkSession, sf: str) -> DataFrame:
    """Pairs to evaluate as data sets are added one after the other."""
    specs = [s for s in catalog.whole_and_parts(spark, sf) if s.name != "events"]
    fn = scalar.all_functions(specs, ("world",), ("month",)).where("function_id RLIKE '\\\\.(density|avg.o_totalprice.|avg.l_quantity.)$'")
    pairs = materialize(relate.candidate_pairs(relate.spans(fn)), "pairs")
    at = lambda side: F.array_position(F.array(*[F.lit(n) for n in _GROW]), F.col(f"{side}_dataset"))
    need = pairs.select(F.greatest(at("left"), at("right")).alias("need"))
    steps = F.explode(F.sequence(F.lit(2), F.lit(len(_GROW))))
    return need.select("need", steps.alias("n_datasets")).where("need <= n_datasets").groupBy(F.col("n_datasets").cast("int").alias("n_datasets")).agg(F.count(F.lit(1)).alias("n_pairs"))


@register()
def space_by_stage(spark: SparkSession, sf: str) -> DataFrame:
    """Bytes on disk: raw tables, functions at all resolutions, extrema, features."""
    ix = _every(spark, sf)
    rows = [("raw", sum(scalar.stored_bytes(table(spark, sf, t)) for t in ("orders", "lineitem", "customer", "supplier")))]
    rows += [(n, scalar.stored_bytes(getattr(ix, n))) for n in ("functions", "pairs", "points", "bits")]
    return spark.createDataFrame(rows, "stage string, bytes long")


@register("""SELECT 'cell' AS kind, CAST(CAST(least(greatest(floor((embedding[2] + 0.5) * 8), 0), 7) * 8 + least(greatest(floor((embedding[1] + 0.5) * 8), 0), 7) AS INTEGER) AS VARCHAR) AS region, count(*) AS density FROM events JOIN embeddings ON vec_id = user_id % (SELECT count(*) FROM embeddings) WHERE dayofmonth(ts) = 7 GROUP BY ALL
 UNION ALL SELECT 'nation', CAST(c_nationkey AS VARCHAR), count(*) FROM events JOIN customer ON user_id = c_custkey WHERE dayofmonth(ts) = 7 GROUP BY ALL""")
def density_by_cell_and_nation(spark: SparkSession, sf: str) -> DataFrame:
    """One day's density on a grid of points and by nation."""
    e = table(spark, sf, "embeddings")
    n = e.count()
    one = table(spark, sf, "events").where("dayofmonth(ts) = 7")
    at = e.select("vec_id", space.cell_of(F.col("embedding")[0], F.col("embedding")[1], -0.5, 0.5, 8).cast("string").alias("region"))
    cells = one.join(at, F.expr(f"user_id % {n}") == F.col("vec_id")).groupBy("region").agg(F.count(F.lit(1)).alias("density"))
    c = table(spark, sf, "customer").select("c_custkey", F.col("c_nationkey").cast("string").alias("region"))
    nations = one.join(c, F.col("user_id") == F.col("c_custkey")).groupBy("region").agg(F.count(F.lit(1)).alias("density"))
    return cells.select(F.lit("cell").alias("kind"), "region", "density").unionByName(nations.select(F.lit("nation").alias("kind"), "region", "density"))
