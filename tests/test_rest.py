"""Permutations, baselines, steps and the contract of the entry module."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from strel.functions.steps import coarser, common_time, to_step
from strel.operators import baselines, permute, space
from strel.sources import catalog

SF = "/root/testdata/sf0.001"


def test_lattice_maps_are_bijections_that_keep_the_torus(spark):
    m = permute.lattice_maps(spark, 5, 5)
    assert m.count() == 24 * 25
    assert m.groupBy("k").agg(F.count_distinct("image").alias("n")).where("n <> 25").count() == 0


def test_grown_maps_are_bijections(spark):
    a = space.lattice(spark, 4, 3)
    m = permute.graph_maps(a, 40)
    assert m.groupBy("k").agg(F.count_distinct("image").alias("n")).where("n <> 12").count() == 0
    f = [r["fidelity"] for r in permute.fidelity(m, a).collect()]
    assert len(f) == 40 and all(0 <= x <= 1 for x in f) and np.mean(f) > 0.5


def test_time_warping():
    x = np.array([0.0, 1, 3, 1, 0])
    assert baselines.dtw_distance(x, x) == 0
    assert baselines.dtw_distance(x, np.zeros(5)) == np.abs(x).sum()
    assert baselines.dtw_distance(np.array([0.0, 0, 1, 2]), np.array([0.0, 1, 2, 2])) == 0


def test_steps(spark):
    d = spark.sql("SELECT timestamp_ntz'1970-01-05 13:00:00' AS a, timestamp_ntz'1970-01-04 00:00:00' AS b")
    r = d.select(*[to_step(F.col(c), s).alias(f"{c}_{s}") for c in "ab" for s in ("hour", "day", "week", "month", "quarter")]).first()
    assert (r["a_hour"], r["a_day"], r["a_week"], r["b_week"], r["a_month"], r["a_quarter"]) == (109, 4, 0, -1, 0, 0)
    assert spark.range(1).select(coarser(F.lit(109), "hour", "week")).first()[0] == 0
    assert common_time("second", "day") == ["day", "week", "month", "quarter"]


def test_tables_without_time_are_refused(spark):
    with pytest.raises(catalog.NoTimeAxis):
        catalog.infer_roles(spark.read.parquet(f"{SF}/benchmark.parquet"))
    assert catalog.infer_roles(spark.read.parquet(f"{SF}/orders.parquet"))["time"] == ["o_orderdate"]


def test_clause_does_not_shuffle_pairs_without_a_key(spark):
    from strel.queries import index
    from strel.plans.query import RelationshipQuery

    q = RelationshipQuery(index(spark, SF, ("orders", "lineitem"), "week", ("density",)))
    plan = q.evaluate()._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan and "Python" not in plan


def test_moves_of_steps_are_bijections_that_keep_blocks(spark):
    from strel.operators.permute import step_maps

    m = step_maps(spark.createDataFrame([(3, 25)], "lo int, hi int"), 6, 5).toPandas()
    for _, g in m.groupby("k"):
        assert sorted(g.t) == sorted(g.image) == list(range(3, 26))
        g = g.sort_values("t")
        inside = (g.t.to_numpy()[1:] - 3) % 5 != 0
        assert (np.diff(g.image.to_numpy())[inside] == 1).all()


def test_tests_that_stop_early(spark):
    from strel.operators.relate import candidate_pairs  # noqa: F401

    rng = np.random.default_rng(0)
    rows = [(f, "world", "week", "salient", "0", int(t), bool(s), not s) for f in ("a.f", "b.g") for t, s in zip(rng.choice(200, 80, replace=False), rng.random(80) < 0.5, strict=True)]
    pts = spark.createDataFrame(rows, "function_id string, space_res string, time_res string, feature_type string, region string, t int, pos boolean, neg boolean")
    pair = spark.createDataFrame([("a.f", "b.g", "world", "week", 0, 199, 1)], "left_fn string, right_fn string, space_res string, time_res string, lo int, hi int, n_regions int")
    whole, early = (permute.free_permutation_test(pair, pts, 600, stop_hits=h).first() for h in (None, 10))
    assert early["n_perm"] < whole["n_perm"] == 600 and abs(early["p_value"] - whole["p_value"]) < 0.25


def test_adjusted_p_values(spark):
    p = [0.01, 0.02, 0.02, 0.5, 0.9]
    got = {(r["i"]): r["p_adjusted"] for r in permute.adjust_bh(spark.createDataFrame(list(enumerate(p)), "i int, p_value double")).collect()}
    want = [min(1, min(p[j] * 5 / sum(x <= p[j] for x in p) for j in range(5) if p[j] >= p[i])) for i in range(5)]
    assert [got[i] for i in range(5)] == pytest.approx(want)


def test_approximate_unique_counts_roll_up(spark):
    from strel.operators import scalar

    o = catalog.orders(spark, SF)
    up = scalar.finish(scalar.roll_up(scalar.states(o, "nation", "day"), o, "day", "month", spark.read.parquet(f"{SF}/nation.parquet").select(F.col("n_nationkey").cast("string").alias("region"), F.col("n_regionkey").cast("string").alias("to_region"))), o)
    exact = scalar.wide(o, "region", "month")
    both = up.join(exact.withColumnsRenamed({"density": "n", "unique(o_custkey)": "u", "avg(o_totalprice)": "a"}), ["region", "t"])
    r = both.select("density", "n", F.abs(F.col("`unique~(o_custkey)`") - F.col("u")).alias("off"), F.abs(F.col("`avg(o_totalprice)`") - F.col("a")).alias("d"), "u").collect()
    assert len(r) == exact.count() and all(x["density"] == x["n"] and x["off"] <= 1 + 0.05 * x["u"] and x["d"] < 1e-6 for x in r)
    approx = scalar.wide(o, "world", "month", approx=0.02).orderBy("t").toPandas()["unique(o_custkey)"]
    assert (abs(approx - scalar.wide(o, "world", "month").orderBy("t").toPandas()["unique(o_custkey)"]) <= 3).all()


def test_every_resolution_from_one_scan_equals_each_alone(spark):
    from strel.operators import scalar

    e = catalog.events(spark, SF)
    found = [("nation", "day"), ("world", "hour"), ("segment", "day")]
    at_once = scalar.from_observed(*scalar.observe(e, found), e, found)
    for s, t in found:
        alone = scalar.long(scalar.wide(e, s, t), "events", s, t)
        cols = ["function_id", "region", "t", "value"]
        a, b = (sorted((r[0], r[1], r[2], round(r[3], 6)) for r in d.select(*cols).collect() if r[3] is not None) for d in (at_once.where((F.col("space_res") == s) & (F.col("time_res") == t)), alone))
        assert a == b
    plan = scalar.observe(e, found)[0]
    assert plan.select("dataset").distinct().count() == 1


def test_missing_values(spark):
    from strel.operators import scalar

    rows = [("a.avg(x)", "world", "week", "0", t, v) for t, v in ((0, 2.0), (3, 8.0), (4, 4.0))]
    fn = spark.createDataFrame(rows, "function_id string, space_res string, time_res string, region string, t int, value double")
    got = {how: [r["value"] for r in scalar.densify(fn, how).orderBy("t").collect()] for how in ("drop", "zero", "carry", "mean", "linear")}
    assert got["drop"] == [2, 8, 4] and got["zero"] == [2, 0, 0, 8, 4] and got["carry"] == [2, 2, 2, 8, 4]
    assert got["linear"] == pytest.approx([2, 4, 6, 8, 4]) and got["mean"] == pytest.approx([2, 14 / 3, 14 / 3, 8, 4])


def test_mean_gradient(spark):
    from strel.operators import scalar

    fn = spark.createDataFrame([("a.f", "world", "week", "0", t, float(v)) for t, v in enumerate((1, 4, 2))], "function_id string, space_res string, time_res string, region string, t int, value double")
    assert [r["value"] for r in scalar.gradient(fn, None, "mean").orderBy("t").collect()] == [3, 2.5, 2]


def test_polygons_that_share_a_side(spark):
    square = lambda r, x, y: [(r, i, x + a, y + b) for i, (a, b) in enumerate(((0.0, 0.0), (1.0, 0.0), (1.0, 1.0), (0.0, 1.0)))]
    corners = spark.createDataFrame([*square("a", 0.0, 0.0), *square("b", 1.0, 0.0), *square("c", 1.0, 1.0), *square("d", 5.0, 5.0)], "region string, i int, x double, y double")
    assert {tuple(r) for r in space.from_polygons(corners).collect()} == {("a", "b"), ("b", "a"), ("b", "c"), ("c", "b")}


def test_area_under_a_perfect_curve(spark):
    from strel.operators import features

    fn = spark.createDataFrame([("a.f", "world", "week", "0", t, float(t)) for t in range(10)], "function_id string, space_res string, time_res string, region string, t int, value double")
    truth = fn.where("t >= 7")
    assert features.auc(features.roc(fn, truth)).first()["auc"] == 1.0


def test_share_of_unrelated_pairs_that_pass(spark):
    from strel.plans import workloads

    tested = spark.createDataFrame([(x / 100,) for x in range(100)], "p_value double")
    r = workloads.calibration(tested).first()
    assert r["tested"] == 100 and r["share"] == pytest.approx(0.06)


def test_entry(spark):
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
    assert e.entry(spark).count() > 0


def test_files_of_every_format(spark, tmp_path):
    from strel.sources import files

    rows = spark.createDataFrame([(1, "a", 2.5), (2, None, None), (3, "b", -1.0)], "i long, s string, x double")
    for kind in files.FORMATS:
        files.write(rows, str(tmp_path / kind), kind)
        assert sorted(map(tuple, files.read(spark, str(tmp_path / kind), kind, rows.schema).collect()), key=str) == sorted(map(tuple, rows.collect()), key=str)
    files.write(rows, str(tmp_path / "parts"), by=("i",))
    assert files.read(spark, str(tmp_path / "parts")).where("i = 3").first()["s"] == "b"
    with pytest.raises(ValueError, match="schema"):
        files.read(spark, str(tmp_path / "csv"), "csv")
    with pytest.raises(ValueError, match="none of"):
        files.read(spark, str(tmp_path / "csv"), "xls")
