"""Cases of the second review: each would have failed before."""

from strel import queries_more, queries_space  # noqa: F401  register their queries
from strel.operators import relate

BITS = "function_id string, space_res string, time_res string, feature_type string, region string, word int, pos long, neg long"
PAIRS = "left_fn string, right_fn string, space_res string, time_res string, lo int, hi int, n_regions long"


def test_pairs_without_features_in_their_common_range_are_no_candidates(spark):
    at = ("world", "week")
    pairs = spark.createDataFrame([("a.x", "b.y", *at, 64, 100, 1)], PAIRS)
    bits = [
        ("a.x", *at, "salient", "0", 1, 2, 0), ("b.y", *at, "salient", "0", 0, 1, 0),  # step 65 is in range, step 0 is not
        ("a.x", *at, "extreme", "0", 0, 2, 0), ("b.y", *at, "extreme", "0", 1, 0, 1 << 60),  # steps 1 and 124
    ]
    found = relate.pair_counts(pairs, spark.createDataFrame(bits, BITS))
    assert [tuple(r) for r in found.select("feature_type", "n1", "n2", "n_common").collect()] == [("salient", 1, 0, 0)]


def test_stages_of_the_pipeline_begin_with_heaps_given_back(spark, monkeypatch):
    import corpus_pipeline

    asked = []
    monkeypatch.setattr(corpus_pipeline, "give_back", asked.append)
    docs = spark.createDataFrame([], "doc_id long, text string, lang string, source string, n_chars long")
    assert dict(corpus_pipeline.STAGES)["packing"](spark, docs, "").count() == 0
    assert asked == [spark]


def test_give_back_collects_in_tasks_and_on_the_driver(spark):
    from strel.runtime import give_back

    beans = spark._jvm.java.lang.management.ManagementFactory.getGarbageCollectorMXBeans
    runs = lambda: sum(b.getCollectionCount() for b in beans())
    before = runs()
    give_back(spark)
    assert runs() - before > 1


def _both(spark, sf, name, *tables):
    """Sorted rows of a query and of its SQL."""
    import duckdb

    from strel.queries import ORACLES, REGISTRY

    con = duckdb.connect()
    con.execute("SET TimeZone = 'UTC'")
    for t in tables:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return sorted(tuple(r) for r in REGISTRY[name](spark, str(sf)).collect()), sorted(con.execute(ORACLES[name]).fetchall())


def _some_nations(folder):
    """Nations with a gap and a row more."""
    import duckdb

    given = "SELECT * FROM '/root/testdata/sf0.001/nation.parquet'"
    duckdb.execute(f"COPY ({given} WHERE n_nationkey <> 12 UNION ALL {given.replace('*', '* REPLACE (27 AS n_nationkey)')} WHERE n_nationkey = 2) TO '{folder}/nation.parquet' (FORMAT parquet)")
    return folder


def test_the_lattice_is_that_of_the_given_nations(spark, tmp_path):
    got, want = _both(spark, _some_nations(tmp_path), "adjacency_nation_lattice", "nation")
    assert got == want and len(want) == 74
    got, want = _both(spark, "/root/testdata/sf0.001", "adjacency_nation_lattice", "nation")
    assert got == want and len(want) == 80


def test_maps_are_those_of_the_given_nations(spark, tmp_path):
    from strel.queries import REGISTRY

    found = REGISTRY["graph_shift_maps"](spark, str(_some_nations(tmp_path)))
    names = {str(k) for k in range(25) if k != 12} | {"27"}
    for side in ("region", "image"):
        assert {r[0] for r in found.select(side).distinct().collect()} == names
    assert found.count() == 200 * 25
    got, want = _both(spark, "/root/testdata/sf0.001", "graph_shift_maps")
    assert got == want and len(want) == 200 * 25


def test_fidelity_is_that_of_the_given_nations(spark, tmp_path):
    from strel.operators import permute, space
    from strel.queries import REGISTRY, nations

    sf = str(_some_nations(tmp_path))
    a = space.lattice_of(nations(spark, sf), 5)
    want = {(r["k"], round(r["fidelity"], 6)) for r in permute.fidelity(permute.graph_maps(a, 200), a).collect()}
    assert {tuple(r) for r in REGISTRY["map_fidelity"](spark, sf).collect()} == want
    got, want = _both(spark, "/root/testdata/sf0.001", "map_fidelity", "nation")
    assert got == want and len(want) == 200


def test_cells_in_three_dimensions_are_those_that_hold_embeddings(spark, tmp_path):
    import math

    rows = [(1, [-0.2, -0.2, -0.2, 9.0]), (2, [-0.2, -0.2, -0.1]), (3, [-0.2, 0.2, -0.2]), (4, [9.0, 9.0, 9.0]), (5, [0.2, 0.2, 0.1]), (6, None), (7, [0.0]), (8, [math.nan, 0.2, 0.2]), (9, [math.inf, 0.2, -0.2]), (10, [0.2, 0.2, None])]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>").coalesce(1).write.parquet(f"{tmp_path}/x")
    next((tmp_path / "x").glob("*.parquet")).rename(tmp_path / "embeddings.parquet")
    got, want = _both(spark, tmp_path, "grid3d_adjacency", "embeddings")
    assert got == want == [(0, 1), (1, 0), (62, 63), (63, 62)]
    got, want = _both(spark, "/root/testdata/sf0.001", "grid3d_adjacency", "embeddings")
    assert got == want and want


FRESH = ["anti_join_steps_without_features", "distinct_steps_of_features", "feature_bits_roundtrip", "feature_counts_all", "intersect_feature_points", "interval_join_feature_runs", "pivot_signs"]


def test_queries_read_the_tables_as_they_are(spark, tmp_path):
    """Once the tables under a path change, their answers do."""
    import shutil

    from strel.queries import _week

    given = "/root/testdata/sf0.001"
    for t in ("orders", "lineitem", "customer", "supplier", "events"):
        shutil.copy(f"{given}/{t}.parquet", tmp_path / f"{t}.parquet")
    _week(spark, str(tmp_path))
    import duckdb

    for t, when in (("orders", "o_orderdate"), ("lineitem", "l_shipdate")):
        duckdb.execute(f"COPY (SELECT * FROM '{given}/{t}.parquet' WHERE hash({when}) % 10 < 7 AND year({when}) < 1998) TO '{tmp_path}/{t}.parquet' (FORMAT parquet)")
    for name in FRESH:
        got, want = _both(spark, tmp_path, name, "orders", "lineitem", "customer", "supplier")
        assert got == want, name
