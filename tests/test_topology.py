"""Hand fixtures with known trees, thresholds and features, and random graphs against brute force."""

import numpy as np
import pytest

from strel.operators import features, relate, topology
from strel.operators.topology import Sweep

H1 = [1, 10, 4, 7, 5, 6, 3, 9, 0, 2]


def function(spark, values, name="a.f", start=0):
    rows = [(name, "world", "week", "0", start + t, float(v)) for t, v in enumerate(values)]
    return spark.createDataFrame(rows, "function_id string, space_res string, time_res string, region string, t int, value double")


def path_pairs(values, sign=1):
    v = np.array(values, float) * sign
    s = Sweep(v, np.arange(len(v)), np.array(["0"] * len(v)))
    return sorted((int(a), int(b), float(abs(v[a] - v[b])), e) for a, b, e in s.pairs)


def test_pairs_of_a_path():
    assert path_pairs(H1) == sorted([(1, 8, 10.0, True), (7, 6, 6.0, False), (3, 2, 3.0, False), (9, 8, 2.0, False), (5, 4, 1.0, False)])
    assert path_pairs(H1, -1) == sorted([(8, 1, 10.0, True), (0, 1, 9.0, False), (6, 7, 6.0, False), (2, 3, 3.0, False), (4, 5, 1.0, False)])


def test_plateaus_and_monotone_and_constant():
    assert sorted(p[2] for p in path_pairs([0, 3, 3, 3, 1, 5, 5, 2, 2, 4])) == [2, 2, 5]
    assert path_pairs([1, 2, 3, 4]) == [(3, 0, 3.0, True)]
    assert path_pairs([2, 2, 2]) == [(0, 2, 0.0, True)]


def test_star_merges_three_ways():
    links = np.array(list("000")), np.array(list("123"))
    s = Sweep(np.array([0.0, 3, 2, 1]), np.zeros(4, int), np.array(list("0123")), links)
    assert sorted(s.pairs) == [(1, 0, True), (2, 0, False), (3, 0, False)]


def test_components_of_random_grids_agree_with_births_and_deaths():
    rng = np.random.default_rng(3)
    near = np.array(list("012")), np.array(list("123"))
    for _ in range(20):
        v = rng.integers(0, 5, 24).astype(float)
        region, t = np.repeat(np.arange(4), 6), np.tile(np.arange(6), 4)
        s = Sweep(v, t, region.astype(str), near)
        for theta in range(6):
            inside = {(r, k) for r, k, x in zip(region.tolist(), t.tolist(), v, strict=True) if x >= theta}
            n, left = 0, set(inside)
            while left:
                n, stack = n + 1, [left.pop()]
                while stack:
                    r, k = stack.pop()
                    for q in ((r - 1, k), (r + 1, k), (r, k - 1), (r, k + 1)):
                        if q in left:
                            left.discard(q)
                            stack.append(q)
            assert n == sum(v[a] >= theta and (e or v[b] < theta) for a, b, e in s.pairs)


@pytest.fixture(scope="module")
def h1(spark):
    return function(spark, H1)


def test_declarative_pairs_equal_the_sweep(spark, h1):
    cols = ["side", "creator_t", "destroyer_t", "persistence", "essential"]
    both = [sorted(map(tuple, p.select(*cols).collect())) for p in (topology.persistence(h1), topology.persistence_1d(h1))]
    assert both[0] == both[1] and len(both[0]) == 10


def test_thresholds_and_features(spark, h1):
    pairs = topology.persistence(h1)
    salient = features.salient_thresholds(pairs)
    assert {r["side"]: r["theta"] for r in salient.collect()} == {"join": 9.0, "split": 3.0}
    extreme = features.extreme_thresholds(pairs, salient)
    assert {r["side"]: r["theta"] for r in extreme.collect()} == {"join": 10.5, "split": -1.75}
    points = features.features(h1, salient, extreme)
    assert {(r["t"], r["pos"]) for r in points.collect()} == {(1, True), (7, True), (0, False), (6, False), (8, False), (9, False)}
    assert points.where("feature_type = 'extreme'").count() == 0
    bits = features.to_bits(points)
    assert sorted(map(tuple, features.from_bits(bits).select("t", "pos", "neg").collect())) == sorted(map(tuple, points.select("t", "pos", "neg").collect()))


def test_constant_function_has_no_feature(spark):
    pairs = topology.persistence(function(spark, [4, 4, 4, 4]))
    assert features.salient_thresholds(pairs).count() == 0


def test_flood_equals_filter(spark, h1):
    got = topology.flood(h1, 5.0).collect()[0]
    assert set(got["points"]) == {f"0:{t}" for t, v in enumerate(H1) if v >= 5}


def _points(spark, name, signed):
    rows = [(name, "world", "week", "salient", "0", abs(t), t > 0, t < 0) for t in signed]
    return spark.createDataFrame(rows, "function_id string, space_res string, time_res string, feature_type string, region string, t int, pos boolean, neg boolean")


def _pair(spark, hi=9):
    return spark.createDataFrame([("a.f", "b.g", "a", "b", "world", "week", 0, hi, 1)], "left_fn string, right_fn string, left_dataset string, right_dataset string, space_res string, time_res string, lo int, hi int, n_regions int")


def test_score_and_strength(spark):
    pts = _points(spark, "a.f", [1, 2, -5]).unionByName(_points(spark, "b.g", [1, -2, -5, 8]))
    r = relate.measures(relate.pair_counts(_pair(spark), features.to_bits(pts))).collect()[0]
    assert (r["n_common"], r["n_pos"], r["n_neg"]) == (3, 2, 1)
    assert r["score"] == pytest.approx(1 / 3) and r["recall"] == 0.75 and r["precision"] == 1 and r["strength"] == pytest.approx(6 / 7)


def test_user_thresholds_may_overlap(spark):
    fn = function(spark, [1, 2, 3, 4])
    pts = features.from_user(fn, {"a.f": (3.0, 2.0)})
    both = pts.unionByName(pts.replace({"a.f": "b.g"}, subset=["function_id"]))
    r = relate.measures(relate.pair_counts(_pair(spark), features.to_bits(both))).collect()[0]
    assert (r["n_common"], r["n_pos"], r["n_neg"], r["score"]) == (4, 4, 2, 0.5)


def test_disjoint_features_are_not_related(spark):
    pts = _points(spark, "a.f", [1]).unionByName(_points(spark, "b.g", [2]))
    r = relate.measures(relate.pair_counts(_pair(spark), features.to_bits(pts))).collect()[0]
    assert r["score"] is None and r["strength"] == 0


def test_rotation_counts_shifts_without_overlap_as_zero(spark):
    pts = _points(spark, "a.f", [1, 3]).unionByName(_points(spark, "b.g", [1, 3]))
    p = relate.rotation_test(_pair(spark, 9), pts).collect()[0]
    assert p["n_perm"] == 9 and p["p_value"] == pytest.approx(2 / 9)  # shifts by 2 and by -2 overlap in one point


def grid(spark, rng, regions=4, steps=9, name="a.f", kinds=5):
    rows = [(name, "region", "week", str(r), t, float(rng.integers(0, kinds))) for r in range(regions) for t in range(steps)]
    return spark.createDataFrame(rows, "function_id string, space_res string, time_res string, region string, t int, value double")


def path(spark, n=4):
    return spark.createDataFrame([(str(i), str(j)) for i in range(n) for j in (i - 1, i + 1) if 0 <= j < n], "a string, b string")


def sweep_by_points(value, t, region, near):
    """The textbook sweep: union-find over all points, one by one."""
    order = np.lexsort((region, t, -value))
    at = {(int(r), int(k)): i for i, (r, k) in enumerate(zip(region, t, strict=True))}
    up, head, pairs, leaf = {}, {}, [], {}

    def find(k):
        while up[k] != k:
            k = up[k]
        return k

    rank = {int(k): n for n, k in enumerate(order)}
    for k in order.tolist():
        r, s = int(region[k]), int(t[k])
        around = [at.get((r, s - 1)), at.get((r, s + 1)), *(at.get((x, s)) for x in near[r])]
        roots = sorted({find(j) for j in around if j is not None and j in up}, key=lambda c: rank[head[c]])
        up[k] = k
        head[k] = k
        leaf[k] = head[roots[0]] if roots else k
        for c in roots[1:]:
            pairs.append((head[c], k, False))
        if roots:
            head[k] = head[roots[0]]
        for c in roots:
            up[c] = k
    last = {}
    for k in order.tolist():
        last[find(k)] = k
    return sorted(pairs + [(head[c], k, True) for c, k in last.items()]), [leaf[k] for k in range(len(value))]


def test_basins_give_the_tree_of_the_textbook_sweep():
    rng = np.random.default_rng(9)
    for _ in range(60):
        n, steps = int(rng.integers(1, 6)), int(rng.integers(1, 9))
        near = {r: [x for x in (r - 1, r + 1) if 0 <= x < n] for r in range(n)}
        keep = rng.random(n * steps) < 0.85
        if not keep.any():
            continue
        region, t, v = np.repeat(np.arange(n), steps)[keep], np.tile(np.arange(steps), n)[keep], rng.integers(0, 6, n * steps)[keep].astype(float)
        links = tuple(np.array([str(x[k]) for x in ((a, b) for a in near for b in near[a])], dtype=str) for k in (0, 1))
        s = Sweep(v, t, region.astype(str), links)
        pairs, leaf = sweep_by_points(v, t, region, near)
        assert sorted((int(a), int(b), e) for a, b, e in s.pairs) == pairs and s.leaf.tolist() == leaf


def test_large_functions_give_the_same_pairs(spark):
    fn = grid(spark, np.random.default_rng(1), 3, 7)
    cols = ["side", "creator_region", "creator_t", "destroyer_region", "destroyer_t", "persistence", "essential"]
    one, large = (sorted(map(tuple, p.select(*cols).collect())) for p in (topology.persistence(fn, path(spark, 3)), topology.persistence_large(fn, path(spark, 3), 3)))
    assert one == large


def test_features_through_the_index_equal_the_filter(spark):
    from strel.plans.query import features_through_index, index_functions

    fn = grid(spark, np.random.default_rng(2))
    ix = index_functions(fn, {"region": path(spark)})
    cols = ["region", "t", "pos", "neg"]
    got = sorted(map(tuple, features_through_index(ix, {"a.f": (1.0, 3.0)}).select(*cols).collect()))
    assert got == sorted(map(tuple, features.from_user(fn, {"a.f": (1.0, 3.0)}).select(*cols).collect())) and got
    touched = topology.flood(fn, 4.0, path(spark), topology.leaves_past(ix.pairs, 4.0)).collect()[0]
    assert touched["touched"] < 4 * 9 * 3 and touched["n_points"] == fn.where("value >= 4").count()


@pytest.mark.parametrize("statistic", ["score", "net"])
def test_rotations_of_words_equal_rotations_of_points(spark, statistic):
    rng = np.random.default_rng(5)
    steps = 150
    rows = [(f, "world", "week", "salient", str(r), int(t), bool(rng.random() < 0.6), bool(rng.random() < 0.5)) for f in ("a.f", "b.g") for r in range(2) for t in rng.choice(steps, 60, replace=False) + 30]
    pts = spark.createDataFrame(rows, "function_id string, space_res string, time_res string, feature_type string, region string, t int, pos boolean, neg boolean").where("pos OR neg")
    pair = spark.createDataFrame([("a.f", "b.g", "world", "week", 35, 170)], "left_fn string, right_fn string, space_res string, time_res string, lo int, hi int")
    for tail in ("directional", "lower", "upper", "two_sided"):
        a, b = relate.rotation_test(pair, pts, statistic, tail).collect(), relate.rotation_test_words(pair, features.to_bits(pts), statistic, tail).collect()
        assert len(a) == len(b) == 1 and a[0]["n_perm"] == b[0]["n_perm"] == 135 and a[0]["p_value"] == pytest.approx(b[0]["p_value"])


def test_sizes_bound_the_strength(spark):
    pts = _points(spark, "a.f", [1, 2, 3, 4, 5, 6, 7, 8]).unionByName(_points(spark, "b.g", [1]))
    bits = features.to_bits(pts)
    assert relate.within_strength(_pair(spark), bits, 0.3).count() == 0  # at most 2 / 9
    kept = relate.within_strength(_pair(spark), bits, 0.2)
    assert relate.measures(relate.pair_counts(kept, bits)).first()["strength"] == pytest.approx(2 / 9)


def test_index_is_stored_and_read_again(spark, tmp_path):
    from strel.plans.query import Clause, RelationshipQuery, ResultCache, index_functions, load_index, store_index

    rng = np.random.default_rng(3)
    fn = grid(spark, rng, 4, 40, "a.f").unionByName(grid(spark, rng, 4, 40, "b.g"))
    ix = index_functions(fn, {"region": path(spark)})
    store_index(ix, str(tmp_path / "ix"))
    again = load_index(spark, str(tmp_path / "ix"), ("region",))
    cols = ["left_fn", "right_fn", "feature_type", "n_common", "score", "p_value"]
    both = [sorted(map(tuple, RelationshipQuery(i, n_maps=20).run(False).select(*cols).collect()), key=str) for i in (ix, again)]
    assert both[0] == both[1] and both[0]
    plan = again.functions.where("value >= 3 AND time_res = 'week'")._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(value), GreaterThanOrEqual(value,3.0)]" in plan and "PartitionFilters: [isnotnull(time_res" in plan
    cache, q = ResultCache(spark, "v1"), RelationshipQuery(again, n_maps=20, clause=Clause(alpha=1.0))
    assert cache.get(q) is None and cache.answer(q).count() == cache.answer(q).count() and cache.get(q) is not None
    with pytest.raises(ValueError, match="no adjacency"):
        RelationshipQuery(index_functions(fn, None)).run(False)


def test_components_of_a_level_set(spark):
    fn = grid(spark, np.random.default_rng(7), 4, 12)
    inside = {(int(r["region"]), r["t"]) for r in fn.where("value >= 3").collect()}
    got: dict = {}
    for r in topology.level_components(fn, 3.0, path(spark)).collect():
        got.setdefault((r["leaf_region"], r["leaf_t"]), set()).add((int(r["region"]), r["t"]))
    assert set().union(*got.values()) == inside
    near = lambda p: {(p[0] - 1, p[1]), (p[0] + 1, p[1]), (p[0], p[1] - 1), (p[0], p[1] + 1)}
    for name, part in got.items():
        assert (int(name[0]), name[1]) in part and not set().union(*map(near, part)) & (inside - part)
        seen, stack = set(), [next(iter(part))]
        while stack:
            p = stack.pop()
            if p not in seen:
                seen.add(p)
                stack += near(p) & part
        assert seen == part
