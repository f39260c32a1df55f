"""Relations of functions: common feature points, score, strength, and permutation tests."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from strel.operators.features import WORD
from strel.runtime import ship

FN = ["function_id", "space_res", "time_res", "feature_type"]


def related_points(a: DataFrame, b: DataFrame) -> DataFrame:
    """Points that are features of both, and whether signs agree (``rel`` 1), oppose (-1) or both (0)."""
    x = a.select("region", "t", F.col("pos").alias("p1"), F.col("neg").alias("n1"))
    y = b.select("region", "t", F.col("pos").alias("p2"), F.col("neg").alias("n2"))
    same = F.expr("p1 AND p2 OR n1 AND n2").cast("int")
    anti = F.expr("p1 AND n2 OR n1 AND p2").cast("int")
    return x.join(y, ["region", "t"]).withColumn("rel", same - anti)


def spans(fn: DataFrame) -> DataFrame:
    """Range of steps, regions and points of every function."""
    return fn.groupBy("function_id", "space_res", "time_res").agg(F.min("t").alias("lo"), F.max("t").alias("hi"), F.count_distinct("region").alias("n_regions"), F.count(F.lit(1)).alias("n_values"))


def candidate_pairs(meta: DataFrame, min_steps: int = 2) -> DataFrame:
    """Pairs of functions of different data sets at one resolution, with their common range of steps.

    ``meta`` is ``spans``: as many rows as functions, so the join is of metadata only.
    """
    d = meta.withColumn("dataset", F.substring_index("function_id", ".", 1))
    names = lambda side: [F.col("space_res"), F.col("time_res"), *[F.col(c).alias(f"{side}_{c}") for c in ("function_id", "dataset", "lo", "hi", "n_regions")]]
    pairs = d.select(*names("left")).join(d.select(*names("right")), ["space_res", "time_res"]).where("left_dataset < right_dataset")
    pairs = pairs.withColumn("lo", F.greatest("left_lo", "right_lo")).withColumn("hi", F.least("left_hi", "right_hi"))
    return pairs.where(F.col("hi") - F.col("lo") + 1 >= min_steps).select(
        F.col("left_function_id").alias("left_fn"), F.col("right_function_id").alias("right_fn"), "left_dataset", "right_dataset", "space_res", "time_res",
        "lo", "hi", F.least("left_n_regions", "right_n_regions").alias("n_regions"),
    )


def _mask() -> Column:
    """Bits of a word that lie in the common range."""
    lo = F.expr(f"greatest(lo - word * {WORD}, 0)")
    hi = F.expr(f"least(hi - word * {WORD}, {WORD - 1})")
    ones = F.lit(-1).cast("long")
    whole = F.call_function("shiftleft", ones, lo.cast("int")).bitwiseAND(F.call_function("shiftrightunsigned", ones, (F.lit(WORD - 1) - hi).cast("int")))
    return F.when(lo <= hi, whole).otherwise(F.lit(0).cast("long"))


def _sides(pairs: DataFrame, bits: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Words of both functions of every pair, cut to its common range: p1, n1 and p2, n2.

    Words that hold no feature in that range are left out.
    """
    key = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    b = bits.select(*FN, "region", "word", "pos", "neg")
    head = pairs.select(*[c for c in (*key, "lo", "hi") if c in pairs.columns])
    on = [c for c in ("space_res", "time_res", "feature_type") if c in head.columns]
    both = lambda fn: head.join(b.withColumnRenamed("function_id", fn), [fn, *on]).withColumn("m", _mask()).where("((pos | neg) & m) <> 0")
    x = both("left_fn").select(*key, "region", "word", F.expr("pos & m").alias("p1"), F.expr("neg & m").alias("n1"))
    y = both("right_fn").select(*key, "region", "word", F.expr("pos & m").alias("p2"), F.expr("neg & m").alias("n2"))
    return x, y


def within_strength(pairs: DataFrame, bits: DataFrame, min_strength: float) -> DataFrame:
    """Pairs and feature types whose sizes alone allow the strength: it is at most 2 min / (n1 + n2).

    Only sizes are compared; the words of pairs that cannot reach the strength never meet.
    """
    key = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    x, y = _sides(pairs, bits)
    n = lambda d, a, b, c: d.groupBy(*key).agg(F.sum(F.expr(f"bit_count({a} | {b})")).alias(c))
    sizes = n(x, "p1", "n1", "s1").join(n(y, "p2", "n2", "s2"), key)
    fit = sizes.where(2 * F.least("s1", "s2") >= min_strength * (F.col("s1") + F.col("s2"))).select(*key)
    return pairs.join(fit, key[:4])


def pair_counts(pairs: DataFrame, bits: DataFrame) -> DataFrame:
    """Sizes and overlaps of the features of every pair, on its common range.

    Columns beside those of ``pairs``: feature_type (unless ``pairs`` names it), n1, n2, n_common,
    n_pos, n_neg. Words of 64 steps meet by equality of (resolution, type, region, word). Pairs of
    which neither function has a feature of a type in the common range have no row for it.
    """
    key = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    x, y = _sides(pairs, bits)
    zero = F.lit(0).cast("long")
    bits_of = lambda e: F.sum(F.bit_count(F.expr(e))).alias
    met = x.join(y, [*key, "region", "word"], "full")
    met = met.select(*key, *[F.coalesce(c, zero).alias(c) for c in ("p1", "n1", "p2", "n2")])
    counts = met.groupBy(*key).agg(
        bits_of("p1 | n1")("n1"), bits_of("p2 | n2")("n2"), bits_of("(p1 | n1) & (p2 | n2)")("n_common"),
        bits_of("(p1 & p2) | (n1 & n2)")("n_pos"), bits_of("(p1 & n2) | (n1 & p2)")("n_neg"),
    )
    return pairs.join(counts, [c for c in key if c in pairs.columns])


def measures(counts: DataFrame) -> DataFrame:
    """score (agreement of signs), precision, recall and strength (their harmonic mean)."""
    n = F.col("n_common")
    return (
        counts.withColumn("score", F.when(n > 0, (F.col("n_pos") - F.col("n_neg")) / n))
        .withColumn("precision", F.when(F.col("n1") > 0, n / F.col("n1")).otherwise(0.0))
        .withColumn("recall", F.when(F.col("n2") > 0, n / F.col("n2")).otherwise(0.0))
        .withColumn("strength", F.when(F.col("n1") + F.col("n2") > 0, 2 * n / (F.col("n1") + F.col("n2"))).otherwise(0.0))
    )


def _in_range(pairs: DataFrame, points: DataFrame, fn: str, p: str, n: str, t: str) -> DataFrame:
    q = points.select(F.col("function_id").alias(fn), "space_res", "time_res", "feature_type", "region", F.col("t").alias(t), F.col("pos").alias(p), F.col("neg").alias(n))
    keep = [c for c in pairs.columns if c != "feature_type"]
    on = [fn, "space_res", "time_res", *(["feature_type"] if "feature_type" in pairs.columns else [])]
    return pairs.join(q, on).where(F.col(t).between(F.col("lo"), F.col("hi"))).select(*keep, "feature_type", "region", t, p, n)


def lag_histogram(pairs: DataFrame, points: DataFrame) -> DataFrame:
    """Overlaps of every pair under every rotation of its second function in time.

    One join and one aggregate give all rotations: a pair of points meets at exactly one lag.
    """
    key = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    head = pairs.select(*[c for c in (*key, "lo", "hi") if c in pairs.columns])
    x = _in_range(head, points, "left_fn", "p1", "n1", "t1").select(*key, "lo", "hi", "region", "t1", "p1", "n1")
    y = _in_range(head, points, "right_fn", "p2", "n2", "t2").select(*key, "region", "t2", "p2", "n2")
    steps = F.col("hi") - F.col("lo") + 1
    met = x.join(y, [*key, "region"]).withColumn("lag", F.pmod(F.col("t1") - F.col("t2"), steps))
    one = lambda e: F.sum(F.expr(e).cast("int")).alias
    return met.groupBy(*key, "lo", "hi", "lag").agg(F.count(F.lit(1)).alias("n_common"), one("p1 AND p2 OR n1 AND n2")("n_pos"), one("p1 AND n2 OR n1 AND p2")("n_neg"))


def _statistic(kind: str) -> Column:
    net = F.col("n_pos") - F.col("n_neg")
    return net / F.col("n_common") if kind == "score" else net.cast("double")


def p_value(observed: Column, null_hits_ge: Column, null_hits_le: Column, null_hits_abs: Column, n: Column, tail: str = "directional", estimator: str = "plain") -> Column:
    """Share of permutations at least as extreme as the observed statistic."""
    hits = {"upper": null_hits_ge, "lower": null_hits_le, "two_sided": null_hits_abs, "directional": F.when(observed < 0, null_hits_le).otherwise(null_hits_ge)}[tail]
    return hits / n if estimator == "plain" else (hits + 1) / (n + 1)


def _test(hist: DataFrame, base: list[str], k: str, total: Column, statistic: str, tail: str, estimator: str) -> DataFrame:
    """p-values from the statistic of each permutation; permutations without overlap count as 0."""
    stat = hist.withColumn("s", F.round(_statistic(statistic), 9))
    seen = stat.where(F.col(k) == 0).select(*base, F.col("s").alias("obs"))
    null = stat.where(F.col(k) != 0).join(seen, base)
    agg = null.groupBy(*base, "obs").agg(
        F.count(F.lit(1)).alias("present"), F.sum((F.col("s") >= F.col("obs")).cast("int")).alias("ge"), F.sum((F.col("s") <= F.col("obs")).cast("int")).alias("le"),
        F.sum((F.abs("s") >= F.abs("obs")).cast("int")).alias("abs"),
    )
    full = seen.join(agg.drop("obs"), base, "left").withColumn("n_perm", total.cast("long"))
    none = F.col("n_perm") - F.coalesce("present", F.lit(0))
    plus = lambda c, ok: F.coalesce(c, F.lit(0)) + F.when(ok, none).otherwise(0)
    o = F.col("obs")
    p = p_value(o, plus("ge", o <= 0), plus("le", o >= 0), plus("abs", o == 0), F.col("n_perm"), tail, estimator)
    return full.where("n_perm > 0").withColumn("p_value", p).select(*base, "n_perm", "p_value")


def rotation_test(pairs: DataFrame, points: DataFrame, statistic: str = "score", tail: str = "directional", estimator: str = "plain") -> DataFrame:
    """p-value of each pair against all rotations in time but the identity, from joins of points.

    Work is the product of the sizes of two feature sets: for sparse features, and as a check.
    """
    base = ["left_fn", "right_fn", "space_res", "time_res", "feature_type", "lo", "hi"]
    out = _test(lag_histogram(pairs, points), base, "lag", F.col("hi") - F.col("lo"), statistic, tail, estimator)
    return out.drop("lo", "hi")


#: Values (regions x steps) of one side that a task transforms at once.
FFT_VALUES = 1 << 21


def rotation_test_words(pairs: DataFrame, bits: DataFrame, statistic: str = "score", tail: str = "directional", estimator: str = "plain") -> DataFrame:
    """The same p-values from words of 64 steps: all rotations of a pair by one Fourier transform.

    The agreement of signs under a rotation is the correlation of (pos - neg) of both functions, the
    overlap that of their feature sets. Every function's words travel to its pairs as one array;
    work per pair is T log T whatever its number of features.
    """
    ship(pairs.sparkSession)
    key = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    whole = bits.groupBy(*FN).agg(F.collect_list(F.struct("region", "word", "pos", "neg")).alias("w"))  # one function's words
    on = [c for c in ("space_res", "time_res", "feature_type") if c in pairs.columns]
    side = lambda fn, to: whole.withColumnsRenamed({"function_id": fn, "w": to})
    met = pairs.select(*[c for c in (*key, "lo", "hi") if c in pairs.columns]).join(side("left_fn", "x"), ["left_fn", *on]).join(side("right_fn", "y"), ["right_fn", *{*on, "feature_type"}])
    rows = met.select(*key, F.col("lo").cast("long").alias("lo"), F.col("hi").cast("long").alias("hi"), "x", "y").where("hi > lo")
    return rows.mapInArrow(_rotate(key, statistic, tail, estimator), "left_fn string, right_fn string, space_res string, time_res string, feature_type string, n_perm long, p_value double")


def _signs(words, place: np.ndarray, n: int, lo: int, steps: int) -> tuple[np.ndarray, np.ndarray]:
    """(pos - neg) and (pos or neg) of words (word, pos, neg) put on ``n`` rows of steps."""
    first = lo // WORD
    width = (lo + steps - 1) // WORD - first + 1
    word, pos, neg = words
    ok = (word >= first) & (word < first + width) & (place >= 0)
    out = []
    for bits in (pos, neg):
        grid = np.zeros((n, width), "<i8")
        grid[place[ok], word[ok] - first] = bits[ok]
        flat = np.unpackbits(grid.view(np.uint8), axis=1, bitorder="little")
        out.append(flat[:, lo - first * WORD : lo - first * WORD + steps].astype(np.float64))
    p, m = out
    return p - m, np.maximum(p, m)


def _correlate(x, y, lo: int, steps: int) -> tuple[np.ndarray, np.ndarray]:
    """Agreement of signs and overlap under every rotation, for rows of two word lists."""
    import pyarrow as pa

    rows, sides = len(x), []
    regions = pa.concat_arrays([v.flatten().field("region") for v in (x, y)]).dictionary_encode()
    codes, kinds = np.asarray(regions.indices), max(1, len(regions.dictionary))
    at = 0
    for v in (x, y):
        flat = v.flatten()
        row = np.repeat(np.arange(rows), np.asarray(v.value_lengths()))
        sides.append((row * kinds + codes[at : at + len(flat)], tuple(np.asarray(flat.field(c), np.int64) for c in ("word", "pos", "neg"))))
        at += len(flat)
    both = np.intersect1d(sides[0][0], sides[1][0])  # (row, region) of both functions
    net, common = np.zeros((rows, steps)), np.zeros((rows, steps))
    part = max(1, FFT_VALUES // steps)
    for begin in range(0, len(both), part):
        some = both[begin : begin + part]
        dense = []
        for where, words in sides:
            place = np.searchsorted(some, where)
            place = np.where(some[np.minimum(place, len(some) - 1)] == where, np.minimum(place, len(some) - 1), -1)
            dense.append(_signs(words, place, len(some), lo, steps))
        for out, (u, v) in zip((net, common), zip(*dense, strict=True), strict=True):
            np.add.at(out, some // kinds, np.fft.irfft(np.fft.rfft(u) * np.conj(np.fft.rfft(v)), steps))
    return np.rint(net), np.rint(common)


def _rotate(key: list[str], statistic: str, tail: str, estimator: str):
    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        for b in batches:
            lo, hi = (np.asarray(b.column(c)) for c in ("lo", "hi"))
            ranges, of = np.unique(np.column_stack([lo, hi]), axis=0, return_inverse=True)
            for k, (first, last) in enumerate(ranges.tolist()):
                steps = last - first + 1
                rows = np.flatnonzero(of.ravel() == k)
                for some in np.array_split(rows, -(-len(rows) * steps // FFT_VALUES)):
                    if not len(some):
                        continue
                    sub = b.take(pa.array(some))
                    net, common = _correlate(sub.column("x"), sub.column("y"), first, steps)
                    s = np.round(net / np.maximum(common, 1) if statistic == "score" else net, 9)
                    obs, null = s[:, :1], s[:, 1:]
                    above, below = (null >= obs).sum(1), (null <= obs).sum(1)
                    hits = {"upper": above, "lower": below, "two_sided": (np.abs(null) >= np.abs(obs)).sum(1), "directional": np.where(obs[:, 0] < 0, below, above)}[tail]
                    p = hits / (steps - 1) if estimator == "plain" else (hits + 1) / steps
                    met = pa.array(np.flatnonzero(common[:, 0] > 0))
                    yield pa.RecordBatch.from_arrays([*(sub.column(c).take(met) for c in key), pa.array(np.full(len(met), steps - 1)), pa.array(p).take(met)], [*key, "n_perm", "p_value"])

    return run


def co_occurrence(pairs: DataFrame, points: DataFrame) -> DataFrame:
    """Overlaps of every pair by (region of the first, region of the second), at equal steps."""
    key = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    head = pairs.select(*[c for c in (*key, "lo", "hi") if c in pairs.columns])
    x = _in_range(head, points, "left_fn", "p1", "n1", "t").select(*key, F.col("region").alias("r1"), "t", "p1", "n1")
    y = _in_range(head, points, "right_fn", "p2", "n2", "t").select(*key, F.col("region").alias("r2"), "t", "p2", "n2")
    one = lambda e: F.sum(F.expr(e).cast("int")).alias
    return x.join(y, [*key, "t"]).groupBy(*key, "r1", "r2").agg(F.count(F.lit(1)).alias("n_common"), one("p1 AND p2 OR n1 AND n2")("n_pos"), one("p1 AND n2 OR n1 AND p2")("n_neg"))


def _moved(met: DataFrame, maps: DataFrame, base: list[str], steps: list[str]) -> DataFrame:
    """Overlaps under the identity (k = 0) and under every map of the regions of the second function."""
    same = met.where("r1 = r2").withColumn("k", F.lit(0))
    on = ["space_res"] if "space_res" in maps.columns else []
    to = maps.select(*on, "k", F.col("region").alias("r2"), F.col("image").alias("r1"))
    cols = [*base, *steps, "k", "n_common", "n_pos", "n_neg"]
    hist = same.select(*cols).unionByName(met.join(to, [*on, "r1", "r2"]).select(*cols))
    return hist.groupBy(*base, *steps, "k").agg(*[F.sum(c).alias(c) for c in ("n_common", "n_pos", "n_neg")])


def _maps_of(maps: DataFrame, base: DataFrame) -> DataFrame:
    """Rows of ``base`` with the number of maps that apply to them."""
    if "space_res" in maps.columns:
        return base.join(maps.groupBy("space_res").agg(F.count_distinct("k").alias("n_maps")), "space_res")
    return base.crossJoin(maps.agg(F.count_distinct("k").alias("n_maps")))  # one row


def spatial_test(pairs: DataFrame, points: DataFrame, maps: DataFrame, statistic: str = "score", tail: str = "directional", estimator: str = "plain") -> DataFrame:
    """p-value of each pair against maps of the regions: ``maps`` has k, region, image.

    With a column space_res, maps apply to the pairs of that resolution. The second function is
    moved by each map. All maps read one table of overlaps by region pair.
    """
    base = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    hist = _maps_of(maps, _moved(co_occurrence(pairs, points), maps, base, []))
    return _test(hist, [*base, "n_maps"], "k", F.col("n_maps"), statistic, tail, estimator).drop("n_maps")


def step_map_test(pairs: DataFrame, points: DataFrame, maps: DataFrame, statistic: str = "score", tail: str = "directional", estimator: str = "plain") -> DataFrame:
    """p-value of each pair against given moves of steps (lo, hi, k, t, image; see ``permute.step_maps``).

    Moves that keep no dependence in time make the unrestricted Monte Carlo test.
    """
    base = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    head = pairs.select(*[c for c in (*base, "lo", "hi") if c in pairs.columns])
    x = _in_range(head, points, "left_fn", "p1", "n1", "image").select(*base, "region", "image", "p1", "n1")
    y = _in_range(head, points, "right_fn", "p2", "n2", "t").select(*base, "lo", "hi", "region", "t", "p2", "n2")
    same = y.withColumn("k", F.lit(0)).withColumn("image", F.col("t"))
    cols = [*base, "region", "k", "image", "p2", "n2"]
    moved = y.join(maps.select("lo", "hi", "k", "t", "image"), ["lo", "hi", "t"]).select(*cols).unionByName(same.select(*cols))
    one = lambda e: F.sum(F.expr(e).cast("int")).alias
    hist = x.join(moved, [*base, "region", "image"]).groupBy(*base, "k").agg(F.count(F.lit(1)).alias("n_common"), one("p1 AND p2 OR n1 AND n2")("n_pos"), one("p1 AND n2 OR n1 AND p2")("n_neg"))
    hist = hist.crossJoin(maps.agg(F.count_distinct("k").alias("n_maps")))  # one row
    return _test(hist, [*base, "n_maps"], "k", F.col("n_maps"), statistic, tail, estimator).drop("n_maps")


def space_time_test(pairs: DataFrame, points: DataFrame, maps: DataFrame, statistic: str = "score", tail: str = "directional", estimator: str = "plain") -> DataFrame:
    """p-value of each pair against every map of the regions together with every rotation in time.

    On a lattice with its translations as maps this is the test on the three-dimensional torus. One
    table of overlaps by (region, region, lag) serves all of them.
    """
    base = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    head = pairs.select(*[c for c in (*base, "lo", "hi") if c in pairs.columns])
    x = _in_range(head, points, "left_fn", "p1", "n1", "t1").select(*base, "lo", "hi", F.col("region").alias("r1"), "t1", "p1", "n1")
    y = _in_range(head, points, "right_fn", "p2", "n2", "t2").select(*base, F.col("region").alias("r2"), "t2", "p2", "n2")
    met = x.join(y, base).withColumn("lag", F.pmod(F.col("t1") - F.col("t2"), F.col("hi") - F.col("lo") + 1))
    one = lambda e: F.sum(F.expr(e).cast("int")).alias
    met = met.groupBy(*base, "lo", "hi", "r1", "r2", "lag").agg(F.count(F.lit(1)).alias("n_common"), one("p1 AND p2 OR n1 AND n2")("n_pos"), one("p1 AND n2 OR n1 AND p2")("n_neg"))
    hist = _maps_of(maps, _moved(met, maps, [*base, "lo", "hi"], ["lag"]))
    every = hist.withColumn("j", F.col("k") * (F.col("hi") - F.col("lo") + 1) + F.col("lag"))  # 0: nothing moved
    total = (F.col("n_maps") + 1) * (F.col("hi") - F.col("lo") + 1) - 1
    return _test(every, [*base, "lo", "hi", "n_maps"], "j", total, statistic, tail, estimator).drop("lo", "hi", "n_maps")
