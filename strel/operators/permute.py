"""Permutations of regions and of steps for tests."""

from __future__ import annotations

from collections import deque

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strel.runtime import ship


def lattice_maps(spark: SparkSession, rows: int, cols: int) -> DataFrame:
    """All translations of a lattice on the torus but the identity: k, region, image."""
    at = spark.range(1, rows * cols).select(F.col("id").cast("int").alias("k")).crossJoin(spark.range(rows * cols).select(F.col("id").cast("int").alias("r")))
    row = F.expr(f"pmod(r div {cols} + k div {cols}, {rows})")
    col = F.expr(f"pmod(r % {cols} + k % {cols}, {cols})")
    return at.select("k", F.col("r").cast("string").alias("region"), (row * cols + col).cast("int").cast("string").alias("image"))


def grow_map(near: dict[str, list[str]], regions: list[str], seed: int) -> dict[str, str]:
    """One bijection of the regions that keeps neighbours together where the graph allows.

    A random region goes to a random image; breadth first, unmapped neighbours of a mapped region
    go to unused neighbours of its image in random order. What is left over goes to the unused
    region nearest to the image of a mapped neighbour.
    """
    rng = np.random.default_rng(seed)
    image: dict[str, str] = {}
    free = set(regions)

    def settle(r: str, to: str, queue: deque) -> None:
        image[r] = to
        free.discard(to)
        queue.append(r)

    def nearest(start: str) -> str:
        seen, queue = {start}, deque([start])
        while queue:
            x = queue.popleft()
            if x in free:
                return x
            for y in sorted(near.get(x, ())):
                if y not in seen:
                    seen.add(y)
                    queue.append(y)
        return sorted(free)[int(rng.integers(len(free)))]

    order = [regions[i] for i in rng.permutation(len(regions))]
    for root in order:
        if root in image:
            continue
        queue: deque = deque()
        settle(root, sorted(free)[int(rng.integers(len(free)))], queue)
        late = []
        while queue:
            r = queue.popleft()
            todo = [x for x in sorted(near.get(r, ())) if x not in image]
            open_ = [x for x in sorted(near.get(image[r], ())) if x in free]
            rng.shuffle(open_)
            for x, to in zip(todo, open_, strict=False):
                settle(x, to, queue)
            late += [(x, r) for x in todo[len(open_) :]]
            if not queue and late:
                x, r0 = late.pop(0)
                while late and x in image:
                    x, r0 = late.pop(0)
                if x not in image:
                    settle(x, nearest(image[r0]), queue)
    return image


def graph_maps(adjacency: DataFrame, n_maps: int = 1000, seed: int = 11) -> DataFrame:
    """``n_maps`` grown bijections of the regions of an adjacency: k, region, image.

    A map is grown by one task that holds the links of its graph (regions of one resolution); they
    come to it by a join, not from the driver. Graphs of several resolutions (a column space_res)
    get maps of their own.
    """
    ship(adjacency.sparkSession)
    of = ["space_res"] if "space_res" in adjacency.columns else []
    ks = adjacency.sparkSession.range(1, n_maps + 1).select(F.col("id").cast("int").alias("k"))
    links = adjacency.groupBy(*of).agg(F.collect_set(F.struct("a", "b")).alias("links")).crossJoin(ks).repartition("k")

    def run(batches):
        import pandas as pd

        for b in batches:
            rows = []
            for row in b.itertuples(index=False):
                near: dict[str, list[str]] = {}
                for x in row.links:
                    near.setdefault(x["a"], []).append(x["b"])
                head = (row.space_res,) if of else ()
                rows += [(*head, int(row.k), r, to) for r, to in grow_map(near, sorted(near), seed * 1_000_003 + int(row.k)).items()]
            yield pd.DataFrame(rows, columns=[*of, "k", "region", "image"])

    return links.mapInPandas(run, f"{'space_res string, ' * len(of)}k int, region string, image string")


def fidelity(maps: DataFrame, adjacency: DataFrame) -> DataFrame:
    """Share of links whose ends stay linked, by map."""
    m = maps.select("k", "region", "image")
    a = adjacency.select(F.col("a").alias("region"), "b")
    ends = m.join(a, "region").select("k", F.col("image").alias("ia"), F.col("b").alias("region")).join(m.select("k", "region", F.col("image").alias("ib")), ["k", "region"])
    kept = ends.join(adjacency.select(F.col("a").alias("ia"), F.col("b").alias("ib"), F.lit(1).alias("hit")), ["ia", "ib"], "left")
    return kept.groupBy("k").agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count(F.lit(1))).alias("fidelity"))


def step_maps(ranges: DataFrame, n_perm: int, block: int = 1) -> DataFrame:
    """Where each step of a range (lo, hi) goes when its blocks of steps are dealt anew by a hash.

    Columns lo, hi, k, t, image; the same in every engine. Blocks of one step keep no dependence.
    """
    from pyspark.sql import Window

    spark = ranges.sparkSession
    b = ranges.select("lo", "hi").distinct().select("lo", "hi", F.explode(F.expr(f"sequence(0, cast((hi - lo) div {block} as int))")).alias("b"))
    b = b.crossJoin(spark.range(1, n_perm + 1).select(F.col("id").cast("int").alias("k")))  # n_perm rows a block, as asked for
    by = Window.partitionBy("lo", "hi", "k").orderBy(F.md5(F.concat(F.lit("perm:"), F.col("k").cast("string"), F.lit(":"), F.col("b").cast("string"))), "b")
    b = b.withColumn("size", F.least(F.lit(block), F.col("hi") - F.col("lo") + 1 - F.col("b") * block))
    b = b.withColumn("start", F.col("lo") + F.coalesce(F.sum("size").over(by.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    i = b.withColumn("i", F.explode(F.expr("sequence(0, cast(size - 1 as int))")))
    return i.select("lo", "hi", "k", (F.col("lo") + F.col("b") * block + F.col("i")).cast("int").alias("t"), (F.col("start") + F.col("i")).cast("int").alias("image"))


def free_permutation_test(pairs: DataFrame, points: DataFrame, n_perm: int = 1000, seed: int = 5, block: int = 1, stop_hits: int | None = None) -> DataFrame:
    """p-values under permutations of points that keep no dependence (or only runs of ``block`` steps).

    Of each pair, the first function keeps its points and the signs of the second are dealt anew
    over the common range. One task handles one pair and holds only its feature points. With
    ``stop_hits`` the permutations of a pair end once so many reach the observed statistic: p is then
    hits over the number tried (n_perm), which spares most of the work for unrelated pairs.
    """
    from strel.operators.relate import _in_range

    ship(pairs.sparkSession)
    key = ["left_fn", "right_fn", "space_res", "time_res", "feature_type"]
    head = pairs.select(*[c for c in (*key, "lo", "hi", "n_regions") if c in pairs.columns])
    x = _in_range(head, points, "left_fn", "p", "n", "t").withColumn("side", F.lit(0))
    y = _in_range(head, points, "right_fn", "p", "n", "t").withColumn("side", F.lit(1))
    both = x.unionByName(y)

    def run(pdf):
        import pandas as pd

        lo, steps = int(pdf["lo"].iloc[0]), int(pdf["hi"].iloc[0] - pdf["lo"].iloc[0] + 1)
        codes, names = pd.factorize(pdf["region"], sort=True)
        n = max(len(names), int(pdf["n_regions"].iloc[0]))
        at = codes.astype(np.int64) * steps + pdf["t"].to_numpy(np.int64) - lo
        sign = pdf["p"].to_numpy(np.int64) - pdf["n"].to_numpy(np.int64)
        first = pdf["side"].to_numpy() == 0
        a = np.zeros(n * steps, np.int8)
        a[at[first]] = sign[first]
        spots, signs = at[~first], sign[~first]

        def stat(where: np.ndarray) -> float:
            z = a[where] * signs
            return z.sum() / max(1, np.count_nonzero(z))

        obs = stat(spots)
        rng = np.random.default_rng(seed)
        hits, tried = 0, 0
        while tried < n_perm and (stop_hits is None or hits < stop_hits):
            if block > 1:  # where each step goes when blocks are dealt anew
                starts = rng.permutation(-(-steps // block)) * block
                order = np.concatenate([np.arange(s, min(s + block, steps)) for s in starts])
                to = np.empty(steps, np.int64)
                to[order] = np.arange(steps)
                where = spots // steps * steps + to[spots % steps]
            else:
                where = rng.choice(n * steps, len(spots), replace=False)
            v = stat(where)
            hits += v <= obs if obs < 0 else v >= obs
            tried += 1
        return pd.DataFrame([{c: pdf[c].iloc[0] for c in key} | {"n_perm": tried, "p_value": hits / max(1, tried)}])

    return both.groupBy(*key).applyInPandas(run, "left_fn string, right_fn string, space_res string, time_res string, feature_type string, n_perm long, p_value double")


def adjust_bh(tested: DataFrame) -> DataFrame:
    """Benjamini-Hochberg adjusted p-values over all tests.

    Tests of one p-value share their adjusted one, so windows run over distinct p-values (at most as
    many as permutations plus one), not over tests.
    """
    from pyspark.sql import Window

    by = tested.groupBy("p_value").agg(F.count(F.lit(1)).alias("n"))
    every, below = Window.partitionBy(), Window.orderBy("p_value").rowsBetween(Window.unboundedPreceding, 0)
    above = Window.orderBy("p_value").rowsBetween(0, Window.unboundedFollowing)
    # the rank of the last test of a p-value is the largest, which gives the smallest ratio
    ratio = by.withColumn("m", F.sum("n").over(every)).withColumn("raw", F.col("p_value") * F.col("m") / F.sum("n").over(below))
    adjusted = ratio.withColumn("p_adjusted", F.least(F.lit(1.0), F.min("raw").over(above))).select("p_value", "p_adjusted")
    return tested.join(adjusted, "p_value")
