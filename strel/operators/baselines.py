"""Methods compared with: correlation, mutual information, time warping, least squares."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from strel.runtime import ship

PAIR = ["left_fn", "right_fn", "space_res", "time_res"]


def aligned(pairs: DataFrame, fn: DataFrame) -> DataFrame:
    """Values of both functions of every pair at every common point: x and y."""
    head = pairs.select(*PAIR, "lo", "hi")
    f = fn.select("function_id", "space_res", "time_res", "region", "t", "value")
    x = head.join(f.withColumnsRenamed({"function_id": "left_fn", "value": "x"}), ["left_fn", "space_res", "time_res"]).where("t BETWEEN lo AND hi")
    y = f.withColumnsRenamed({"function_id": "right_fn", "value": "y"})
    return x.join(y, ["right_fn", "space_res", "time_res", "region", "t"]).select(*PAIR, "region", "t", "x", "y")


def pearson(pairs: DataFrame, fn: DataFrame) -> DataFrame:
    return aligned(pairs, fn).groupBy(*PAIR).agg(F.corr("x", "y").alias("pcc"))


def least_squares(pairs: DataFrame, fn: DataFrame, binary: bool = False) -> DataFrame:
    """Slope, intercept and r2 of y on x; ``binary``: on whether x is above its mean."""
    z = aligned(pairs, fn)
    if binary:
        z = z.withColumn("x", (F.col("x") > F.avg("x").over(Window.partitionBy(*PAIR))).cast("double"))
    return z.groupBy(*PAIR).agg(F.regr_slope("y", "x").alias("slope"), F.regr_intercept("y", "x").alias("intercept"), F.regr_r2("y", "x").alias("r2"))


def mutual_information(pairs: DataFrame, fn: DataFrame, bins: int | None = None) -> DataFrame:
    """Mutual information over equal-width bins, by the geometric mean of the entropies.

    Without ``bins``, the number of points sets it: sqrt(n / 5), from 2 to 64.
    """
    w = Window.partitionBy(*PAIR)
    z = aligned(pairs, fn).withColumn("n", F.count(F.lit(1)).over(w))
    k = F.lit(bins) if bins else F.least(F.greatest(F.ceil(F.sqrt(F.col("n") / 5)), F.lit(2)), F.lit(64))
    z = z.withColumn("k", k)
    cell = lambda c: F.when(F.max(c).over(w) > F.min(c).over(w), F.least(F.floor((F.col(c) - F.min(c).over(w)) / (F.max(c).over(w) - F.min(c).over(w)) * F.col("k")), F.col("k") - 1)).otherwise(0).cast("int")
    c = z.withColumn("bx", cell("x")).withColumn("by", cell("y")).groupBy(*PAIR, "n", "bx", "by").agg(F.count(F.lit(1)).alias("c"))
    wx, wy = Window.partitionBy(*PAIR, "bx"), Window.partitionBy(*PAIR, "by")
    c = c.withColumn("cx", F.sum("c").over(wx)).withColumn("cy", F.sum("c").over(wy))
    p = F.col("c") / F.col("n")
    own = lambda m: F.sum(-p * F.log(F.col(m) / F.col("n")))
    out = c.groupBy(*PAIR).agg(F.sum(p * F.log(F.col("c") * F.col("n") / (F.col("cx") * F.col("cy")))).alias("mi"), own("cx").alias("hx"), own("cy").alias("hy"))
    return out.select(*PAIR, F.when((F.col("hx") > 1e-12) & (F.col("hy") > 1e-12), F.col("mi") / F.sqrt(F.col("hx") * F.col("hy"))).alias("nmi"))


def dtw_distance(x: np.ndarray, y: np.ndarray, band: int | None = None) -> float:
    """Dynamic time warping with absolute differences, by anti-diagonals of the cost table."""
    n, m = len(x), len(y)
    prev2, prev = np.full(n + 1, np.inf), np.full(n + 1, np.inf)
    prev2[0] = 0.0
    for d in range(2, n + m + 1):
        cur = np.full(n + 1, np.inf)
        i = np.arange(max(1, d - m), min(n, d - 1) + 1)
        if band is not None:
            i = i[np.abs(2 * i - d) <= band + abs(n - m)]
        if len(i):
            j = d - i
            best = np.minimum(np.minimum(prev[i - 1], prev[i]), prev2[i - 1])
            cur[i] = np.abs(x[i - 1] - y[j - 1]) + best
        prev2, prev = prev, cur
    return float(prev[n])


def time_warping(pairs: DataFrame, fn: DataFrame, band: int | None = None) -> DataFrame:
    """1 - distance / (distance of both to the zero line), over standardised series; one task a pair."""
    ship(fn.sparkSession)

    def run(pdf):
        import pandas as pd

        pdf = pdf.sort_values("t")
        x, y = (v - v.mean() for v in (pdf["x"].to_numpy(), pdf["y"].to_numpy()))
        x, y = (v / v.std() if v.std() > 0 else v for v in (x, y))
        zero = np.abs(x).sum() + np.abs(y).sum()  # every value is matched with zero
        s = 1 - dtw_distance(x, y, band) / zero if zero > 0 else math.nan
        return pd.DataFrame([{c: pdf[c].iloc[0] for c in PAIR} | {"dtw": s}])

    return aligned(pairs, fn).groupBy(*PAIR).applyInPandas(run, "left_fn string, right_fn string, space_res string, time_res string, dtw double")


def compare_methods(found: DataFrame, other: DataFrame, col: str, least: float) -> DataFrame:
    """Verdicts of two methods on the same pairs: both, only the first, only the other, none."""
    a = found.groupBy(*PAIR).agg(F.max("significant").alias("ours"))
    b = other.select(*PAIR, (F.abs(col) >= least).alias("theirs"))
    both = a.join(b, PAIR, "full").select(*PAIR, F.coalesce("ours", F.lit(False)).alias("ours"), F.coalesce("theirs", F.lit(False)).alias("theirs"))
    return both.withColumn("verdict", F.when(F.col("ours") & F.col("theirs"), "both").when(F.col("ours"), "only ours").when(F.col("theirs"), f"only {col}").otherwise("none"))
