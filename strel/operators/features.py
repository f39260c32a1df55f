"""Thresholds from persistence, and features: the points that pass them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from strel.functions.steps import season_of
from strel.operators.topology import HEAD

WORD = 64


def _season(t: str) -> F.Column:
    c = F.col(t)
    return F.when(F.col("time_res") == "hour", season_of(c, "hour")).when(F.col("time_res") == "day", season_of(c, "day")).otherwise(F.lit(0))


def with_season(df: DataFrame, t: str = "t", seasonal: bool = True) -> DataFrame:
    return df.withColumn("season", _season(t) if seasonal else F.lit(0))


def two_means(pairs: DataFrame) -> DataFrame:
    """Pairs with ``high``: whether persistence lies in the upper of two clusters.

    ``pairs`` has a season column. The split minimises the squared distances exactly, over the
    sorted distinct values of (function, side, season); of equal splits the one with the smaller
    upper cluster counts. If all values are equal they are high, unless they are 0.
    """
    group = [*HEAD, "side", "season"]
    by = Window.partitionBy(*group).orderBy("persistence")
    run = by.rowsBetween(Window.unboundedPreceding, 0)
    every = Window.partitionBy(*group)
    d = pairs.groupBy(*group, "persistence").agg(F.count(F.lit(1)).alias("c"))
    p, c = F.col("persistence"), F.col("c")
    d = d.select(
        *group, "persistence", F.sum(c).over(run).alias("n"), F.sum(c * p).over(run).alias("s"), F.sum(c * p * p).over(run).alias("q"),
        F.sum(c).over(every).alias("n_all"), F.sum(c * p).over(every).alias("s_all"), F.sum(c * p * p).over(every).alias("q_all"),
        F.count(F.lit(1)).over(every).alias("kinds"),
    )
    rest = F.col("n_all") - F.col("n")
    cost = F.round((F.col("q") - F.col("s") ** 2 / F.col("n")) + (F.col("q_all") - F.col("q") - (F.col("s_all") - F.col("s")) ** 2 / rest), 6)
    cut = d.where((F.col("n") < F.col("n_all"))).groupBy(*group).agg(F.min(F.struct(cost.alias("cost"), (-p).alias("p"))).alias("best")).select(*group, (-F.col("best.p")).alias("cut"))
    return pairs.join(cut, group, "left").withColumn("high", F.when(F.col("cut").isNotNull(), F.col("persistence") > F.col("cut")).otherwise(F.col("persistence") > 0))


def salient_thresholds(pairs: DataFrame, seasonal: bool = True) -> DataFrame:
    """theta by function, season and sign: the least high-persistence peak, the greatest such valley."""
    high = two_means(with_season(pairs, "creator_t", seasonal)).where("high")
    theta = F.when(F.col("side") == "join", F.min("birth")).otherwise(F.max("birth"))
    return high.groupBy(*HEAD, "season", "side").agg(theta.alias("theta")).withColumn("feature_type", F.lit("salient"))


def extreme_thresholds(pairs: DataFrame, salient: DataFrame, seasonal: bool = True, whisker: float = 1.5) -> DataFrame:
    """Box-plot outlier bounds over all extrema that pass the salient threshold of their season."""
    seasons = with_season(pairs, "creator_t", seasonal)
    passing = seasons.join(salient.select(*HEAD, "season", "side", "theta"), [*HEAD, "season", "side"])
    passing = passing.where(F.when(F.col("side") == "join", F.col("birth") >= F.col("theta")).otherwise(F.col("birth") <= F.col("theta")))
    q = passing.groupBy(*HEAD, "side").agg(F.percentile("birth", F.array(F.lit(0.25), F.lit(0.75))).alias("q"))
    iqr = F.col("q")[1] - F.col("q")[0]
    theta = F.when(F.col("side") == "join", F.col("q")[1] + whisker * iqr).otherwise(F.col("q")[0] - whisker * iqr)
    return q.select(*HEAD, "side", theta.alias("theta")).withColumn("feature_type", F.lit("extreme"))


def features(fn: DataFrame, salient: DataFrame, extreme: DataFrame | None = None, seasonal: bool = True) -> DataFrame:
    """Points that pass thresholds: feature_type, region, t, pos, neg.

    A point can be both when thresholds overlap. Extreme features are salient ones that also pass
    the extreme threshold.
    """
    wide = salient.groupBy(*HEAD, "season").agg(F.max(F.when(F.col("side") == "join", F.col("theta"))).alias("up"), F.max(F.when(F.col("side") == "split", F.col("theta"))).alias("down"))
    v, no = F.col("value"), F.lit(False)
    at = with_season(fn, "t", seasonal).join(wide, [*HEAD, "season"])
    at = at.withColumn("pos", F.coalesce(v >= F.col("up"), no)).withColumn("neg", F.coalesce(v <= F.col("down"), no)).where("pos OR neg")
    cols = [*HEAD, "feature_type", "region", "t", "pos", "neg"]
    out = at.withColumn("feature_type", F.lit("salient"))
    if extreme is not None:
        ex = extreme.groupBy(*HEAD).agg(F.max(F.when(F.col("side") == "join", F.col("theta"))).alias("eu"), F.max(F.when(F.col("side") == "split", F.col("theta"))).alias("ed"))
        rare = at.join(ex, HEAD)
        rare = rare.withColumn("pos", F.col("pos") & F.coalesce(v >= F.col("eu"), no)).withColumn("neg", F.col("neg") & F.coalesce(v <= F.col("ed"), no)).where("pos OR neg")
        out = out.select(*cols).unionByName(rare.withColumn("feature_type", F.lit("extreme")).select(*cols))
    return out.select(*cols)


def from_user(fn: DataFrame, thresholds: dict[str, tuple[float | None, float | None]]) -> DataFrame:
    """Features of listed functions under given (lower, upper) thresholds; None: no such features."""
    rows = [(f, hi, lo) for f, (lo, hi) in thresholds.items()]
    th = fn.sparkSession.createDataFrame(rows, "function_id string, up double, down double")
    at = fn.join(F.broadcast(th), "function_id").withColumn("pos", F.coalesce(F.col("value") >= F.col("up"), F.lit(False))).withColumn("neg", F.coalesce(F.col("value") <= F.col("down"), F.lit(False)))
    return at.where("pos OR neg").withColumn("feature_type", F.lit("user")).select(*HEAD, "feature_type", "region", "t", "pos", "neg")


def to_bits(points: DataFrame) -> DataFrame:
    """Feature points as words of 64 steps: one bit a point and sign."""
    bit = F.expr(f"shiftleft(1L, pmod(t, {WORD}))")
    words = points.withColumn("word", F.floor(F.col("t") / WORD).cast("int"))
    return words.groupBy(*HEAD, "feature_type", "region", "word").agg(
        F.bit_or(F.when(F.col("pos"), bit).otherwise(F.lit(0))).alias("pos"), F.bit_or(F.when(F.col("neg"), bit).otherwise(F.lit(0))).alias("neg")
    )


def from_bits(bits: DataFrame) -> DataFrame:
    """The points of bit words again."""
    at = bits.withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(WORD - 1))))
    on = lambda c: F.expr(f"(shiftrightunsigned({c}, i) & 1) = 1")
    out = at.select(*HEAD, "feature_type", "region", (F.col("word") * WORD + F.col("i")).alias("t"), on("pos").alias("pos"), on("neg").alias("neg"))
    return out.where("pos OR neg")


def feature_counts(bits: DataFrame) -> DataFrame:
    """Sizes of the positive, the negative and all features of every function."""
    return bits.groupBy(*HEAD, "feature_type").agg(
        F.sum(F.bit_count("pos")).alias("n_pos"), F.sum(F.bit_count("neg")).alias("n_neg"), F.sum(F.expr("bit_count(pos | neg)")).alias("n_points")
    )


def roc(fn: DataFrame, truth: DataFrame) -> DataFrame:
    """True and false positive rates of every threshold of each function against true points (region, t)."""
    marked = fn.join(truth.select("region", "t").distinct().withColumn("hit", F.lit(1)), ["region", "t"], "left").withColumn("hit", F.coalesce("hit", F.lit(0)))
    by = Window.partitionBy(*HEAD).orderBy(F.col("theta").desc()).rowsBetween(Window.unboundedPreceding, 0)
    every = Window.partitionBy(*HEAD)
    g = marked.groupBy(*HEAD, F.col("value").alias("theta")).agg(F.sum("hit").alias("tp"), F.sum(1 - F.col("hit")).alias("fp"))
    return g.select(*HEAD, "theta", (F.sum("tp").over(by) / F.sum("tp").over(every)).alias("tpr"), (F.sum("fp").over(by) / F.sum("fp").over(every)).alias("fpr"))


def auc(points: DataFrame) -> DataFrame:
    """Area under the curve of ``roc``, by trapezoids."""
    by = Window.partitionBy(*HEAD).orderBy(F.col("theta").desc())
    x0, y0 = F.coalesce(F.lag("fpr").over(by), F.lit(0.0)), F.coalesce(F.lag("tpr").over(by), F.lit(0.0))
    area = points.select(*HEAD, ((F.col("fpr") - x0) * (F.col("tpr") + y0) / 2).alias("a"))
    return area.groupBy(*HEAD).agg(F.sum("a").alias("auc"))


def zscore_events(fn: DataFrame, width: int = 8, z: float = 2.0) -> DataFrame:
    """Points further than z deviations from the mean of the ``width`` steps before."""
    by = Window.partitionBy(*HEAD, "region").orderBy("t").rowsBetween(-width, -1)
    d = fn.withColumn("m", F.avg("value").over(by)).withColumn("s", F.stddev_pop("value").over(by)).withColumn("n", F.count("value").over(by))
    return d.where((F.col("n") == width) & (F.abs(F.col("value") - F.col("m")) > z * F.col("s"))).select(*HEAD, "region", "t", "value", (F.col("value") > F.col("m")).alias("pos"))
