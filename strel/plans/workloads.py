"""Planted workloads: the given tables with effects put in by hashes, the same in every engine."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from strel.functions.steps import to_step
from strel.operators import scalar
from strel.runtime import table

FN = ["function_id", "space_res", "time_res", "region", "t", "value"]


def uniform(*parts) -> Column:
    """A number in [0, 1) from a key, by the first 32 bits of its md5."""
    key = F.concat(*[p.cast("string") if isinstance(p, Column) else F.lit(p) for p in parts])
    return F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("long") / F.lit(4294967296)


def sampled(df: DataFrame, key: str, rate: float) -> DataFrame:
    """A share of the rows, chosen by a key: the same ones in every run and engine. For previews."""
    return df.where(uniform("sample:", F.col(key)) < rate)


def as_functions(df: DataFrame, name: str, space_res: str = "world", time_res: str = "week") -> DataFrame:
    """Points (t, value and maybe region) as one function."""
    region = F.col("region").cast("string") if "region" in df.columns else F.lit("0")
    return df.select(F.lit(name).alias("function_id"), F.lit(space_res).alias("space_res"), F.lit(time_res).alias("time_res"), region.alias("region"), F.col("t").cast("int").alias("t"), F.col("value").cast("double").alias("value"))


def storms(spark: SparkSession, sf: str, rate: float = 0.01, drop: float = 0.8) -> DataFrame:
    """Daily trips that fall on storm days, and wind that rises on them."""
    storm = uniform("storm:", F.col("t")) < rate
    rows = table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", to_step(F.col("l_shipdate"), "day").alias("t"))
    trips = rows.where(~(storm & (uniform("drop:", F.col("l_orderkey"), ":", F.col("l_linenumber")) < drop)))
    trips = as_functions(trips.groupBy("t").agg(F.count(F.lit(1)).alias("value")), "trips.density", time_res="day")
    wind = table(spark, sf, "orders").select("o_totalprice", to_step(F.col("o_orderdate"), "day").alias("t")).groupBy("t").agg(scalar.exact_avg(F.col("o_totalprice"), 2).alias("a"))
    wind = as_functions(wind.select("t", (F.col("a") / 10000 + F.when(storm, 40).otherwise(0)).alias("value")), "wind.avg", time_res="day")
    return scalar.densify(trips.unionByName(wind))


def rain(spark: SparkSession, sf: str, rate: float = 0.1, drop: float = 0.6) -> DataFrame:
    """Daily number, suppliers and price of trips, and rain: on rain days trips are fewer and dearer."""
    wet = uniform("rain:", F.col("t")) < rate
    rows = table(spark, sf, "lineitem").select("l_orderkey", "l_linenumber", "l_suppkey", "l_extendedprice", to_step(F.col("l_shipdate"), "day").alias("t"))
    rows = rows.where(~(wet & (uniform("drop:", F.col("l_orderkey"), ":", F.col("l_linenumber")) < drop)))
    trips = rows.groupBy("t").agg(F.count(F.lit(1)).cast("double").alias("density"), F.count_distinct("l_suppkey").cast("double").alias("unique"), scalar.exact_avg(F.col("l_extendedprice"), 2).alias("price"))
    each = F.explode(F.array(*[F.struct(F.lit(f"taxi.{m}").alias("m"), v.alias("value")) for m, v in (("density", F.col("density")), ("unique", F.col("unique")), ("avg", F.col("price") * F.when(wet, 1.6).otherwise(1.0)))]))
    trips = trips.select("t", each.alias("x")).select(F.col("x.m").alias("function_id"), F.lit("world").alias("space_res"), F.lit("day").alias("time_res"), F.lit("0").alias("region"), F.col("t").cast("int").alias("t"), F.col("x.value"))
    level = table(spark, sf, "orders").select("o_totalprice", to_step(F.col("o_orderdate"), "day").alias("t")).groupBy("t").agg(scalar.exact_avg(F.col("o_totalprice"), 2).alias("a"))
    level = as_functions(level.select("t", (F.col("a") / 10000 + F.when(wet, 40).otherwise(0)).alias("value")), "weather.rain", time_res="day")
    return scalar.densify(trips.unionByName(level))


def snow(spark: SparkSession, sf: str, rate: float = 0.12, stay: float = 0.5) -> DataFrame:
    """Snow of one day a week and riders who stay away on its other days, by day and by week."""
    week = F.floor((F.col("t") - 4) / 7)
    snowy = uniform("snow:", week) < rate
    the_day = F.expr("(t - 4) % 7") == F.floor(uniform("snowday:", week) * 7)
    o = table(spark, sf, "orders").select("o_orderkey", to_step(F.col("o_orderdate"), "day").alias("t"))
    o = o.where(~(snowy & ~the_day & (uniform("stay:", F.col("o_orderkey")) < stay)))
    bikes = as_functions(o.groupBy("t").agg(F.count(F.lit(1)).alias("value")), "bikes.density", time_res="day")
    fall = table(spark, sf, "lineitem").select(to_step(F.col("l_shipdate"), "day").alias("t")).groupBy("t").agg(F.count(F.lit(1)).alias("value"))
    fall = as_functions(fall.withColumn("value", F.col("value") + F.when(snowy & the_day, 200).otherwise(0)), "weather.snow", time_res="day")
    days = bikes.unionByName(fall)
    weeks = days.groupBy("function_id", "space_res", F.lit("week").alias("time_res"), "region", week.cast("int").alias("t")).agg(F.sum("value").alias("value"))
    return scalar.densify(days.unionByName(weeks.select(*days.columns)))


def signs(spark: SparkSession, sf: str, common: float = 0.06) -> DataFrame:
    """Fares and speeds by region and month, and over the world: every month both rise in one of the
    regions, but in some months fares rise everywhere while speeds fall. Factors are whole numbers, so
    sums are exact."""
    burst = F.when(F.col("region") == F.floor(uniform("burst:", F.col("t")) * 5).cast("string"), 4).otherwise(1)
    flood = uniform("flood:", F.col("t")) < common
    o = table(spark, sf, "orders").join(table(spark, sf, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    o = o.groupBy((F.col("c_nationkey") % 5).cast("string").alias("region"), to_step(F.col("o_orderdate"), "month").alias("t")).agg(F.count(F.lit(1)).alias("n"))
    li = table(spark, sf, "lineitem").join(table(spark, sf, "supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
    li = li.groupBy((F.col("s_nationkey") % 5).cast("string").alias("region"), to_step(F.col("l_shipdate"), "month").alias("t")).agg(F.count(F.lit(1)).alias("n"))
    fares = as_functions(o.where("region IS NOT NULL").select("region", "t", (F.col("n") * burst * F.when(flood, 2).otherwise(1)).alias("value")), "fares.density", "region", "month")
    speed = as_functions(li.where("region IS NOT NULL").select("region", "t", (F.col("n") * burst * F.when(flood, 1).otherwise(2)).alias("value")), "speed.density", "region", "month")
    places = fares.unionByName(speed)
    world = places.groupBy("function_id", F.lit("world").alias("space_res"), "time_res", F.lit("0").alias("region"), "t").agg(F.sum("value").alias("value"))
    return scalar.densify(places.unionByName(world.select(*places.columns)))


def two_years(spark: SparkSession, sf: str, planted: bool = True) -> DataFrame:
    """The second and third year of weekly orders on one axis; planted: the same weeks of both are thinned out."""
    o = table(spark, sf, "orders").select("o_orderkey", to_step(F.col("o_orderdate"), "week").alias("w"))
    start = o.agg(F.min("w").alias("w0")).select((F.col("w0") + 52).alias("start"))  # one row
    o = o.crossJoin(start).where("w BETWEEN start AND start + 103")
    if planted:
        rate = F.when(uniform("wk:", F.expr("(w - start) % 52")) < 0.15, 0.25).otherwise(1.0)
        o = o.where(uniform("keep:", F.col("o_orderkey")) < rate)
    n = o.groupBy((F.col("w") - F.col("start")).alias("t")).agg(F.count(F.lit(1)).alias("value"))
    return align_ranges(scalar.densify(as_functions(n, "orders.density")), "year1", 0, "year2", 52, 52)


def noisy(fn: DataFrame, levels: tuple[float, ...] = (0.0, 0.01, 0.02, 0.05, 0.10)) -> DataFrame:
    """Copies of functions with bounded noise of given shares of their interquartile range."""
    q = fn.groupBy("function_id").agg(F.percentile("value", F.array(F.lit(0.25), F.lit(0.75))).alias("q"))
    z = sum((uniform("z:", F.col("t"), ":", str(k)) for k in range(1, 12)), uniform("z:", F.col("t"), ":", "0")) - 6.0
    at = fn.join(q, "function_id").withColumn("iqr", F.col("q")[1] - F.col("q")[0])
    lv = F.explode(F.array(*[F.lit(x) for x in levels]))
    at = at.withColumn("level", lv)
    width = F.col("level") * F.col("iqr")
    moved = F.col("value") + F.greatest(-width, F.least(width, z * width / 2))
    name = F.concat(F.lit("noise"), F.round(F.col("level") * 100).cast("int").cast("string"), F.lit(".density"))
    return fn.unionByName(at.select(name.alias("function_id"), "space_res", "time_res", "region", "t", moved.alias("value")))


def severity(spark: SparkSession, sf: str, rate: float = 0.1) -> DataFrame:
    """Weekly discount and price rise together on rain weeks; the numbers of rows stay as they are."""
    rain = uniform("rain:", F.col("t")) < rate
    li = table(spark, sf, "lineitem").select("l_discount", to_step(F.col("l_shipdate"), "week").alias("t")).groupBy("t").agg(scalar.exact_avg(F.col("l_discount"), 2).alias("a"), F.count(F.lit(1)).alias("n"))
    o = table(spark, sf, "orders").select("o_totalprice", to_step(F.col("o_orderdate"), "week").alias("t")).groupBy("t").agg(scalar.exact_avg(F.col("o_totalprice"), 2).alias("a"), F.count(F.lit(1)).alias("n"))
    parts = [
        as_functions(li.select("t", (F.col("a") + F.when(rain, 0.03).otherwise(0.0)).alias("value")), "lineitem.avg(l_discount)"),
        as_functions(li.select("t", F.col("n").alias("value")), "lineitem.density"),
        as_functions(o.select("t", (F.col("a") * F.when(rain, 1.5).otherwise(1.0)).alias("value")), "orders.avg(o_totalprice)"),
        as_functions(o.select("t", F.col("n").alias("value")), "orders.density"),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return scalar.densify(out)


def bursts(spark: SparkSession, sf: str, rate: float = 0.01, size: int = 5) -> DataFrame:
    """Clicks and purchases by hour and nation, with common local bursts."""
    e = table(spark, sf, "events").select("event_type", "user_id", to_step(F.col("ts"), "hour").alias("t"))
    c = table(spark, sf, "customer").select("c_custkey", F.col("c_nationkey").cast("string").alias("region"))
    n = e.join(c, F.col("user_id") == F.col("c_custkey")).where("event_type IN ('click', 'purchase')").groupBy("event_type", "region", "t").agg(F.count(F.lit(1)).alias("value"))
    span = table(spark, sf, "events").agg(F.min(to_step(F.col("ts"), "hour")).alias("lo"), F.max(to_step(F.col("ts"), "hour")).alias("hi"))  # one row
    steps = span.select("lo", F.explode(F.sequence("lo", "hi")).alias("t"))
    grid = steps.crossJoin(table(spark, sf, "nation").select(F.col("n_nationkey").cast("string").alias("region")))  # every nation at every hour
    out = None
    for kind in ("click", "purchase"):
        own = grid.join(n.where(F.col("event_type") == kind).select("region", "t", "value"), ["region", "t"], "left")
        burst = F.when(uniform("burst:", F.col("region"), ":", F.col("t") - F.col("lo")) < rate, size).otherwise(0)
        fn = as_functions(own.select("region", "t", (F.coalesce("value", F.lit(0)) + burst).alias("value")), f"{kind}.density", "nation", "hour")
        out = fn if out is None else out.unionByName(fn)
    return out


def calibration(tested: DataFrame, alpha: float = 0.05) -> DataFrame:
    """Share of tested pairs that pass: near alpha on tables without any relation."""
    return tested.agg(F.count(F.lit(1)).alias("tested"), F.avg((F.col("p_value") <= alpha).cast("double")).alias("share"))


def align_ranges(fn: DataFrame, name_a: str, lo_a: int, name_b: str, lo_b: int, steps: int) -> DataFrame:
    """Two ranges of each function on one axis, as functions of two data sets."""
    part = lambda name, lo: fn.where(F.col("t").between(lo, lo + steps - 1)).withColumn("t", (F.col("t") - lo).cast("int")).withColumn("function_id", F.concat(F.lit(name + "."), F.substring_index("function_id", ".", -1)))
    return part(name_a, lo_a).unionByName(part(name_b, lo_b))
