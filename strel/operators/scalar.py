"""Scalar functions: one number for each (region, step) of a data set, at every resolution.

A table of functions has the columns function_id, space_res, time_res, region, t, value. Raw rows
are read once per data set; all measures of a tuple share that scan and its one shuffle.
"""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from strel.functions.steps import TIME_DAG, coarser, reachable, to_step
from strel.runtime import materialize
from strel.sources.catalog import DatasetSpec

KEYS = ["function_id", "space_res", "time_res", "region", "t"]


def exact_avg(col: Column, decimals: int | None) -> Column:
    """Average that does not depend on the order of rows, for values of few decimals."""
    if decimals is None:
        return F.avg(col)
    unit = 10**decimals
    return F.sum(F.round(col * unit).cast("long")) / F.count(col) / unit


def assign_points(spec: DatasetSpec, space_res: str, time_res: str) -> DataFrame:
    """The rows of a data set with region and t; only the columns with roles are read."""
    region = F.lit("0") if space_res == "world" else F.col(spec.space[space_res]).cast("string")
    keep = [*spec.ids, *spec.attrs]
    return spec.df.select(region.alias("region"), to_step(F.col(spec.time), time_res).alias("t"), *keep).where("region IS NOT NULL AND t IS NOT NULL")


def wide(spec: DatasetSpec, space_res: str, time_res: str, unique: Iterable[str] | None = None, attrs: Iterable[str] | None = None, approx: float | None = None) -> DataFrame:
    """One row for each point with tuples: density, unique ids, average attributes."""
    unique = tuple(spec.ids if unique is None else unique)
    attrs = tuple(spec.attrs if attrs is None else attrs)
    distinct = (lambda c: F.approx_count_distinct(c, approx)) if approx else F.count_distinct
    return assign_points(spec, space_res, time_res).groupBy("region", "t").agg(
        F.count(F.lit(1)).cast("double").alias("density"),
        *[distinct(c).cast("double").alias(f"unique({c})") for c in unique],
        *[exact_avg(F.col(c), spec.decimals).alias(f"avg({c})") for c in attrs],
    )


def long(points: DataFrame, dataset: str, space_res: str, time_res: str) -> DataFrame:
    """Wide measures as functions."""
    measures = [c for c in points.columns if c not in ("region", "t")]
    pairs = F.explode(F.array(*[F.struct(F.lit(f"{dataset}.{m}").alias("function_id"), F.col(f"`{m}`").alias("value")) for m in measures]))
    out = points.select("region", "t", pairs.alias("x"))
    return out.select("x.function_id", F.lit(space_res).alias("space_res"), F.lit(time_res).alias("time_res"), "region", "t", "x.value")


def attribute(spec: DatasetSpec, attr: str, space_res: str, time_res: str, agg) -> DataFrame:
    """A function of one attribute under any aggregate: a name or a function from column to column."""
    named = {"sum": F.sum, "median": F.median, "min": F.min, "max": F.max, "avg": lambda c: exact_avg(c, spec.decimals), "stddev": F.stddev}
    how = named[agg] if isinstance(agg, str) else agg
    label = agg if isinstance(agg, str) else getattr(agg, "__name__", "custom")
    points = assign_points(spec, space_res, time_res).groupBy("region", "t").agg(how(F.col(attr)).cast("double").alias(f"{label}({attr})"))
    return long(points, spec.name, space_res, time_res)


def states(spec: DatasetSpec, space_res: str, time_res: str) -> DataFrame:
    """Mergeable partial aggregates of every point: they roll up along the resolutions."""
    unit = 10 ** (spec.decimals or 0)
    return assign_points(spec, space_res, time_res).groupBy("region", "t").agg(
        F.count(F.lit(1)).alias("n"),
        *[F.hll_sketch_agg(F.col(c).cast("string")).alias(f"hll_{c}") for c in spec.ids],
        *[x for c in spec.attrs for x in (F.count(c).alias(f"cnt_{c}"), F.sum(F.round(F.col(c) * unit).cast("long")).alias(f"sum_{c}"), F.min(c).alias(f"min_{c}"), F.max(c).alias(f"max_{c}"))],
    )


def roll_up(state: DataFrame, spec: DatasetSpec, time_from: str, time_to: str, space_map: DataFrame | None = None) -> DataFrame:
    """Partial aggregates of a coarser resolution from those of a finer one, without the raw rows.

    ``space_map`` (region, to_region) turns regions into coarser ones; it has one row a region.
    """
    if space_map is not None:
        state = state.join(space_map, "region").drop("region").withColumnRenamed("to_region", "region")
    return state.withColumn("t", coarser(F.col("t"), time_from, time_to)).groupBy("region", "t").agg(
        F.sum("n").alias("n"),
        *[F.hll_union_agg(f"hll_{c}").alias(f"hll_{c}") for c in spec.ids],
        *[x for c in spec.attrs for x in (F.sum(f"cnt_{c}").alias(f"cnt_{c}"), F.sum(f"sum_{c}").alias(f"sum_{c}"), F.min(f"min_{c}").alias(f"min_{c}"), F.max(f"max_{c}").alias(f"max_{c}"))],
    )


def finish(state: DataFrame, spec: DatasetSpec) -> DataFrame:
    """Wide measures of partial aggregates; unique counts are sketch estimates."""
    unit = 10 ** (spec.decimals or 0)
    return state.select(
        "region", "t", F.col("n").cast("double").alias("density"),
        *[F.hll_sketch_estimate(f"hll_{c}").cast("double").alias(f"unique~({c})") for c in spec.ids],
        *[(F.col(f"sum_{c}") / F.col(f"cnt_{c}") / unit).alias(f"avg({c})") for c in spec.attrs],
        *[F.col(f"{a}_{c}").cast("double").alias(f"{a}({c})") for c in spec.attrs for a in ("min", "max")],
    )


#: Resolutions at which relationships are evaluated, the finest first.
EVALUATED_TIME = ("hour", "day", "week", "month")
EVALUATED_SPACE = ("nation", "segment", "region", "world")


def viable(spec: DatasetSpec, spaces: Iterable[str] = EVALUATED_SPACE, times: Iterable[str] = EVALUATED_TIME) -> list[tuple[str, str]]:
    """The (space, time) resolutions of a data set: those that its own can be brought to."""
    reach = reachable(spec.native_time)
    return [(s, t) for s in spaces if s == "world" or s in spec.space for t in times if t in reach]


def observe(spec: DatasetSpec, resolutions: list[tuple[str, str]]) -> tuple[DataFrame, str]:
    """One scan of the raw rows: what all functions at these resolutions are made of, and its step.

    A row for each data set, place (at every resolution of space), step and kind: partial sums of
    tuples (kind ``''``), or one identifier that occurs there (kind: its column). The step is the
    coarsest from which all wanted ones follow.
    """
    times = {t for _, t in resolutions}
    base = next(t for t in reversed(list(TIME_DAG)) if times <= reachable(t) and t in reachable(spec.native_time))
    places = [F.col(spec.space[s]).cast("string").alias(f"at_{s}") for s in dict.fromkeys(s for s, _ in resolutions) if s != "world"]
    names = F.explode(spec.parts if spec.parts is not None else F.array(F.lit(spec.name)))
    rows = spec.df.select(names.alias("dataset"), *places, to_step(F.col(spec.time), base).alias("t"), *spec.ids, *spec.attrs).where("t IS NOT NULL")
    kinds = F.array(F.struct(F.lit("").alias("kind"), F.lit(None).cast("string").alias("id")), *[F.struct(F.lit(c).alias("kind"), F.col(c).cast("string").alias("id")) for c in spec.ids])
    rows = rows.select("*", F.explode(kinds).alias("__as")).where("__as.kind = '' OR __as.id IS NOT NULL")
    unit = 10 ** (spec.decimals or 0)
    total = (lambda c: F.sum(F.round(c * unit).cast("long"))) if spec.decimals is not None else F.sum
    own = lambda c: F.when(F.col("__as.kind") == "", F.col(c))
    seen = rows.groupBy("dataset", *[f"at_{s}" for s in dict.fromkeys(s for s, _ in resolutions) if s != "world"], "t", "__as.kind", "__as.id").agg(
        F.count(F.lit(1)).alias("n"), *[x for c in spec.attrs for x in (F.count(own(c)).alias(f"cnt_{c}"), total(own(c)).alias(f"sum_{c}"))]
    )
    return materialize(seen, "observed"), base


def from_observed(seen: DataFrame, base: str, spec: DatasetSpec, resolutions: list[tuple[str, str]]) -> DataFrame:
    """All functions at all given resolutions, in one pass over ``observe``'s rows.

    Every row goes to each resolution; counts and sums of places and steps are pre-aggregated before
    they are shuffled, identifiers are counted once a point.
    """
    place = lambda s: F.lit("0") if s == "world" else F.col(f"at_{s}")
    at = F.explode(F.array(*[F.struct(F.lit(s).alias("space_res"), F.lit(t).alias("time_res"), place(s).alias("region"), coarser(F.col("t"), base, t).cast("int").alias("t")) for s, t in resolutions]))
    head = ["space_res", "time_res", "region", "t"]
    sums = [c for c in seen.columns if c.startswith(("cnt_", "sum_"))]
    rows = seen.select("dataset", "kind", "id", "n", *sums, at.alias("x")).select("dataset", "kind", "id", "n", *sums, "x.*").where("region IS NOT NULL")
    unit = 10 ** (spec.decimals or 0)
    tuples = rows.where("kind = ''").groupBy("dataset", *head).agg(F.sum("n").alias("n"), *[F.sum(c).alias(c) for c in sums])
    values = [F.struct(F.lit("density").alias("m"), F.col("n").cast("double").alias("value"))]
    values += [F.struct(F.lit(f"avg({c})").alias("m"), (F.col(f"sum_{c}") / F.col(f"cnt_{c}") / unit).alias("value")) for c in spec.attrs]
    name = F.concat("dataset", F.lit("."), "m").alias("function_id")
    out = tuples.select("dataset", *head, F.explode(F.array(*values)).alias("v")).select("dataset", *head, "v.*").select(name, *head, "value")
    if spec.ids:
        unique = rows.where("kind <> ''").groupBy("dataset", *head, "kind", "id").agg(F.lit(1).alias("one")).groupBy("dataset", *head, "kind").agg(F.count(F.lit(1)).cast("double").alias("value"))
        out = out.unionByName(unique.withColumn("m", F.concat(F.lit("unique("), "kind", F.lit(")"))).select(name, *head, "value"))
    return out


def all_functions(specs: Iterable[DatasetSpec], spaces: Iterable[str] = EVALUATED_SPACE, times: Iterable[str] = EVALUATED_TIME, missing: str = "carry") -> DataFrame:
    """Every function of every data set at every viable resolution, on dense grids; one scan a table."""
    out = None
    for s in specs:
        found = viable(s, tuple(spaces), tuple(times))
        if found:
            fn = from_observed(*observe(s, found), s, found)
            out = fn if out is None else out.unionByName(fn)
    if out is None:
        raise ValueError("no data set has a viable resolution among the given ones")
    return densify(out.select(*KEYS, "value"), missing)


def densify(fn: DataFrame, missing: str = "carry") -> DataFrame:
    """A value for every region and every step in a function's range.

    Counts are 0 where there was no tuple. For other functions ``missing`` decides: ``drop`` leaves
    the point out, ``zero``, ``carry`` (last value of the region, before the first: the next one),
    ``mean`` (of the region) or ``linear`` (between the neighbours in time). Null values count as
    no tuple.
    """
    fn = fn.where("value IS NOT NULL")
    head = ["function_id", "space_res", "time_res"]
    spans = fn.groupBy(*head).agg(F.min("t").alias("lo"), F.max("t").alias("hi"))
    grid = fn.select(*head, "region").distinct().join(spans, head).select(*head, "region", F.explode(F.sequence("lo", "hi")).alias("t"))
    full = grid.join(fn, KEYS, "left")
    count = F.col("function_id").rlike("\\.(density|unique)")
    by = Window.partitionBy(*head, "region").orderBy("t")
    before = F.last("value", True).over(by.rowsBetween(Window.unboundedPreceding, 0))
    after = F.first("value", True).over(by.rowsBetween(0, Window.unboundedFollowing))
    if missing == "drop":
        return full.withColumn("value", F.when(count, F.coalesce("value", F.lit(0.0))).otherwise(F.col("value"))).where("value IS NOT NULL")
    if missing == "linear":
        has = F.when(F.col("value").isNotNull(), F.col("t"))
        t0, t1 = F.last(has, True).over(by.rowsBetween(Window.unboundedPreceding, 0)), F.first(has, True).over(by.rowsBetween(0, Window.unboundedFollowing))
        fill = F.when(t1 == t0, before).otherwise(F.coalesce(before + (after - before) * (F.col("t") - t0) / (t1 - t0), before, after))
    else:
        fill = {"zero": lambda: F.lit(0.0), "carry": lambda: F.coalesce(before, after), "mean": lambda: F.avg("value").over(Window.partitionBy(*head, "region"))}[missing]()
    return full.withColumn("value", F.when(F.col("value").isNotNull(), F.col("value")).when(count, F.lit(0.0)).otherwise(fill)).select(*KEYS, "value")


def gradient(fn: DataFrame, adjacency: DataFrame | None = None, how: str = "max") -> DataFrame:
    """The largest (or mean) change from a point to its neighbours in time and, if given, in space."""
    by = Window.partitionBy("function_id", "space_res", "time_res", "region").orderBy("t")
    near = fn.select(
        *KEYS,
        F.when(F.lag("t").over(by) == F.col("t") - 1, F.abs(F.col("value") - F.lag("value").over(by))).alias("before"),
        F.when(F.lead("t").over(by) == F.col("t") + 1, F.abs(F.col("value") - F.lead("value").over(by))).alias("after"),
    )
    near = near.select(*KEYS, F.explode(F.array("before", "after")).alias("d"))
    if adjacency is not None:
        pairs = fn.join(adjacency.withColumnRenamed("a", "region"), "region")
        other = fn.select("function_id", "space_res", "time_res", F.col("region").alias("b"), "t", F.col("value").alias("near"))
        near = near.unionByName(pairs.join(other, ["function_id", "space_res", "time_res", "b", "t"]).select(*KEYS, F.abs(F.col("value") - F.col("near")).alias("d")))
    agg = {"max": F.max, "mean": F.avg}[how]
    return near.groupBy(*KEYS).agg(F.coalesce(agg("d"), F.lit(0.0)).alias("value")).withColumn("function_id", F.concat(F.lit("gradient "), "function_id"))


def stored_bytes(df: DataFrame) -> int:
    """Bytes of the files of a stored table (as ``materialize`` or a reader gave it)."""
    jvm, conf = df.sparkSession.sparkContext._jvm, df.sparkSession.sparkContext._jsc.hadoopConfiguration()
    paths = [jvm.org.apache.hadoop.fs.Path(f) for f in df.inputFiles()]
    return sum(p.getFileSystem(conf).getFileStatus(p).getLen() for p in paths)


def footprint(fn: DataFrame, bytes_a_value: int = 4) -> DataFrame:
    """Values and bytes of every function."""
    return fn.groupBy("function_id", "space_res", "time_res").agg(F.count(F.lit(1)).alias("n_values")).withColumn("n_bytes", F.col("n_values") * bytes_a_value)
