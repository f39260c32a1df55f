"""Data sets: tables with declared roles of their columns."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from strel.operators import space
from strel.runtime import ranked, table

#: Spatial resolutions from fine to coarse, and what each may be rolled up to.
SPACE_DAG = {"point": ("cell", "nation", "segment"), "cell": ("world",), "nation": ("region", "world"), "region": ("world",), "segment": ("world",), "world": ()}


@dataclass(frozen=True)
class DatasetSpec:
    """A table and the roles of its columns: identifiers, space, time, numeric attributes.

    ``space`` maps a spatial resolution to the column that holds its region; every data set has the
    one-region resolution ``world``.
    """

    name: str
    df: DataFrame
    time: str
    native_time: str
    ids: tuple[str, ...] = ()
    space: dict[str, str] = field(default_factory=dict)
    attrs: tuple[str, ...] = ()
    #: Decimal places of attributes: sums are then exact and do not depend on the order of rows.
    decimals: int | None = 2
    #: Names of the data sets that a row belongs to (an array column); none: ``name`` alone.
    parts: Column | None = None

    def family(self, name: str, *parts: Column) -> DatasetSpec:
        """Several data sets read in one scan: each row belongs to those that ``parts`` name (not to null ones)."""
        return replace(self, name=name, parts=F.filter(F.array(*parts), lambda x: x.isNotNull()))

    def where(self, name: str, condition: str) -> DatasetSpec:
        """A part of the table as a data set of its own."""
        return replace(self, name=name, df=self.df.where(condition))


class NoTimeAxis(ValueError):
    """The table has no column that can serve as time."""


def infer_roles(df: DataFrame) -> dict[str, list[str]]:
    """Roles that column types and names suggest: a proposal for a declared spec."""
    roles: dict[str, list[str]] = {"time": [], "ids": [], "attrs": []}
    for f in df.schema.fields:
        if isinstance(f.dataType, T.TimestampType | T.TimestampNTZType | T.DateType):
            roles["time"].append(f.name)
        elif f.name.endswith(("key", "_id")):
            roles["ids"].append(f.name)
        elif isinstance(f.dataType, T.NumericType):
            roles["attrs"].append(f.name)
    if not roles["time"]:
        raise NoTimeAxis(f"no time column among {df.columns}; declare an ordinal axis instead")
    return roles


def encode_category(df: DataFrame, col: str, to: str | None = None) -> DataFrame:
    """Adds the rank of a categorical column among its values, from 0.

    The distinct values are ranked by ranges, so no task holds all of them. They are counted before
    they are sent to executors; very many are joined by a shuffle.
    """
    # nulls take part as the lowest value
    codes = ranked(df.select(F.col(col).alias("__value")).distinct(), [F.col("__value").asc_nulls_first()], "__code", "categories").withColumn("__code", F.col("__code").cast("int"))
    small = codes.limit(100_001).count() <= 100_000
    joined = df.join(F.broadcast(codes) if small else codes, F.col(col).eqNullSafe(F.col("__value")), "left")
    return joined.withColumn(to or f"{col}_code", F.col("__code")).drop("__value", "__code")


def orders(spark: SparkSession, sf: str) -> DatasetSpec:
    place = table(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    rows = table(spark, sf, "orders").select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority")
    df = rows.join(place, rows["o_custkey"] == place["c_custkey"], "left").withColumn("c_regionkey", F.expr("c_nationkey % 5"))
    return DatasetSpec("orders", df, "o_orderdate", "day", ("o_custkey",), {"nation": "c_nationkey", "region": "c_regionkey", "segment": "c_mktsegment"}, ("o_totalprice",))


def lineitem(spark: SparkSession, sf: str) -> DatasetSpec:
    place = table(spark, sf, "supplier").select("s_suppkey", "s_nationkey")
    rows = table(spark, sf, "lineitem")
    df = rows.join(place, rows["l_suppkey"] == place["s_suppkey"], "left").withColumn("s_regionkey", F.expr("s_nationkey % 5"))
    return DatasetSpec("lineitem", df, "l_shipdate", "day", ("l_suppkey", "l_partkey"), {"nation": "s_nationkey", "region": "s_regionkey"}, ("l_quantity", "l_extendedprice", "l_discount", "l_tax"))


def events(spark: SparkSession, sf: str) -> DatasetSpec:
    place = table(spark, sf, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    rows = table(spark, sf, "events").withColumn("k", F.get_json_object("props", "$.k").cast("double"))
    df = rows.join(place, rows["user_id"] == place["c_custkey"], "left").withColumn("c_regionkey", F.expr("c_nationkey % 5"))
    return DatasetSpec("events", df, "ts", "second", ("user_id",), {"nation": "c_nationkey", "region": "c_regionkey", "segment": "c_mktsegment"}, ("value", "k"))


def corpus(spark: SparkSession, sf: str, parts: bool = True) -> list[DatasetSpec]:
    """Orders and lineitem, and (``parts``) their splits by status and return flag."""
    o, li = orders(spark, sf), lineitem(spark, sf)
    out = [o, li]
    if parts:
        out += [o.where(f"orders_{s}", f"o_orderstatus = '{s}'") for s in ("F", "O", "P")]
        out += [li.where(f"lineitem_{s}", f"l_returnflag = '{s}'") for s in ("A", "N", "R")]
    return out


def splits(spark: SparkSession, sf: str) -> list[DatasetSpec]:
    """Orders by status and lineitem by return flag, each table read once."""
    return [orders(spark, sf).family("orders", F.concat(F.lit("orders_"), "o_orderstatus")), lineitem(spark, sf).family("lineitem", F.concat(F.lit("lineitem_"), "l_returnflag"))]


def whole_and_parts(spark: SparkSession, sf: str) -> list[DatasetSpec]:
    """Orders, lineitem and events, and their parts by status, flag and type: 14 data sets in three scans."""
    return [
        orders(spark, sf).family("orders", F.lit("orders"), F.concat(F.lit("orders_"), "o_orderstatus")),
        lineitem(spark, sf).family("lineitem", F.lit("lineitem"), F.concat(F.lit("lineitem_"), "l_returnflag")),
        events(spark, sf).family("events", F.lit("events"), F.concat(F.lit("events_"), "event_type")),
    ]


def many(spark: SparkSession, sf: str, suppliers: int = 34) -> list[DatasetSpec]:
    """A corpus of 302 small data sets cut from the given tables, in three scans."""
    o, li, ev = orders(spark, sf), lineitem(spark, sf), events(spark, sf)
    return [
        li.family("lineitem", F.concat(F.lit("lineitem_"), (F.col("l_suppkey") % suppliers).cast("string"), F.lit("_"), "l_returnflag")),
        o.family("orders", F.concat(F.lit("orders_"), "c_mktsegment", F.lit("_"), F.substring("o_orderpriority", 1, 1), F.lit("_"), "o_orderstatus")),
        ev.family("events", F.concat(F.lit("events_"), "event_type", F.lit("_"), (F.col("user_id") % 25).cast("string"))),
    ]


def space_maps(spark: SparkSession, sf: str) -> dict[str, DataFrame]:
    """Adjacency of the resolutions that have more than one region: nations on a lattice, regions as
    its quotient, segments on a path."""
    nations = space.lattice(spark, 5, 5)
    up = table(spark, sf, "nation").select(F.col("n_nationkey").cast("string").alias("region"), F.col("n_regionkey").cast("string").alias("to_region"))
    names = table(spark, sf, "customer").select(F.col("c_mktsegment").alias("s")).distinct()
    path = names.withColumn("next", F.lead("s").over(Window.orderBy("s"))).where("next IS NOT NULL")  # a handful of segments
    segments = path.select(F.col("s").alias("a"), F.col("next").alias("b")).unionByName(path.select(F.col("next").alias("a"), F.col("s").alias("b")))
    return {"nation": nations, "region": space.quotient(nations, up), "segment": segments}
