"""Tables in files: parquet, ORC, JSON lines and CSV, read with a declared schema and written by partition."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

FORMATS = ("parquet", "orc", "json", "csv")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | T.StructType | None = None) -> DataFrame:
    """A table from files. Text formats need a schema: inferring one would scan all rows beforehand."""
    if kind not in FORMATS:
        raise ValueError(f"{kind} is none of {FORMATS}")
    if kind in ("json", "csv") and schema is None:
        raise ValueError(f"{kind} files need a schema")
    reader = spark.read.format(kind)
    if schema is not None:
        reader = reader.schema(schema)
    if kind == "csv":
        reader = reader.option("header", True).option("mode", "FAILFAST")
    return reader.load(path)


def write(df: DataFrame, path: str, kind: str = "parquet", by: tuple[str, ...] = (), rows_a_file: int = 5_000_000) -> None:
    """Writes a table; with ``by`` one folder a value, rows of a value kept together before they are written."""
    if kind not in FORMATS:
        raise ValueError(f"{kind} is none of {FORMATS}")
    out = (df.repartition(*by) if by else df).write.mode("overwrite").format(kind).option("maxRecordsPerFile", rows_a_file)
    if kind == "csv":
        out = out.option("header", True)
    (out.partitionBy(*by) if by else out).save(path)
