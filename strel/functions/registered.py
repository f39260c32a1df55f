"""Functions for SQL: polygons, custom aggregates, merge trees, stored relationships."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strel.runtime import ship


def inside(x: pd.Series, y: pd.Series, xs: pd.Series, ys: pd.Series) -> pd.Series:
    """Whether a point lies in a polygon given by the arrays of its corners."""
    out = []
    for a, b, px, py in zip(x, y, xs, ys, strict=True):
        n, hit = len(px), False
        for i in range(n):
            x1, y1, x2, y2 = px[i], py[i], px[i - 1], py[i - 1]
            if (y1 > b) != (y2 > b) and a < (x2 - x1) * (b - y1) / (y2 - y1) + x1:
                hit = not hit
        out.append(hit)
    return pd.Series(out)


def trimmed_mean(v: pd.Series) -> float:
    """A custom aggregate: the mean without the lowest and the highest tenth."""
    v = v.dropna().sort_values()
    k = len(v) // 10
    return float(v.iloc[k : len(v) - k].mean()) if len(v) else float("nan")


class PersistenceOf:
    """``TABLE(f) PARTITION BY function_id``: pairs of a function of time with columns t and value."""

    def __init__(self):
        self.rows: list[tuple[int, float]] = []

    def eval(self, row):
        self.rows.append((int(row["t"]), float(row["value"])))

    def terminate(self):
        import numpy as np

        from strel.operators.topology import Sweep

        if self.rows:
            t, v = (np.array(x) for x in zip(*sorted(self.rows), strict=True))
            for side, sign in (("join", 1), ("split", -1)):
                for a, b, _ in Sweep(v * sign, t, np.zeros(len(t), int).astype(str)).pairs:
                    yield side, int(t[a]), float(v[a]), float(v[b])


def register_all(spark: SparkSession, relationships: DataFrame | None = None) -> None:
    """Registers the functions; with stored relationships also ``related(dataset, min_score)``."""
    ship(spark)
    spark.udf.register("inside", F.pandas_udf(inside, "boolean"))
    spark.udf.register("trimmed_mean", F.pandas_udf(trimmed_mean, "double"))
    spark.udtf.register("persistence_of", F.udtf(PersistenceOf, returnType="side string, creator_t int, birth double, death double"))
    if relationships is not None:
        relationships.createOrReplaceTempView("strel_relationships")
        spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION related(ds STRING, min_score DOUBLE)
          RETURNS TABLE (left_fn STRING, right_fn STRING, feature_type STRING, score DOUBLE, strength DOUBLE, p_value DOUBLE)
          RETURN SELECT left_fn, right_fn, feature_type, score, strength, p_value FROM strel_relationships
          WHERE (left_dataset = related.ds OR right_dataset = related.ds) AND abs(score) >= related.min_score""")
