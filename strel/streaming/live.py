"""Live functions and features of a stream of events.

Time of an event is its ``ts``; the source's timestamp without zone is read as UTC. Late rows are
dropped by the watermark; ``drain`` says how many.
"""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strel.runtime import shared_dir


def source(spark: SparkSession, path: str, per_trigger: int | None = None) -> DataFrame:
    """Events as a stream, from a folder of parquet files or one such file."""
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if per_trigger:
        reader = reader.option("maxFilesPerTrigger", per_trigger)
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(at).isFile():
        reader = reader.option("pathGlobFilter", at.getName())
        path = at.getParent().toString()
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def density(events: DataFrame, step: str = "1 hour", slide: str | None = None, late: str = "1 hour", keys: tuple[str, ...] = ()) -> DataFrame:
    """Counts by window (tumbling, or sliding by ``slide``) and keys."""
    w = F.window("ts", step, slide) if slide else F.window("ts", step)
    return events.withWatermark("ts", late).groupBy(w.alias("w"), *keys).agg(F.count(F.lit(1)).alias("value"))


def unique(events: DataFrame, col: str = "user_id", step: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Distinct ids by window, by a sketch whose state is bounded."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", step).alias("w")).agg(F.approx_count_distinct(col).alias("value"))


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events without repeats of an event_id inside the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def sessions(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """Sessions of a user: runs of events with no longer gap between them."""
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def flags(counts: DataFrame, thresholds: DataFrame) -> DataFrame:
    """Closed windows with the signs that stored thresholds (up, down: one row) give them.

    ``counts`` may be a stream: the thresholds are the static side of the join.
    """
    return counts.crossJoin(F.broadcast(thresholds.limit(1))).select("w", "value", (F.col("value") >= F.col("up")).alias("pos"), (F.col("value") <= F.col("down")).alias("neg")).where("pos OR neg")


def related(a: DataFrame, b: DataFrame, late: str = "1 hour") -> DataFrame:
    """Features of two live functions (ts, pos, neg) that meet at one step."""
    return met(a.withWatermark("ts", late), b.withWatermark("ts", late))


def met(a: DataFrame, b: DataFrame) -> DataFrame:
    """The same for streams that have their watermark: both times bound the state of the join."""
    x = a.select(F.col("ts").alias("t1"), F.col("pos").alias("p1"), F.col("neg").alias("n1"))
    y = b.select(F.col("ts").alias("t2"), F.col("pos").alias("p2"), F.col("neg").alias("n2"))
    return x.join(y, F.expr("t1 = t2"))


def running_relation(points: DataFrame) -> DataFrame:
    """Counts and score of all feature points that have met so far (update or complete mode)."""
    same, anti = F.expr("p1 AND p2 OR n1 AND n2").cast("int"), F.expr("p1 AND n2 OR n1 AND p2").cast("int")
    out = points.agg(F.count(F.lit(1)).alias("n_common"), F.sum(same).alias("n_pos"), F.sum(anti).alias("n_neg"))
    return out.withColumn("score", (F.col("n_pos") - F.col("n_neg")) / F.col("n_common"))


def open_peaks(series: DataFrame) -> DataFrame:
    """Persistence of a growing series, without a second look at it.

    State is the falling stack of peaks that are still open and the valleys between them. A value
    above an open peak closes it: its persistence is its height over the higher of its two valleys.
    ``series`` has function_id, t and value, in order of t inside a batch.
    """

    def step(key, pdfs, state):
        stack = list(zip(*state.get, strict=True)) if state.exists else []  # (peak, its time, valley after it)
        closed = []
        for pdf in pdfs:
            for t, v in pdf.sort_values("t")[["t", "value"]].itertuples(index=False):
                low = v
                while stack and stack[-1][0] < v:
                    peak, at, valley = stack.pop()
                    low = min(low, valley)
                    floor = max(valley, stack[-1][2]) if stack else valley
                    if peak > floor:
                        closed.append((key[0], int(at), float(peak), float(floor)))
                    if stack:
                        p, a, w = stack[-1]
                        stack[-1] = (p, a, min(w, valley))
                if stack and v < stack[-1][2]:
                    p, a, _ = stack[-1]
                    stack[-1] = (p, a, v)
                stack.append((v, t, v))
        state.update(tuple(map(list, zip(*stack, strict=True))) if stack else ([], [], []))
        yield pd.DataFrame(closed, columns=["function_id", "creator_t", "birth", "death"])

    return series.groupBy("function_id").applyInPandasWithState(step, "function_id string, creator_t long, birth double, death double", "peaks array<double>, times array<long>, valleys array<double>", "append", "NoTimeout")


def drain(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over what its source holds now and returns the stored result.

    In complete mode every batch replaces the result; in append mode batches add to it: only then
    are windows closed by the watermark, and rows behind it dropped.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/strel/stream-{uuid.uuid4().hex}"

    def store(df: DataFrame, epoch: int) -> None:
        df.write.mode("overwrite").parquet(f"{base}/out" if mode == "complete" else f"{base}/out/epoch={epoch}")

    q = stream.writeStream.outputMode(mode).foreachBatch(store).option("checkpointLocation", f"{base}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    late = sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
    out = spark.read.parquet(f"{base}/out").drop("epoch")
    out._strel_late = late
    return out


def late_rows(drained: DataFrame) -> int:
    """Rows that ``drain`` saw dropped for being late."""
    return drained._strel_late
