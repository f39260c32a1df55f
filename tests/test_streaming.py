"""Live functions: windows, late rows, sketches, joins and incremental persistence."""

import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F

from strel.streaming import live

T0 = dt.datetime(2024, 1, 1)
SCHEMA = "event_id long, ts timestamp_ntz, user_id long, value double"


def stored(spark, folder, batches):
    """One file a batch, in order of time of writing."""
    import os
    import time

    folder.mkdir()
    for k, rows in enumerate(batches):
        spark.createDataFrame(rows, SCHEMA).coalesce(1).write.parquet(str(folder / f".b{k}"))
        part = next(p for p in (folder / f".b{k}").iterdir() if p.suffix == ".parquet")
        os.rename(part, folder / f"part-{k}.parquet")
        os.utime(folder / f"part-{k}.parquet", (time.time() + k, time.time() + k))
    return str(folder)


def row(i, minutes, user=0, value=0.0):
    return (i, T0 + dt.timedelta(minutes=minutes), user, value)


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    path = stored(spark, tmp_path / "in", [[row(1, 10), row(2, 20)], [row(3, 600)], [row(5, 610)], [row(4, 30)], [row(6, 900)]])
    out = live.drain(live.density(live.source(spark, path, 1)), "append")
    got = {r["w"]["start"].hour: r["value"] for r in out.collect()}
    assert got[0] == 2 and live.late_rows(out) == 1  # the row of minute 30 came after its hour had closed


def test_sliding_windows_and_unique_users(spark, tmp_path):
    path = stored(spark, tmp_path / "in", [[row(i, 7 * i, i % 5) for i in range(40)]])
    out = live.drain(live.density(live.source(spark, path), "2 hours", "1 hour"))
    minutes = [7 * i for i in range(40)]
    for r in out.collect():
        begin = (r["w"]["start"] - T0).total_seconds() / 60
        assert r["value"] == sum(begin <= m < begin + 120 for m in minutes)
    assert {r["value"] for r in live.drain(live.unique(live.source(spark, path))).collect()} == {5}


def test_two_streams_of_features_meet(spark, tmp_path):
    path = stored(spark, tmp_path / "in", [[row(i, 60 * (i // 2), i % 2, 1.0 if i % 3 else -1.0) for i in range(40)]])

    def side(user):
        e = live.source(spark, path).where(F.col("user_id") == user)
        return e.select("ts", (F.col("value") > 0).alias("pos"), (F.col("value") < 0).alias("neg"))

    r = live.running_relation(live.drain(live.related(side(0), side(1)), "append")).first()
    signs = [(1 if (2 * k) % 3 else -1, 1 if (2 * k + 1) % 3 else -1) for k in range(20)]
    same = sum(a == b for a, b in signs)
    assert (r["n_common"], r["n_pos"], r["n_neg"]) == (20, same, 20 - same) and r["score"] == pytest.approx((2 * same - 20) / 20)


def test_flags_come_out_of_the_stream(spark, tmp_path):
    path = stored(spark, tmp_path / "in", [[row(i, m) for i, m in enumerate([0, 1, 2, 3, 70, 130, 131, 600])]])
    th = spark.createDataFrame([(4.0, 1.0)], "up double, down double")
    out = live.drain(live.flags(live.density(live.source(spark, path)), th), "append")
    assert {(r["w"]["start"].hour, r["value"], r["pos"], r["neg"]) for r in out.collect()} == {(0, 4, True, False), (1, 1, False, True)}


def test_peaks_closed_so_far_are_those_of_the_whole_series(spark, tmp_path):
    from strel.operators.topology import Sweep

    v = np.random.default_rng(1).permutation(60).astype(float).tolist()
    path = stored(spark, tmp_path / "in", [[row(t, t, 0, v[t]) for t in range(a, a + 20)] for a in (0, 20, 40)])
    s = live.source(spark, path, 1).select(F.lit("a.f").alias("function_id"), F.col("event_id").alias("t"), "value")
    got = {(r["creator_t"], r["birth"], r["death"]) for r in live.drain(live.open_peaks(s), "append").collect()}
    pairs = {(int(a), v[a], v[b]) for a, b, e in Sweep(np.array(v), np.arange(60), np.zeros(60, int).astype(str)).pairs if not e}
    later = lambda t: any(v[k] > v[t] for k in range(t + 1, 60))
    assert {p for p in pairs if later(p[0])} == got
