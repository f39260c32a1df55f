"""Integer time steps and seasons."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Temporal resolutions from fine to coarse, and what each may be rolled up to. A week lies in the
#: month of its Monday, which loses the exact border: that edge is lossy.
TIME_DAG = {"second": ("hour",), "hour": ("day",), "day": ("week", "month"), "week": (), "month": ("quarter",), "quarter": (), "ordinal": ()}
LOSSY = {("week", "month")}


def to_step(ts: Column, time_res: str) -> Column:
    """Number of whole steps from 1970 (weeks: from Monday 1970-01-05), for a timestamp without zone."""
    day = F.datediff(F.to_date(ts), F.lit("1970-01-01").cast("date"))
    return {
        "second": lambda: (day.cast("long") * 86400 + F.hour(ts) * 3600 + F.minute(ts) * 60 + F.second(ts).cast("int")).cast("long"),
        "hour": lambda: day * 24 + F.hour(ts),
        "day": lambda: day,
        "week": lambda: F.floor((day - 4) / 7).cast("int"),
        "month": lambda: (F.year(ts) - 1970) * 12 + F.month(ts) - 1,
        "ordinal": lambda: ts.cast("int"),  # a declared integer axis of a table without time
        "quarter": lambda: (F.year(ts) - 1970) * 4 + F.quarter(ts) - 1,
    }[time_res]()


def coarser(t: Column, source: str, target: str) -> Column:
    """The step of ``target`` that holds step ``t`` of ``source``."""
    if source == target:
        return t
    if source == "hour":
        return coarser(F.floor(t / 24).cast("int"), "day", target)
    if source == "month":
        return F.floor(t / 3).cast("int")
    day = t if source == "day" else t * 7 + 4
    date = F.date_add(F.lit("1970-01-01").cast("date"), day)
    return to_step(date, target)


def season_of(t: Column, time_res: str) -> Column:
    """The interval that has thresholds of its own: months of hours, quarters of days, else the whole."""
    if time_res == "hour":
        return coarser(t, "hour", "month")
    if time_res == "day":
        return coarser(t, "day", "quarter")
    return F.lit(0)


def reachable(time_res: str) -> set[str]:
    """Resolutions that steps of one can be brought to without loss, itself included."""
    return {time_res}.union(*(reachable(y) for y in TIME_DAG[time_res]))


def common_time(a: str, b: str) -> list[str]:
    """Resolutions that both can be brought to, the finest first."""
    order = list(TIME_DAG)
    return sorted(reachable(a) & reachable(b), key=order.index)
