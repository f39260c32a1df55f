"""Site-relative line frequency: lines that stand on too large a share of a host's pages go.

A host's total is the number of its different page texts; a line's count is the number of those
texts that contain it. Copies of a page thus vote once: a mirrored page is no boilerplate. A line
is dropped from every page of the host if count / total exceeds ``ratio`` and count is at least
``min_pages``.

Lines are compared without surrounding blanks; empty lines always stay. Null texts stay null and
are no page. A null host is a host of its own. Counts are pre-aggregated before they are shuffled,
and a host has at most (lines a page) / ratio boilerplate lines, whatever its number of pages.
Columns other than text pass unchanged, but an input's own n_lines and n_dropped are replaced. Rows
that repeat lose the same lines. An empty table gives no row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from strel.runtime import materialize

RATIO = 0.05
MIN_PAGES = 3
#: Boilerplate lines (8 bytes each) that may be sent to every executor; more are shuffled.
BROADCAST_LINES = 2_000_000
#: Pages of a host that meet its lines in one task, where both are shuffled.
PAGES_A_TASK = 100_000


def _key(line: Column) -> Column:
    return F.trim(line, F.lit(" \t\r"))


def boilerplate(docs: DataFrame, host_col: str = "source", text_col: str = "text", ratio: float = RATIO, min_pages: int = MIN_PAGES) -> DataFrame:
    """host and ``lines``, the 64-bit hashes of its boilerplate lines."""
    pages = docs.where(F.col(text_col).isNotNull()).select(F.col(host_col).cast("string").alias("host"), F.xxhash64(text_col).alias("page"), F.split(text_col, "\n").alias("ls"))
    totals = pages.groupBy("host", "page").agg(F.lit(1).alias("one")).groupBy("host").agg(F.count(F.lit(1)).alias("total"))
    keys = F.array_distinct(F.transform(F.filter("ls", lambda x: _key(x) != ""), lambda x: F.xxhash64(_key(x))))
    counts = (
        pages.select("host", "page", F.explode(keys).alias("line"))
        .groupBy("host", "line", "page").agg(F.lit(1).alias("one"))
        .groupBy("host", "line").agg(F.count(F.lit(1)).alias("n"))
        .where(F.col("n") >= min_pages)
    )
    often = counts.join(totals, counts["host"].eqNullSafe(totals["host"])).where(F.col("n") > ratio * F.col("total"))
    return often.groupBy(counts["host"].alias("host")).agg(F.collect_list("line").alias("lines"))


def drop_boilerplate(docs: DataFrame, host_col: str = "source", text_col: str = "text", ratio: float = RATIO, min_pages: int = MIN_PAGES) -> DataFrame:
    """``docs`` with boilerplate lines removed from the text; adds n_lines and n_dropped."""
    bad = materialize(boilerplate(docs, host_col, text_col, ratio, min_pages).select(F.col("host").alias("__host"), F.col("lines").alias("__lines")), "boilerplate")
    size = bad.agg(F.coalesce(F.sum(F.size("__lines")), F.lit(0))).first()[0]
    host = docs[host_col].cast("string")
    if size <= BROADCAST_LINES:
        joined = docs.join(F.broadcast(bad), host.eqNullSafe(bad["__host"]), "left")
    else:  # the pages of a large host are dealt to several tasks, each with a copy of its lines
        parts = docs.groupBy(host.alias("__of")).agg(F.ceil(F.count(F.lit(1)) / PAGES_A_TASK).cast("int").alias("__parts")).where("__parts > 1")
        parts = materialize(parts, "large-hosts")  # at most one for PAGES_A_TASK rows
        n = F.coalesce("__parts", F.lit(1))
        spread = docs.join(F.broadcast(parts), host.eqNullSafe(parts["__of"]), "left").withColumn("__part", F.pmod(F.xxhash64(text_col), n)).drop("__of", "__parts")
        copies = bad.join(F.broadcast(parts), bad["__host"].eqNullSafe(parts["__of"]), "left").withColumn("__copy", F.explode(F.sequence(F.lit(0), n - 1))).drop("__of", "__parts")
        joined = spread.join(copies, spread[host_col].cast("string").eqNullSafe(copies["__host"]) & (spread["__part"] == copies["__copy"]), "left").drop("__part", "__copy")
    ls = F.split(F.col(text_col), "\n")
    kept = F.when(F.col("__lines").isNull(), ls).otherwise(F.filter(ls, lambda x: (_key(x) == "") | ~F.array_contains(F.col("__lines"), F.xxhash64(_key(x)))))
    out = joined.withColumn("__kept", kept).withColumn("n_lines", F.coalesce(F.size(F.when(F.col(text_col).isNotNull(), ls)), F.lit(0)))
    out = out.withColumn("n_lines", F.greatest("n_lines", F.lit(0))).withColumn("n_dropped", F.when(F.col(text_col).isNull(), 0).otherwise(F.col("n_lines") - F.size("__kept")))
    return out.withColumn(text_col, F.when(F.col(text_col).isNotNull(), F.array_join("__kept", "\n"))).drop("__host", "__lines", "__kept")


ORACLE = r"""
WITH p AS (SELECT doc_id, source, text, string_split(text, chr(10)) AS ls FROM documents),
t AS (SELECT source, count(DISTINCT text) AS total FROM p GROUP BY source),
l AS (SELECT source, text, trim(unnest(ls), ' ' || chr(9) || chr(13)) AS line FROM p),
c AS (SELECT source, line, count(DISTINCT text) AS n FROM l WHERE line <> '' GROUP BY ALL),
b AS (SELECT c.source, list(c.line) AS bad FROM c JOIN t ON c.source IS NOT DISTINCT FROM t.source WHERE n >= 3 AND n > 0.05 * total GROUP BY c.source),
k AS (SELECT p.doc_id, p.source, p.text, p.ls, list_filter(p.ls, lambda x: NOT list_contains(coalesce(b.bad, []), trim(x, ' ' || chr(9) || chr(13)))) AS kept
      FROM p LEFT JOIN b ON p.source IS NOT DISTINCT FROM b.source)
SELECT doc_id, source, CASE WHEN text IS NOT NULL THEN array_to_string(kept, chr(10)) END AS text,
       CAST(coalesce(len(ls), 0) AS INTEGER) AS n_lines, CAST(coalesce(len(ls) - len(kept), 0) AS INTEGER) AS n_dropped
FROM k
"""
