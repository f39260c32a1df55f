"""Exact length histogram: counts of tokens for every context limit at once.

Texts are encoded once, and the histogram of their lengths is stored; a row is then one number. Documents are aggregated by encoded length, and
suffix sums over that histogram answer totals, quantiles and truncated totals for any limit
without another look at the texts.

Null texts count as empty (length 0). Repeated rows count as often as they stand. An empty table
gives an empty histogram. Columns but the id and the text are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from strel.llm.encode import blocks, each, encoder, tokenizer_path
from strel.runtime import materialize, ship

#: Lengths of one bucket of the two-level suffix sums.
BUCKET = 1024


def _count_task(path: str):
    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        enc = encoder(path)
        for b in batches:
            for keys, texts in blocks(each(b.column("doc_id")), each(b.column("text"))):
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(enc.counts(texts), pa.int64())], ["doc_id", "n_tokens"])

    return run


def token_lengths(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", tokenizer: str | None = None) -> DataFrame:
    """doc_id and n_tokens of every whole text."""
    ship(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(_count_task(tokenizer or tokenizer_path()), "doc_id long, n_tokens long")


def length_histogram(lengths: DataFrame) -> DataFrame:
    """Per length that occurs: documents, and the sums from that length up and over all.

    Columns: n_tokens, n_docs; docs_from and tokens_from (this length or longer); docs_upto and
    tokens_upto (this length or shorter); kept_tokens (tokens left when every text is cut to this
    length); quantile (share of documents at most this long).

    Suffix sums run in two levels, over buckets of lengths and inside a bucket, so that no task
    holds all lengths.
    """
    hist = materialize(lengths.groupBy("n_tokens").agg(F.count(F.lit(1)).alias("n_docs")), "lengths")  # read twice below
    hist = hist.withColumn("bucket", F.expr(f"n_tokens div {BUCKET}"))
    per = hist.groupBy("bucket").agg(F.sum("n_docs").alias("b_docs"), F.sum(F.col("n_docs") * F.col("n_tokens")).alias("b_tokens"))
    over = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    per = per.select(
        "bucket",
        F.coalesce(F.sum("b_docs").over(over), F.lit(0)).alias("docs_before"),
        F.coalesce(F.sum("b_tokens").over(over), F.lit(0)).alias("tokens_before"),
        F.sum("b_docs").over(every).alias("docs_all"),
        F.sum("b_tokens").over(every).alias("tokens_all"),
    )
    inside = Window.partitionBy("bucket").orderBy("n_tokens").rowsBetween(Window.unboundedPreceding, 0)
    upto = (
        hist.join(per, "bucket")
        .withColumn("docs_upto", F.col("docs_before") + F.sum("n_docs").over(inside))
        .withColumn("tokens_upto", F.col("tokens_before") + F.sum(F.col("n_docs") * F.col("n_tokens")).over(inside))
    )
    longer = F.col("docs_all") - F.col("docs_upto")
    return upto.select(
        "n_tokens",
        "n_docs",
        (longer + F.col("n_docs")).alias("docs_from"),
        (F.col("tokens_all") - F.col("tokens_upto") + F.col("n_docs") * F.col("n_tokens")).alias("tokens_from"),
        "docs_upto",
        "tokens_upto",
        (F.col("tokens_upto") + longer * F.col("n_tokens")).alias("kept_tokens"),
        (F.col("docs_upto") / F.col("docs_all")).alias("quantile"),
    )


def total_at(hist: DataFrame, limit: int) -> DataFrame:
    """Documents and tokens in all, and tokens left when every text is cut to ``limit``; one row."""
    below = F.col("n_tokens") <= F.lit(limit)
    return hist.agg(
        F.coalesce(F.sum("n_docs"), F.lit(0)).alias("n_docs"),
        F.coalesce(F.sum(F.col("n_docs") * F.col("n_tokens")), F.lit(0)).alias("n_tokens"),
        F.coalesce(F.sum(F.col("n_docs") * F.when(below, F.col("n_tokens")).otherwise(F.lit(limit))), F.lit(0)).alias("kept_tokens"),
    )


def length_quantile(hist: DataFrame, q: float) -> DataFrame:
    """The smallest length that at least a share ``q`` of the documents does not exceed; one row."""
    return hist.where(F.col("quantile") >= F.lit(q)).agg(F.min("n_tokens").alias("n_tokens"))
