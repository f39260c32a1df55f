"""A corpus pipeline of five stages of ``strel.llm``.

Every stage takes (spark, docs, sf_dir) and works on all its predecessor kept; all but the last
return the columns of ``documents`` (others are dropped). No stage needs ids: rows with null or
repeated ids are judged by their own text. Null and empty texts are clean and pass, each as its own
document; rows that repeat a text are one group of near duplicates. Empty tables give empty results.
"""

from __future__ import annotations

import functools
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from strel.llm import decontam, linedup, packing, paritysketch, toxicity
from strel.runtime import give_back, materialize, shared_dir, table

#: Scores and trained models are not SQL.
ORACLE_SQL = None
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity grammar scores 0.5 or more go; the grammar learns from all labels."""
    grammar = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    return toxicity.score(docs, grammar, tuple(COLUMNS)).where("score < 0.5").select(*COLUMNS)


def drop_site_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Boilerplate lines of a source go from its documents; the documents stay."""
    return linedup.drop_boilerplate(docs).withColumn("n_chars", F.coalesce(F.length("text").cast("long"), F.col("n_chars"))).select(*COLUMNS)


def keep_one_of_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near duplicates one row stays, that of the smallest id; null ids come last.

    Rows are told apart by numbers of their own, so null and repeated ids neither lose nor hide a row.
    """
    rows = materialize(docs.withColumn("__row", F.monotonically_increasing_id()), "rows")
    classes = paritysketch.near_duplicates(rows.select(F.col("__row").alias("doc_id"), "text"))
    ids = rows.select("__row", F.col("doc_id").isNull().alias("none"), "doc_id")
    first = classes.select(F.col("doc_id").alias("__row"), "component_id").join(ids, "__row").groupBy("component_id").agg(F.min(F.struct("none", "doc_id", "__row")).alias("kept"))
    return rows.join(first.select("kept.__row"), "__row", "left_semi").select(*COLUMNS)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return decontam.clean(docs, table(spark, sf_dir, "benchmark")).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token sequences of what is left."""
    return packing.pack(docs)


def _fresh(stage: Callable) -> Callable:
    """The stage, begun with heaps that do not hold what earlier ones left in them."""

    @functools.wraps(stage)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        give_back(spark)
        return stage(spark, docs, sf_dir)

    return run_stage


STAGES = [
    ("toxicity", reject_toxic),
    ("line_dedup", _fresh(drop_site_lines)),
    ("near_duplicates", _fresh(keep_one_of_near_duplicates)),
    ("decontamination", _fresh(decontaminate)),
    ("packing", _fresh(pack)),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to ``documents``; between stages the rows are stored and read again."""
    docs = table(spark, sf_dir, "documents")
    base = f"{shared_dir(spark)}/strel/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:  # it has read its input: what it returns is stored
            path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(base)
            path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
            return out
        out.write.mode("overwrite").parquet(f"{base}/{k}-{name}")
        docs = spark.read.parquet(f"{base}/{k}-{name}")
    return docs
