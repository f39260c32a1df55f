"""The registered queries of the operators in this subpackage, over their whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from strel.llm import decontam, lengths, licences, linedup, packing, paritysketch, pii, quality, toxicity, vptree
from strel.runtime import table


def _fold(parts: int) -> Column:
    """The rest of a document's id, by which label folds are told apart."""
    return F.crc32(F.col("doc_id").cast("string")) % parts


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    grammar = toxicity.fit(docs, table(spark, sf_dir, "labels").where(_fold(5) != 0))
    scored = toxicity.score(docs, grammar)
    return scored.select("doc_id", (_fold(5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = quality.describe(table(spark, sf_dir, "documents").select("doc_id", "text"))
    model = quality.fit(docs, table(spark, sf_dir, "labels").where(_fold(3) != 1))
    scored = quality.score(docs, model)
    return scored.select("doc_id", (_fold(3) == 1).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op4_private_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find(table(spark, sf_dir, "documents"))


def op5_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licences.scan(table(spark, sf_dir, "documents"))


def op6_token_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lengths.length_histogram(lengths.token_lengths(table(spark, sf_dir, "documents")))


def op7_parity_sketch_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return paritysketch.near_duplicates(table(spark, sf_dir, "documents"))


def op8_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contained(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op9_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return vptree.nearest(vectors, vectors.where("vec_id % 20 = 0"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    return linedup.drop_boilerplate(docs)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    every = (
        op1_packing, op2_toxicity, op3_quality, op4_private_data, op5_licence_scan, op6_token_lengths, op7_parity_sketch_join,
        op8_decontamination, op9_nearest, op10_line_dedup,
    )
    return {f.__name__: f for f in every}


def oracle_sql() -> dict[str, str]:
    return {"op8_decontamination": decontam.ORACLE, "op10_line_dedup": linedup.ORACLE}
