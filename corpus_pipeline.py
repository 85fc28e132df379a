"""From raw documents to packed training sequences: five stages, each written as Parquet and read again by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tempcorr.llm import op2_packing, op4_substring, op7_neardup, op9_decontamination, op10_language
from tempcorr.llm.common import written

#: No SQL: language models and the packing of token ids are not expressible.
ORACLE_SQL = None


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can be told; the rejected ones go."""
    return op10_language.accepted(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: shingles of five words, a similarity of 0.8.

    Of rows with one doc_id and one text one stays; rows of one doc_id with other texts are documents of their own,
    and rows without a doc_id stay.
    """
    found = written(op7_neardup.near_duplicates(docs, size=5, similar=80).where("kept").groupBy("doc_id", F.col("text_key").alias("_text_key")).agg(F.count("*").alias("_rows")), "pipeline-kept")
    named = docs.withColumn("_text_key", F.xxhash64(F.col("text").cast("string")))
    once = named.join(found.where("_rows = 1"), ["doc_id", "_text_key"], "left_semi").select(*docs.columns)
    again = named.join(found.where("_rows > 1"), ["doc_id", "_text_key"], "left_semi").dropDuplicates(["doc_id", "_text_key"]).select(*docs.columns)
    return once.unionByName(again).unionByName(docs.where("doc_id is null"))


def substrings(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without the passages that earlier documents have."""
    return op4_substring.without_passages(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no benchmark item contaminates."""
    return op9_decontamination.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences of 2,048 tokens."""
    return op2_packing.pack(docs)


STAGES = [("language", language), ("near_duplicates", near_duplicates), ("substrings", substrings), ("decontamination", decontamination), ("packing", packing)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
