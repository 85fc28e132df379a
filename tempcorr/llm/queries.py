"""The operators' queries over whole tables, and SQL for those that SQL can express."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tempcorr.llm import op1_html, op2_packing, op3_suffix, op4_substring, op5_warc, op6_quality, op7_neardup, op8_scoring, op9_decontamination, op10_language
from tempcorr.llm.common import documents
from tempcorr.llm.oracles import ORACLES


def html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op1_html.extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op2_packing.pack(documents(spark, sf_dir))


def suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op3_suffix.dedup(documents(spark, sf_dir)).drop("kept")


def substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op4_substring.dedup(documents(spark, sf_dir)).drop("kept_text")


def warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op5_warc.archive(spark.read.parquet(f"{sf_dir}/pages.parquet")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "urlkey", "captured")


def quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op6_quality.clean(documents(spark, sf_dir)).drop("kept_text")


def neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op7_neardup.near_duplicates(documents(spark, sf_dir)).drop("text_key")


def scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op8_scoring.score(documents(spark, sf_dir))


def decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op9_decontamination.judge(op9_decontamination.find(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))).drop("text_key")


def language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return op10_language.identify(docs).select("doc_id", op10_language.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def queries() -> dict:
    return {
        "op1_html_extraction": html_extraction,
        "op2_packing": packing,
        "op3_suffix_dedup": suffix_dedup,
        "op4_substring_dedup": substring_dedup,
        "op5_warc": warc,
        "op6_quality": quality,
        "op7_neardup": neardup,
        "op8_lm_scoring": scoring,
        "op9_decontamination": decontamination,
        "op10_language": language,
    }


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
