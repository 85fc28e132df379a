"""The stages of the pipeline, one by one and together, against plain Python; rows without an id, repeated rows, other columns."""

import brute
import pytest
from pyspark.sql import functions as F

import corpus_pipeline as pipeline
from tempcorr.llm import op2_packing, op3_suffix, op4_substring, op6_quality, op7_neardup, op8_scoring, op9_decontamination, op10_language


def texts(df):
    return [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]


@pytest.fixture(scope="module")
def stages(spark, small):
    """What each stage gives on the smallest tables."""
    from tempcorr.llm.common import written

    docs = spark.read.parquet(f"{small}/documents.parquet")
    odd = docs.where("doc_id < 6").withColumn("doc_id", F.col("doc_id") + 10**6).withColumn("text", F.when(F.col("doc_id") == 10**6, F.lit(None)).when(F.col("doc_id") == 10**6 + 1, "").when(F.col("doc_id") == 10**6 + 2, " 12 \n").otherwise(F.col("text")))
    docs = docs.unionByName(odd).unionByName(docs.where("doc_id in (3, 7)"))
    out = [docs]
    for name, stage in pipeline.STAGES:
        out.append(written(stage(spark, out[-1], small), f"test-{name}"))
    return out


def test_language_stage(stages):
    kept, every = dict(texts(stages[1])), dict(texts(stages[0]))
    assert stages[1].columns == stages[0].columns and not {10**6, 10**6 + 1, 10**6 + 2} & set(kept)
    long = {d for d, t in every.items() if t and len(t) > 300}
    assert len(long & set(kept)) >= 0.97 * len(long)


def test_near_duplicates_stage(stages):
    rows = texts(stages[1])
    want = sorted({d for d, _, _, kept in brute.neardup(rows, 5, 80) if kept})
    assert sorted(d for d, _ in texts(stages[2])) == want  # of repeated rows one stays
    assert stages[2].columns == stages[0].columns


def test_substring_stage(stages):
    want = {d: n - gone for d, n, gone, _ in brute.substring(texts(stages[2]))}
    got = dict(texts(stages[3]))
    assert {d: len(brute.SPLIT.findall(t)) for d, t in got.items()} == {d: n for d, n in want.items() if n}
    assert stages[3].columns == stages[0].columns and all(r["n_chars"] == len(r["text"]) for r in stages[3].collect())


def test_decontamination_stage(spark, small, stages):
    items = [tuple(r) for r in spark.read.parquet(f"{small}/benchmark.parquet").select("item_id", "text").collect()]
    bad = {r[0] for r in brute.decontamination(texts(stages[3]), items) if r[-1]}
    assert {d for d, _ in texts(stages[4])} == {d for d, _ in texts(stages[3])} - bad


def test_packing_stage(stages):
    assert {r["doc_id"] for r in stages[5].select("doc_id").collect()} == {d for d, _ in texts(stages[4])}


def test_rows_without_an_id_and_other_columns(spark, small):
    some = spark.read.parquet(f"{small}/documents.parquet").limit(40)
    docs = some.unionByName(some.limit(2).withColumn("doc_id", F.lit(None).cast("long"))).withColumn("key", F.lit(1)).withColumn("shard", F.lit("s")).withColumn("row", F.lit(2.5)).withColumn("_text_key", F.lit(3))
    bench = spark.createDataFrame([(1, "w1 w2")], "item_id long, text string")
    assert op2_packing.pack(docs).where("start = 0").count() == 42
    assert op3_suffix.dedup(docs).count() == op6_quality.clean(docs).count() == op10_language.identify(docs).count() == 42
    assert op8_scoring.score(docs).count() == op9_decontamination.judge(op9_decontamination.find(docs, bench)).count() == 42
    assert op4_substring.dedup(docs).count() == op7_neardup.near_duplicates(docs).count() == 42
    for name, stage in pipeline.STAGES[:-1]:
        found = stage(spark, docs, small)
        assert found.columns == docs.columns and found.where("doc_id is null").count() == 2, name
