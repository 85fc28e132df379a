"""The SQL of the text queries against the queries, on the smallest tables."""

import duckdb
import pytest

from tempcorr.llm import op3_suffix
from tempcorr.llm.queries import oracle_sql, queries

DATA = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["op5_warc", "op6_quality", "op9_decontamination"])
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for table in ("documents", "pages", "benchmark"):
        con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{DATA}/{table}.parquet'")
    got = queries()[name](spark, DATA)
    columns = sorted(got.columns)
    want = con.execute(f"SELECT {', '.join(columns)} FROM ({oracle_sql()[name]})").fetchall()
    assert sorted(map(repr, want)) == sorted(repr(tuple(r)) for r in got.select(*columns).collect())


def test_suffix_dedup_equals_sql(spark):
    """Repeated ids, null, empty and touching spans too: the SQL and the operator over the smallest table and rows like these."""
    part = "".join(chr(97 + i * i % 23) for i in range(400))
    rows = [(-1, None), (-2, ""), (-3, part), (-3, part + "ß" + part), (-4, "x" + part + part[::-1] + "y"), (-5, part[::-1]), (-6, "ab" * 500), (-7, part[:399])]
    docs = spark.read.parquet(f"{DATA}/documents.parquet").select("doc_id", "text").unionByName(spark.createDataFrame(rows, "doc_id long, text string"))
    con = duckdb.connect()
    con.register("documents", docs.toArrow())
    got = op3_suffix.dedup(docs).drop("kept")
    want = con.execute(f"SELECT {', '.join(got.columns)} FROM ({oracle_sql()['op3_suffix_dedup']})").fetchall()
    assert sorted(map(repr, want)) == sorted(repr(tuple(r)) for r in got.collect())
    assert {(-5, 400, 400, 1), (-4, 802, 800, 1), (-7, 399, 0, 0)} <= {r[:4] for r in want}
