"""The queries that SQL can state against DuckDB, on given tables and on awkward rows."""

import duckdb
import pytest

from wsample.llm import decontaminate, lines
from wsample.llm.queries import QUERIES, SQL


def rows(df):
    return sorted(repr(tuple(r)) for r in df[sorted(df.columns)].itertuples(index=False))


@pytest.mark.parametrize("name", sorted(SQL))
def test_twin(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    assert rows(QUERIES[name](spark, sf).toPandas()) == rows(con.execute(SQL[name]).df())


def test_awkward_rows(spark):
    texts = ["a b c d", "a b  c d e\n\nabcde", "abcdx\nabcd", "x b c d e", None, "", " \t ", "Été naïve ωmega", "one\x0btwo  three\nfour", "one two three", "A B c d", "abcde f", "abcde g\nabcde"]
    docs = spark.createDataFrame([*enumerate(texts), (99, "a b c\na b c\na b")], "doc_id long, text string")
    items = spark.createDataFrame([(1, "b c d"), (2, "ÉTÉ naïve"), (None, "one"), (3, None), (4, "été naïve"), (10, "x")], "item_id long, text string")
    con = duckdb.connect()
    con.register("documents", docs.toPandas())
    con.register("held", items.toPandas())
    con.execute("CREATE VIEW benchmark AS SELECT CAST(CASE WHEN item_id > 0 THEN item_id END AS BIGINT) AS item_id, text FROM held")
    got = lines.dedup_lines(docs).selectExpr("doc_id", "n_lines", "n_exact", "n_near", "md5(cast(coalesce(text, '') as binary)) AS text_md5")
    assert rows(got.toPandas()) == rows(con.execute(SQL["op1_line_dedup"]).df())
    assert rows(decontaminate.contamination(docs, items).toPandas()) == rows(con.execute(SQL["op6_decontamination"]).df())
