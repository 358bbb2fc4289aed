"""Corpus queries against their SQL, on the smallest tables and on texts made to be awkward."""

import pytest

from joinlearn.llm import queries
from tests.conftest import rows_of

WORDS = [f"w{i}" for i in range(24)]


@pytest.fixture(scope="module")
def odd_tables(spark, tmp_path_factory):
    folder = str(tmp_path_factory.mktemp("odd"))
    passage = " ".join(WORDS)
    docs = [
        (1, None, "a"), (2, "", None), (3, " \t\n\v\f\r", "a"), (4, passage.upper() + " x " + passage, "a"), (5, "one two\n\none two\n \n one two", "b"),
        (6, "a b c a b c a b", None), (7, "é—ü # 𝄞   w3", "b"), (8, " ".join(["same"] * 70), "c"), (9, "alpha-BETA, gamma", "c"), (10, "alpha beta", "c"),
        (11, "Released under the MIT License.\n", "c"), (12, "Released under the MIT License.\n\nReleased under the  MIT License", "c"), (13, "Released under the MIT License.\n" * 3 + "x", "c"),
        *[(100 + i, "short text", "bad") for i in range(30)], *[(200 + i, " ".join(f"u{i}x{j}" for j in range(60)), "good") for i in range(30)],
    ]
    items = [(1, passage), (2, "Alpha beta"), (3, ""), (4, None), (10, " ".join(WORDS[:9])), (5, "same " * 15), (6, passage)]
    spark.createDataFrame(docs, "doc_id long, text string, source string").write.parquet(f"{folder}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    return folder


@pytest.mark.parametrize("name", ["op4_host_quality", "op5_decontaminate", "op6_licenses"])
@pytest.mark.parametrize("tables", ["sf", "odd_tables"])
def test_query_equals_sql(spark, request, name, tables):
    duckdb = pytest.importorskip("duckdb")
    folder = request.getfixturevalue(tables)
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        path = f"{folder}/{t}.parquet"
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{path if tables == 'sf' else path + '/*.parquet'}'")
    want, got = con.sql(queries.oracle_sql()[name]).df(), queries.queries()[name](spark, folder).toPandas()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns) and rows_of(want[cols]) == rows_of(got[cols])
