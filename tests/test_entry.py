import glob
import importlib
import os
import sys

import pytest

import __spark_entry__ as entry
from joinlearn import queries as learner


def test_flagship(spark):
    rows = entry.entry(spark)
    assert rows.count() == 1269 and "prediction" in rows.columns


FAST = ["toy_counts", "toy_registers", "count_factorized_w5", "sum_product_w5", "moments_pr2_v1", "materialized_moments", "ridge_one_feature", "bgd_fixed_recursive", "fd_map_brand", "nation_mn_join", "activity_composite_join", "session_event_moments", "sliding_event_moments", "as_of_event_value"]


@pytest.mark.parametrize("name", FAST)
def test_query_equals_sql(spark, sf, name):
    duckdb = pytest.importorskip("duckdb")
    from tests.conftest import rows_of

    con = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    want, got = con.sql(entry.oracle_sql()[name]).df(), entry.queries()[name](spark, sf).toPandas()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns)
    assert rows_of(want[cols]) == rows_of(got[cols])


def test_every_sql_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries()) and len(learner.queries()) > 60


def test_entry_without_the_corpus_operators(monkeypatch):
    for name in [m for m in sys.modules if m.startswith("joinlearn.llm") or m == "corpus_pipeline"]:
        monkeypatch.delitem(sys.modules, name)
    monkeypatch.setitem(sys.modules, "joinlearn.llm", None)
    monkeypatch.setitem(sys.modules, "corpus_pipeline", None)
    try:
        bare = importlib.reload(entry)
        assert set(bare.queries()) == set(learner.queries())
    finally:
        monkeypatch.undo()
        importlib.reload(entry)
