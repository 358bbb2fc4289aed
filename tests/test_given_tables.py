import pytest

import __spark_entry__ as entry


@pytest.mark.parametrize("name", ["entry_identities", "toy_counts", "toy_registers"])
def test_results_come_from_the_given_tables(spark, sf, sf01, name):
    duckdb = pytest.importorskip("duckdb")
    from tests.conftest import rows_of

    seen = []
    for d in (sf, sf01):
        con = duckdb.connect()
        for t in ("customer", "supplier", "orders", "part", "lineitem"):
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
        want, got = con.execute(entry.oracle_sql()[name]).df(), entry.queries()[name](spark, d).toPandas()
        seen.append(rows_of(got[sorted(got.columns)]))
        assert seen[-1] == rows_of(want[sorted(want.columns)])
    assert seen[0] != seen[1]
