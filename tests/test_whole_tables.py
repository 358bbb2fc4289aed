import glob
import os

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from joinlearn import queries as learner
from joinlearn import workloads
from joinlearn.functions import bgd as solver

NAMES = ["moments_all_views_grouped", "materialized_moments", "individual_aggregates", "order_per_key_set_moments", "linear_only_onehot_moments", "distributed_matvec", "onehot_width", "zero_suppressed_rows"]


def test_scores_cover_the_whole_join(spark, sf):
    n = workloads.star(spark, sf, "W2")[0].listing().count()
    assert n > 4 * workloads.star(spark, sf, "W1")[0].listing().count()
    for name in ("predict_lr", "fm_scores"):
        assert entry.queries()[name](spark, sf).count() == n


@pytest.mark.parametrize("name", NAMES)
def test_whole_tables_equal_sql(spark, sf, name):
    duckdb = pytest.importorskip("duckdb")
    from tests.conftest import rows_of

    con = duckdb.connect()
    for p in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(p)[:-8]} AS SELECT * FROM '{p}'")
    assert "% 5" not in entry.oracle_sql()[f"{name}_v2"] and "% 5" in entry.oracle_sql()[name]
    for one in (name, f"{name}_v2"):
        want, got = con.sql(entry.oracle_sql()[one]).df(), entry.queries()[one](spark, sf).toPandas()
        cols = sorted(want.columns)
        assert rows_of(want[cols]) == rows_of(got[sorted(got.columns)])


def test_degree_two_learns_all_features(spark, sf, monkeypatch):
    seen = []

    def fit(model, *_, **options):
        seen.append((type(model).__name__, model.query.continuous, model.query.categorical))
        theta = options.get("theta0")
        return solver.FitResult(np.zeros(model.width) if theta is None else theta, 0, "", 0.0, 0.0, 0.0)

    monkeypatch.setattr(learner.solver, "bgd", fit)
    monkeypatch.setattr(learner, "moments", lambda *a, **k: None)
    monkeypatch.setattr(learner, "FeatureLayout", lambda *a: None)
    monkeypatch.setattr(learner, "SigmaIndex", lambda *a: None)
    for kind in (learner.Linear, learner.FactorizationMachine):
        monkeypatch.setattr(kind, "attach", lambda self, _: setattr(self, "width", 3000) or self)
    monkeypatch.setattr(learner, "_fm_start", lambda m: None)
    monkeypatch.setattr(learner, "rmse", lambda *a: 0.0)
    for w in (1, 2, 3):
        for kind in ("pr2", "fm"):
            entry.queries()[f"{kind}_fit_v{w}"](spark, sf)
            assert set(seen[-1][1]) == set(workloads.CONTINUOUS) and len(seen[-1][2]) == (9 if w == 3 else 8)


def test_scores_come_from_fitted_factors(spark, sf):
    got = entry.queries()["fm_scores"](spark, sf).agg(F.sqrt(F.avg((F.col("prediction") - F.col("l_quantity")) ** 2)), F.stddev_pop("l_quantity")).first()
    assert got[0] <= 1.01 * float(got[1])


def test_factorization_machine_of_w4_learns_all_features(spark, sf, monkeypatch):
    from joinlearn import queries, workloads

    class Asked(Exception):
        pass

    def moments(query, *_, **__):
        raise Asked(query)

    monkeypatch.setattr(queries, "moments", moments)
    with pytest.raises(Asked) as asked:
        queries.QUERIES["fm_fit_v4"](spark, sf)
    (query,) = asked.value.args
    assert set(query.features) == {*workloads.CONTINUOUS, *workloads.CATEGORICAL, "partkey"} and not query.where
