"""The experiments: how each measure moves with rows, categories, dependencies, sharing and sparsity. Timings vary from run to run."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession

from . import workloads
from .baselines import design, stochastic
from .functions.bgd import bgd
from .functions.layout import FeatureLayout, SigmaIndex
from .functions.models import Linear, rmse
from .operators import dependencies as fd
from .operators import measures
from .operators.moments import combination_counts, entry_counts, lower, moments, onehot_query
from .plans.monomials import aggregate_monomials, feature_monomials
from .plans.views import Views

LAM = 1e-3


def _noop(df: DataFrame) -> float:
    return measures.time_noop(df)


def learn(spark: SparkSession, sf_dir: str, workload: str, strategy: str = "factorized") -> dict:
    measures.release(spark)  # shuffles of the workload before
    query, order = workloads.star(spark, sf_dir, workload)
    mom = moments(query, query.aggregates(1), order, strategy)
    began = time.time()
    model = Linear(query).attach(SigmaIndex(FeatureLayout(mom, query.feature_map(1))))
    penalty = fd.merged_penalty(model, workloads.PART, fd.groupings(query, workloads.PART, model.layout)) if workload == "W4F" else None
    fit = bgd(model, LAM, penalty=penalty, precondition="diag", tol=1e-6, max_iter=600)
    s, g = mom.entries()
    return {"workload": workload, "strategy": strategy, "n_rows": int(mom.rows), "parameters": model.width, "scalar": s, "grouped": g, "aggregate_s": mom.seconds, "converge_s": time.time() - began, "runs": fit.runs, "rmse": rmse(model, fit.theta)}


SCHEMA = "workload string, strategy string, n_rows long, parameters long, scalar long, grouped long, aggregate_s double, converge_s double, runs long, rmse double"


def _table(spark: SparkSession, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame([tuple(r.values()) for r in rows], SCHEMA)


def rows_and_categories(spark: SparkSession, sf_dir: str) -> DataFrame:
    """W1 to W2: five times the rows. W2 to W3 and W4: more categories. W4 to W4F: the dependency."""
    return _table(spark, [learn(spark, sf_dir, w) for w in ("W1", "W2", "W3", "W4", "W4F")])


def strategies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, [learn(spark, sf_dir, "W2", s) for s in ("factorized", "materialize")])


def sharing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(strategy, aggregates, seconds, seconds_each): all aggregates at once, and one job for each of a few."""
    query, order = workloads.star(spark, sf_dir, "W2")
    wanted = query.aggregates(1)
    bulk = moments(query, wanted, order)
    some = [m for m in wanted if len(m.cats) == 1][:6]
    one = sum(_noop(df) for _, _, df in lower(query, some, strategy="individual"))
    n = sum(bulk.entries())
    return spark.createDataFrame([("bulk", n, bulk.seconds, bulk.seconds / n), ("individual", len(some), one, one / len(some))], "strategy string, aggregates long, seconds double, seconds_each double")


def onehot_against_sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(form, columns, entries, seconds): categories as indicator columns, dense, against grouped sums."""
    query, order = workloads.star(spark, sf_dir, "W2", categorical=("l_returnflag", "l_linestatus", "o_orderpriority", "o_orderstatus", "c_mktsegment"))
    sparse = moments(query, query.aggregates(1), order)
    hot = onehot_query(spark, query)
    dense = moments(hot, hot.aggregates(1))
    return spark.createDataFrame([("sparse", len(query.features), sum(sparse.entries()), sparse.seconds), ("onehot", len(hot.features), sum(dense.entries()), dense.seconds)], "form string, columns long, entries long, seconds double")


def degree_two_entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(workload, model, scalar, grouped): aggregates of degree-two models."""
    rows = []
    for w in ("W1", "W2", "W4F"):
        measures.release(spark)
        query, order = workloads.star(spark, sf_dir, w)
        models = [(name, aggregate_monomials(feature_monomials(query.continuous, query.categorical, 2, squares), query.response)) for name, squares in (("pr2", True), ("fm", False))]
        counts = combination_counts(query, list(dict.fromkeys(m.cats for _, wanted in models for m in wanted if m.cats)), order)
        rows += [(w, name, *entry_counts(query, wanted, order, counts)) for name, wanted in models]
    return spark.createDataFrame(rows, "workload string, model string, scalar long, grouped long")


def epoch_against_descent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(learner, seconds): one stochastic epoch over exported rows, and the whole route over moments."""
    query, order = workloads.star(spark, sf_dir, "W2")
    rows, width = design.sparse_rows(Views(query, order).joined(), list(query.continuous), list(query.categorical), "l_quantity")
    _, epoch = measures.timed(lambda: stochastic.sgd_ftrl(rows, width, 10_000))
    del rows
    measures.release(spark)
    _, route = measures.timed(lambda: learn(spark, sf_dir, "W2"))
    return spark.createDataFrame([("epoch", epoch), ("moments", route)], "learner string, seconds double")


def minibatch_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(batch, shuffle, batches, seconds) of an epoch."""
    query, order = workloads.star(spark, sf_dir, "W2", False, ("l_discount",), ("l_returnflag",))
    (rows, width), out = design.sparse_rows(Views(query, order).joined(), ["l_discount"], ["l_returnflag"], "l_quantity"), []
    for size in (100, 1000, 10_000):
        for shuffle in (False, True):
            (_, n), s = measures.timed(lambda size=size, shuffle=shuffle: stochastic.sgd_ftrl(rows, width, size, shuffle=shuffle))
            out.append((size, shuffle, n, s))
    return spark.createDataFrame(out, "batch int, shuffle boolean, batches int, seconds double")
