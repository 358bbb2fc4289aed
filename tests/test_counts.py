import pytest

import __spark_entry__ as entry
from joinlearn import queries as learner
from joinlearn import workloads
from joinlearn.operators.moments import linear_entries, moments, occurrences
from joinlearn.plans.query import FeatureQuery


def test_occurrences_equal_collected_moments(spark, sf, monkeypatch):
    q, order = workloads.star(spark, sf, "W4")
    want = moments(q, q.aggregates(1), order, kernel="arrow", eager=False)
    for least in (0, 5, 1_000):  # all categories grouped, some, none but the part key
        monkeypatch.setattr("joinlearn.operators.moments.SET_LEVELS", least)
        n, found = occurrences(q, order)
        assert n == want.rows and all(found[ks] == len(t) for ks, t in want.tables.items() if ks)
        assert linear_entries(q, found)[:2] == want.entries()


def test_occurrences_of_nothing_and_of_nulls(spark):
    rows = spark.createDataFrame([(1, "a", None), (2, None, "x"), (2, None, "x")], "k int, b string, c string")
    q = FeatureQuery({"r": rows}, (), ("b", "c"))
    assert occurrences(q) == (3, {("b",): 2, ("c",): 2, ("b", "c"): 2})
    assert occurrences(FeatureQuery({"r": rows.limit(0)}, (), ("b", "c"))) == (0, {("b",): 0, ("c",): 0, ("b", "c"): 0})


def nothing_collected(*_, **__):
    raise MemoryError("moments are not collected to be counted")


COUNTING = ["dense_vs_sparse_ratio", "aggregate_counts_lr", "feature_counts"]


@pytest.mark.parametrize("name", COUNTING)
def test_counts_collect_no_moments(spark, sf, monkeypatch, name):
    want = entry.queries()[name](spark, sf).collect()
    monkeypatch.setattr(learner, "moments", nothing_collected)
    assert entry.queries()[name](spark, sf).collect() == want
