import numpy as np
import pytest

from joinlearn import workloads
from joinlearn.functions.layout import FeatureLayout, SigmaIndex
from joinlearn.functions.models import Linear
from joinlearn.operators import dealt
from joinlearn.operators import moments as operator
from joinlearn.operators.moments import entry_counts, moments
from joinlearn.plans.monomials import by_keys


def _entries(found):
    return {str(m): dict(zip(zip(*[t[k].tolist() for k in ks], strict=True) if ks else [()], found.column(m).tolist(), strict=True)) for ks, t in found.tables.items() for m in found.monomials[ks]}


@pytest.mark.parametrize("workload", ["W1", "W4", "W4F"])
def test_large_category_is_grouped_in_one_pass(spark, sf, monkeypatch, workload):
    monkeypatch.setattr(dealt, "SMALL_LEVELS", 100 if workload != "W1" else 1_000)
    monkeypatch.setattr(dealt, "ROWS", 200)
    q, order = workloads.star(spark, sf, workload)
    mine = moments(q, q.aggregates(1), order, "materialize" if workload == "W1" else "factorized")
    assert mine.strategy.endswith("/dealt")
    views = moments(q, q.aggregates(1), order, kernel="sql")
    assert mine.entries() == views.entries()
    a, b = _entries(mine), _entries(views)
    assert a.keys() == b.keys()
    for m, values in a.items():
        assert values.keys() == b[m].keys(), m
        assert np.allclose([values[k] for k in values], [b[m][k] for k in values], rtol=1e-9), m
    layouts = [FeatureLayout(x, q.feature_map(1)) for x in (mine, views)]
    assert all(layouts[0].levels[c].tolist() == layouts[1].levels[c].tolist() for c in q.categorical)
    x = np.arange(layouts[0].width) % 7.0
    assert (mine.wide(("o_orderpriority", "partkey")) is not None) == (workload != "W1")
    assert np.allclose(*(Linear(q).attach(SigmaIndex(lay)).sigma.matvec(x) for lay in layouts))


@pytest.mark.parametrize("workload", ["W1", "W4F"])
def test_degree_two_combinations_are_counted_in_one_pass(spark, sf, monkeypatch, workload):
    monkeypatch.setattr(dealt, "SMALL_LEVELS", 100)
    monkeypatch.setattr(dealt, "ROWS", 200)
    q, order = workloads.star(spark, sf, workload, False, ("l_discount",))
    rows, groups = q.listing().select(*q.categorical).toPandas(), by_keys(q.aggregates(2))
    want = sum(len(ms) * len(rows[list(ks)].drop_duplicates()) for ks, ms in groups.items() if ks)

    def refused(*_):
        raise AssertionError("no view for each key set")

    monkeypatch.setattr(operator, "lower", refused)
    assert entry_counts(q, q.aggregates(2), order) == (len(groups[()]), want)


def test_materialised_join_is_grouped_by_all_key_sets_at_once(spark, sf, monkeypatch):
    from joinlearn import experiments

    def refused(*_):
        raise AssertionError("no join for each key set")

    got = [experiments.learn(spark, sf, "W2")]
    monkeypatch.setattr(operator, "lower", refused)
    got.append(experiments.learn(spark, sf, "W2", "materialize"))
    assert all(got[0][k] == got[1][k] for k in ("n_rows", "parameters", "scalar", "grouped"))
    assert abs(got[0]["rmse"] - got[1]["rmse"]) < 1e-4


def test_views_of_large_relations_are_evaluated_apart(spark, sf, monkeypatch):
    q, order = workloads.star(spark, sf, "W2")
    together = moments(q, q.aggregates(1), order)
    jobs, stacked = [], operator._stacked
    monkeypatch.setattr(operator, "APART", 100)
    monkeypatch.setattr(operator, "_stacked", lambda views: jobs.append(len(views)) or stacked(views))
    apart = moments(q, q.aggregates(1), order)
    assert len(jobs) > 1 and set(jobs) == {1}
    a, b = _entries(apart), _entries(together)
    assert a.keys() == b.keys() and all(a[m].keys() == b[m].keys() and np.allclose([a[m][k] for k in a[m]], [b[m][k] for k in a[m]]) for m in a)


def test_entries_of_the_large_category_come_in_the_layouts_order(spark, sf, monkeypatch):
    monkeypatch.setattr(dealt, "SMALL_LEVELS", 100)
    q, order = workloads.star(spark, sf, "W2", False, ("l_discount",), ("partkey", "l_returnflag"))
    found = moments(q, q.aggregates(2), order)
    assert found.strategy.endswith("/dealt")
    lay = FeatureLayout(found, q.feature_map(2))
    for ks, t in found.tables.items():
        if "partkey" in ks:
            assert lay.positions(ks, ks).tolist() == list(range(len(t)))


@pytest.mark.parametrize("workload, held", [("W3", 1 << 24), ("W3", 100), ("W4", 1 << 24)])
def test_wide_payloads_are_summed_in_columns_and_come_merged(spark, sf, monkeypatch, workload, held):
    monkeypatch.setattr(dealt, "SMALL_LEVELS", 100)
    monkeypatch.setattr(dealt, "ROWS", 500)
    monkeypatch.setattr(dealt, "HELD", held)
    monkeypatch.setattr(operator, "MANY_PIECES", 0)
    cats = {"W3": ("l_returnflag", "o_orderstatus", "c_mktsegment", "s_nationkey"), "W4": ("l_returnflag", "o_orderstatus", "partkey")}[workload]
    q, order = workloads.star(spark, sf, workload, False, ("l_discount", "p_size", "o_totalprice"), cats)
    parts, add = [], dealt.Gathered.add
    monkeypatch.setattr(dealt.Gathered, "add", lambda self, part: (parts.append(part), add(self, part)))
    mine = moments(q, q.aggregates(2), order)
    assert mine.strategy.endswith("/dealt")
    assert workload == "W4" or len(parts) == len(by_keys(q.aggregates(2)))
    other = moments(q, q.aggregates(2), order, kernel="arrow")
    a, b = _entries(mine), _entries(other)
    assert mine.entries() == other.entries() and a.keys() == b.keys()
    for m, values in a.items():
        assert values.keys() == b[m].keys(), m
        assert np.allclose([values[k] for k in values], [b[m][k] for k in values], rtol=1e-9), m
    h = q.feature_map(2)
    layouts = [FeatureLayout(x, h) for x in (mine, other)]
    x = np.arange(layouts[0].width) % 7.0
    assert np.allclose(*(SigmaIndex(lay).matvec(x) for lay in layouts))


def test_wide_payloads_over_no_rows(spark, sf, monkeypatch):
    from dataclasses import replace

    monkeypatch.setattr(operator, "MANY_PIECES", 0)
    q, order = workloads.star(spark, sf, "W3", False, ("l_discount",), ("l_returnflag", "o_orderstatus"))
    found = moments(replace(q, where={"orders": "false"}), q.aggregates(2), order)
    assert found.strategy.endswith("/dealt") and found.rows == 0 and found.entries()[1] == 0
