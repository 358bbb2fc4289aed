import numpy as np
import pandas as pd
import pytest

from joinlearn import workloads
from joinlearn.operators import moments as ops
from joinlearn.operators.moments import Moments, lower, moments
from joinlearn.plans.monomials import ONE, Monomial, variable
from joinlearn.plans.order import VariableOrder
from joinlearn.plans.query import FeatureQuery


def same(a: Moments, b: Moments, tol=1e-9):
    assert set(a.tables) == set(b.tables)
    for k in a.tables:
        for m in a.monomials[k]:
            x = dict(zip(map(tuple, a.tables[k][list(k)].astype(str).values.tolist()), a.column(m), strict=True))
            y = dict(zip(map(tuple, b.tables[k][list(k)].astype(str).values.tolist()), b.column(m), strict=True))
            assert x.keys() == y.keys()
            assert np.allclose([x[t] for t in x], [y[t] for t in x], rtol=tol, atol=1e-9), (k, m)


@pytest.mark.parametrize("load", [workloads.many_to_many, workloads.composite, workloads.nation_pairs])
@pytest.mark.parametrize("degree", [1, 2])
def test_strategies_and_kernels_agree(spark, sf, load, degree):
    q, order = load(spark, sf)
    if degree == 2:
        q.continuous, q.categorical = q.continuous[:1], q.categorical[:2]
        order = VariableOrder.suggest(q)
    wanted = q.aggregates(degree)
    base = moments(q, wanted, strategy="materialize", kernel="sql")
    for strategy, kernel, eager in (("factorized", "sql", True), ("factorized", "sql", False), ("factorized", "arrow", True), ("materialize", "arrow", True)):
        same(base, moments(q, wanted, order, strategy, kernel, eager))
    same(base, moments(q, wanted, strategy="order_per_keys", kernel="sql"))


def test_star_under_two_orders(spark, sf):
    q, order = workloads.star(spark, sf, "W1", False, ("p_size", "l_discount"), ("p_brand", "o_orderstatus"))
    same(moments(q, q.aggregates(1), order), moments(q, q.aggregates(1), VariableOrder.suggest(q)))


def test_marginals_and_rows(spark, sf):
    q, order = workloads.star(spark, sf, "W1")
    m = moments(q, q.aggregates(1), order, eager=False)
    assert m.rows == 1269 and m.entries() == (55, 3277)
    for c in q.categorical:
        assert m.column(variable(c, True)).sum() == m.rows
        z = variable("l_discount", False)
        assert np.isclose(m.column(variable(c, True) * z).sum(), m.scalar(z))


@pytest.mark.parametrize("workload,grouped", [("W2", 3355), ("W3", 4559), ("W4", 9552), ("W4F", 5903)])
def test_entry_counts(spark, sf, workload, grouped):
    q, order = workloads.star(spark, sf, workload)
    assert moments(q, q.aggregates(1), order, kernel="arrow", eager=False).entries() == (55, grouped)


def test_worked_example_values(spark):
    q, order = workloads.toy(spark)
    m = moments(q, q.aggregates(1), order)
    s = lambda **e: m.scalar(Monomial(tuple(sorted(e.items()))))
    assert (m.rows, s(A=1), s(C=1), s(D=1), s(A=2), s(A=1, C=1), s(A=1, D=1), s(C=2), s(C=1, D=1), s(D=2)) == (11, 12, 37, 210, 14, 44, 240, 151, 810, 4700)
    by = {r.B: (r.m0,) for r in m.tables[("B",)].itertuples()}
    assert by == {"b1": (8,), "b2": (3,)}


def test_sets_bags_and_empty(spark):
    r = spark.createDataFrame([(1, 2.0), (1, 2.0), (2, 3.0)], "a int, x double")
    s = spark.createDataFrame([(1, 5.0), (1, 6.0)], "a int, y double")
    bag = FeatureQuery({"r": r, "s": s}, ("x",), (), "y")
    assert moments(bag, bag.aggregates(1)).rows == 4
    sets = FeatureQuery({"r": r, "s": s}, ("x",), (), "y", set_semantics=True)
    assert moments(sets, sets.aggregates(1)).rows == 2
    none = FeatureQuery({"r": r.limit(0), "s": s}, ("x",), (), "y")
    assert moments(none, none.aggregates(1)).rows == 0
    apart = FeatureQuery({"r": r.withColumnRenamed("a", "b"), "s": s}, ("x",), (), "y", extra=("a", "b"))
    m = moments(apart, apart.aggregates(1))
    assert m.rows == 6 and m.scalar(Monomial((("x", 1), ("y", 1)))) == 77.0


def test_nulls(spark):
    r = spark.createDataFrame([("u", 1.0, 1.0), (None, 2.0, 2.0), ("v", None, 3.0)], "c string, x double, y double")
    dropped = FeatureQuery({"r": r}, ("x",), ("c",), "y", null_policy="drop_row")
    assert moments(dropped, dropped.aggregates(1)).rows == 1
    level = FeatureQuery({"r": r.dropna(subset=["x"])}, ("x",), ("c",), "y", null_policy="own_level")
    own = moments(level, level.aggregates(1))
    assert sorted(own.tables[("c",)].c) == ["u", "∅"]


def test_random_shapes(spark):
    rng = np.random.default_rng(11)
    for seed in range(4):
        n = int(rng.integers(1, 30))
        frame = lambda cols, n=n: spark.createDataFrame(pd.DataFrame({c: rng.integers(0, 4, n) for c in cols}))
        rel = [{"r": frame("ab"), "s": frame("bc"), "t": frame("bd")}, {"r": frame("abc"), "s": frame("cd"), "t": frame("de")}, {"r": frame("ab"), "s": frame("cd")}, {"r": frame("abx"), "s": frame("aby"), "t": frame("az")}][seed]
        names = sorted({c for d in rel.values() for c in d.columns})
        q = FeatureQuery(rel, (names[-1],), tuple(names[:2]), names[-2] if names[-2] not in names[:2] else None, extra=tuple(names))
        same(moments(q, q.aggregates(1), kernel="sql"), moments(q, q.aggregates(1), strategy="materialize", kernel="sql"))


def test_long_table_saved_and_read(spark, sf, tmp_path):
    q, order = workloads.star(spark, sf, "W1", False, ("l_discount",), ("l_returnflag",))
    roots = lower(q, q.aggregates(1), order, eager=False)
    ops.save(roots, str(tmp_path / "m"))
    back = spark.read.parquet(str(tmp_path / "m"))
    assert back.count() == ops.long_table(roots).count() and back.where("monomial = '1'").first().value == 1269.0


def test_limit_names_the_key_set(spark, sf):
    q, order = workloads.star(spark, sf, "W1", False, (), ("l_returnflag",))
    with pytest.raises(MemoryError, match="l_returnflag"):
        moments(q, q.aggregates(1), order, kernel="sql", limit=3)
    assert ONE == Monomial()


def test_cyclic_bag(spark):
    rng = np.random.default_rng(2)
    frame = lambda cols: spark.createDataFrame(pd.DataFrame({c: rng.integers(0, 5, 40) for c in cols}))
    q = FeatureQuery({"r": frame("ab"), "s": frame("bc"), "t": frame("ac")}, ("c",), ("a",), extra=("b",))
    same(moments(q, q.aggregates(1), kernel="sql"), moments(q, q.aggregates(1), strategy="materialize", kernel="sql"))
