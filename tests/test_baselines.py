import numpy as np
import pytest

from joinlearn import workloads
from joinlearn.baselines import design, least_squares, stochastic
from joinlearn.operators import joins, measures

CONT, CATS = ("l_discount", "p_size"), ("l_returnflag", "o_orderstatus")


@pytest.fixture(scope="module")
def rows(spark, sf):
    return workloads.star(spark, sf, "W1", False, CONT, CATS)[0].listing().cache()


@pytest.fixture(scope="module")
def dense(rows):
    df, names = design.onehot_encode(rows, list(CATS), drop_first=True)
    return df, [*CONT, *names]


def test_least_squares_agree(dense):
    df, cols = dense
    x = df.select(*cols, "l_quantity").toPandas().to_numpy(float)
    want = np.linalg.lstsq(np.column_stack([np.ones(len(x)), x[:, :-1]]), x[:, -1], rcond=None)[0]
    for f in (least_squares.closed_form, least_squares.by_qr, least_squares.glm):
        assert np.allclose(f(df, cols, "l_quantity"), want, atol=1e-6)
    assert np.allclose(least_squares.chunked(df, cols, "l_quantity", strict=False), want, atol=1e-6)


def test_limits_and_ranks(rows, dense):
    full, names = design.onehot_encode(rows, list(CATS))
    cols = [*CONT, *names]
    with pytest.raises(design.DesignLimitError):
        least_squares.closed_form(full, cols, "l_quantity", max_columns=5)
    with pytest.raises(design.DesignLimitError):
        least_squares.by_qr(full, cols, "l_quantity", value_limit=100)
    with pytest.raises(design.RankError):
        least_squares.by_qr(full, cols, "l_quantity")
    with pytest.raises(design.RankError):
        least_squares.chunked(full, cols, "l_quantity", 200)
    with pytest.raises(design.DesignLimitError):
        design.onehot_encode(rows, list(CATS), max_columns=3)
    assert measures.status_of(lambda: least_squares.by_qr(full, cols, "l_quantity")) == ("rank", None)


def test_sparse_rows_and_stochastic_learners(rows, tmp_path, spark):
    from joinlearn.sources.tables import read_libsvm, write_sparse

    sparse = design.to_sparse_rows(rows, list(CONT), list(CATS), "l_quantity").cache()
    assert sparse.count() == rows.count()
    write_sparse(sparse, str(tmp_path / "s"))
    width = 2 + design.dictionaries(rows, list(CATS)).count()
    assert read_libsvm(spark, str(tmp_path / "s"), width).count() == rows.count()
    scale = np.ones(width)
    scale[1] = 50
    w, n = stochastic.sgd_ftrl(sparse, width, 100, epochs=2, alpha=5.0, scale=scale)
    y = np.array([r.label for r in sparse.collect()])
    pred = np.array([w[0] + sum(w[i] * v for i, v in zip(r.indices, r["values"], strict=True)) for r in sparse.collect()])
    assert n == 2 * -(-len(y) // 100) and np.sqrt(np.mean((pred - y) ** 2)) < 1.1 * y.std()
    got = stochastic.fm_mcmc(sparse, width, 2, 8)
    assert got["rmse"] <= got["baseline_rmse"] * 1.01
    with pytest.raises(MemoryError):
        stochastic.fm_mcmc(sparse, width, max_rows=10)


def test_gradient_through_joins(spark, sf):
    rel = workloads.star_relations(spark, sf)
    fact = rel["lineitem"].select("partkey", "l_quantity", "l_discount")
    theta = {"1": 1.0, "l_discount": 2.0, "p_size": 0.1}
    got = {r.feature: r.gradient for r in least_squares.gradient_through_joins(fact, [(rel["part"], "partkey", ["p_size"])], ["l_discount"], "l_quantity", theta).collect()}
    x = fact.join(rel["part"], "partkey").select("l_discount", "p_size", "l_quantity").toPandas()
    r = 1 + 2 * x.l_discount + 0.1 * x.p_size - x.l_quantity
    for f, v in (("1", 1), ("l_discount", x.l_discount), ("p_size", x.p_size)):
        assert np.isclose(got[f], (r * v).mean())


def test_compression(spark, sf):
    q, order = workloads.many_to_many(spark, sf)
    got, rows, deps = measures.compression(q, order).first(), q.listing().cache(), order.dependencies(q)
    assert got.listing == 358530 and got.ratio > 100
    assert got.factorized == sum(rows.select(*deps[v], v).distinct().count() for v in order.parent)
    q, order = workloads.star(spark, sf, "W2", extra=("s_nationkey",))
    got = measures.compression(q, order).first()
    assert (got.listing, got.factorized) == (132000, 54160)
    assert measures.variable_counts(q, order, grouped=True).count() == 22


def test_as_of_and_banded(spark):
    left = spark.createDataFrame([(1, 5, "a"), (1, 1, "b"), (2, 9, "c")], "k int, t int, n string")
    right = spark.createDataFrame([(1, 2, 10.0), (1, 5, 20.0), (1, 5, 30.0), (2, 10, 1.0)], "k int, t int, v double")
    assert {r.n: r.v_as_of for r in joins.as_of(left, right, "k", "t", "v").collect()} == {"a": 30.0, "b": None, "c": None}
    a = spark.createDataFrame([(0.0,), (2.4,)], "x double")
    b = spark.createDataFrame([(1.0,), (-0.9,), (3.5,), (1.3,)], "y double")
    assert {(r.x, r.y) for r in joins.banded(a, b, "x", "y", 1.1).collect()} == {(0.0, 1.0), (0.0, -0.9), (2.4, 3.5), (2.4, 1.3)}
