import numpy as np
import pytest

from joinlearn import workloads
from joinlearn.functions.bgd import bb_step, bgd, solve_exact
from joinlearn.functions.layout import FeatureLayout, SigmaIndex, features
from joinlearn.functions.models import FactorizationMachine, Linear, gradient, objective, rmse
from joinlearn.functions.penalties import BlockCholesky, ClosedForm, DenseD, Ridge, Woodbury
from joinlearn.operators import dependencies as fd
from joinlearn.operators import predict
from joinlearn.operators.moments import moments
from joinlearn.plans.monomials import Monomial, aggregate_monomials, variable

LAM = 1e-2


def fitted(q, order, model):
    return model.attach(SigmaIndex(FeatureLayout(moments(q, aggregate_monomials(model.h, q.response), order, eager=False), model.h)))


@pytest.fixture(scope="module")
def star(spark, sf):
    return workloads.star(spark, sf, "W1", False, ("l_discount", "p_size"), ("l_returnflag", "o_orderstatus", "c_mktsegment"))


def numeric(model, theta, penalty, lam=LAM, eps=1e-6):
    out = np.zeros(len(theta))
    for i in range(len(theta)):
        e = np.zeros(len(theta))
        e[i] = eps * max(1, abs(theta[i]))
        out[i] = (objective(model, theta + e, lam, penalty) - objective(model, theta - e, lam, penalty)) / (2 * e[i])
    return out


@pytest.mark.parametrize("make", [Linear, lambda q: Linear(q, 2), lambda q: FactorizationMachine(q, 3)])
def test_gradients(star, make):
    model = fitted(*star, make(star[0]))
    theta = np.random.default_rng(1).normal(0, 0.3, model.width)
    want = numeric(model, theta, Ridge(model.width))
    assert np.allclose(gradient(model, theta, LAM, Ridge(model.width)), want, rtol=1e-4, atol=1e-3 * np.abs(want).max())


@pytest.mark.parametrize("make", [Linear, lambda q: Linear(q, 2), lambda q: FactorizationMachine(q, 3)])
def test_loss_from_moments_is_loss_on_rows(star, make):
    q, order = star
    model = fitted(q, order, make(q))
    theta = np.random.default_rng(2).normal(0, 0.2, model.width)
    rows = predict.predict(model, theta, q.listing()).toPandas()
    assert np.isclose(np.sqrt(np.mean((rows.prediction - rows.l_quantity) ** 2)), rmse(model, theta), rtol=1e-8)


def test_matvec_is_dense_product(star):
    model = fitted(*star, Linear(star[0], 2))
    s, g = model.sigma, np.random.default_rng(0).normal(size=model.width)
    assert np.allclose(s.matvec(g), s.dense() @ g) and np.allclose(s.dense(), s.dense().T)
    assert np.allclose(np.diag(s.dense()), s.diagonal())


def test_one_aggregate_fills_three_pairs():
    h = [variable("A", True), variable("B", True), variable("C", True), *(variable(a, True) * variable(b, True) for a, b in ("AB", "AC", "BC"))]
    abc = Monomial((), ("A", "B", "C"))
    pairs = [(i, j) for i in range(6) for j in range(i, 6) if h[i] * h[j] == abc]
    assert {(0, 5), (1, 4), (2, 3)} <= set(pairs)


@pytest.mark.parametrize("step", ["bb1", "bb2"])
@pytest.mark.parametrize("degree", [1, 2])
def test_descent_reaches_the_exact_solution(star, degree, step):
    model = fitted(*star, Linear(star[0], degree))
    fit = bgd(model, LAM, tol=1e-11, max_iter=20_000, precondition="diag", step=step)
    best = objective(model, solve_exact(model, LAM), LAM, Ridge(model.width))
    assert abs(fit.objective - best) <= 1e-6 * best
    values = [t[1] for t in fit.trace]
    assert all(b <= a + 1e-12 * abs(a) for a, b in zip(values, values[1:], strict=False))


def test_accepted_steps_are_shorter_than_the_exact_ones(star):
    model = fitted(*star, Linear(star[0]))
    fit = bgd(model, LAM, tol=None, max_iter=1)
    d = gradient(model, model.start(), LAM, Ridge(model.width))
    h = model.sigma.dense() + LAM * np.eye(model.width)
    limit = (d @ d) / (d @ h @ d)
    assert fit.trace[0][3] < limit
    assert bb_step(np.ones(2), -np.ones(2), "bb1", 0.5) == 0.5 and bb_step(np.ones(2), 2 * np.ones(2), "bb2", 1) == 0.5


def test_fm_descends_and_reduces_to_lr(star):
    q, order = star
    fm = fitted(q, order, FactorizationMachine(q, 2))
    fit = bgd(fm, LAM, tol=None, max_iter=120, seed=0, precondition="diag")
    assert fit.objective < objective(fm, fm.start(0), LAM, Ridge(fm.width))
    lr = fitted(q, order, Linear(q))
    theta = np.zeros(fm.width)
    theta[: lr.width] = np.random.default_rng(3).normal(size=lr.width)
    assert np.isclose(rmse(fm, theta), rmse(lr, theta[: lr.width]))


def test_penalties_agree():
    rng = np.random.default_rng(4)
    g, h, gamma = rng.integers(0, 5, 40), rng.integers(0, 3, 40), rng.normal(size=40)
    for a in (1.0, 3.0):
        want = DenseD([g], a).solve(gamma)
        for kind in (BlockCholesky, ClosedForm, Woodbury):
            assert np.allclose(kind([g], a).solve(gamma), want)
        assert np.allclose(Woodbury([g, h], a).solve(gamma), DenseD([g, h], a).solve(gamma))
    with pytest.raises(ValueError):
        ClosedForm([g, h])


def test_dependency_checks(spark, sf):
    part = workloads.star_relations(spark, sf)["part"]
    assert fd.holds(part, "partkey", "p_brand") and not fd.holds(part, "p_brand", "p_type")
    chain = [fd.Dependency("suppkey", ("nationkey",)), fd.Dependency("nationkey", ("regionkey",))]
    assert fd.closure(chain) == [fd.Dependency("suppkey", ("nationkey", "regionkey"))]


def test_linear_fit_under_a_chain(spark, sf):
    q, order, dep = workloads.supplier_chain(spark, sf)
    full = fitted(q, order, Linear(q))
    exact = solve_exact(full, LAM)
    r, rorder, _ = workloads.supplier_chain(spark, sf, reduced=True)
    small = fitted(r, rorder, Linear(r))
    groups = fd.groupings(q, dep, small.layout)
    pen = fd.merged_penalty(small, dep, groups)
    theta = solve_exact(small, LAM, pen)
    assert np.isclose(objective(small, theta, LAM, pen), objective(full, exact, LAM, Ridge(full.width)), rtol=1e-10)
    own = fd.recover(small, theta, dep, groups)
    assert np.allclose(own["suppkey"], exact[full.layout.block(variable("suppkey", True))], atol=1e-7)
    regions = np.sort(exact[full.layout.block(variable("regionkey", True))])
    assert np.allclose(np.sort(own["regionkey"]), regions, atol=1e-7)


def test_polynomial_fit_under_a_dependency(spark, sf):
    cats = ("partkey", "p_brand", "p_type", "l_returnflag")
    q, order = workloads.star(spark, sf, "W1", False, ("l_discount",), cats)
    r, rorder = workloads.star(spark, sf, "W1", False, ("l_discount",), ("partkey", "l_returnflag"))
    dep = fd.Dependency("partkey", ("p_brand", "p_type"))
    assert fd.reduce_query(q, [dep]).categorical == r.categorical
    full, small = fitted(q, order, Linear(q, 2)), fitted(r, rorder, Linear(r, 2))
    pen = fd.merged_penalty(small, dep, fd.groupings(q, dep, small.layout))
    a, b = solve_exact(full, LAM), solve_exact(small, LAM, pen)
    assert np.isclose(objective(small, b, LAM, pen), objective(full, a, LAM, Ridge(full.width)), rtol=1e-8)
    assert np.isclose(rmse(small, b), rmse(full, a), rtol=1e-6)


def test_fm_under_a_dependency(spark, sf):
    q, _ = workloads.star(spark, sf, "W1", False, ("l_discount",), ("partkey", "p_brand", "p_type", "l_returnflag"))
    r, rorder = workloads.star(spark, sf, "W1", False, ("l_discount",), ("partkey", "l_returnflag"))
    dep = fd.Dependency("partkey", ("p_brand", "p_type"))
    model = fitted(r, rorder, fd.DependentFM(r, dep, 2))
    model.with_groups(fd.groupings(q, dep, model.layout))
    theta = np.random.default_rng(5).normal(0, 0.3, model.width)
    pick = np.random.default_rng(6).choice(model.width, 40, replace=False)
    want = np.zeros(len(pick))
    for k, i in enumerate(pick):
        e = np.zeros(model.width)
        e[i] = 1e-6
        want[k] = (model.value(theta + e) - model.value(theta - e)) / 4e-6
    assert np.allclose(model.apply(theta)[pick], want, rtol=1e-4, atol=1e-4)
    # original parameters that merge to theta have at least this squared norm, and the recovered ones have exactly it
    gamma, merged, factors, own, spread = model.parts(theta)
    inner = 0.5 * (merged**2 - own**2 - sum(s**2 for s in spread)).sum(1)
    base = model.d.solve(gamma - inner)
    linear = [base, *(np.bincount(g, weights=base) for g in model.groups)]
    assert np.allclose(base + sum(x[g] for x, g in zip(linear[1:], model.groups, strict=True)) + inner, gamma)
    w, v = model.split(theta)
    rest = w @ w - gamma @ gamma + (v**2).sum() - (merged**2).sum()
    total = rest + sum(x @ x for x in linear) + (own**2).sum() + sum((f**2).sum() for f in factors)
    assert np.isclose(model.value(theta), total)


def test_unseen_levels_contribute_nothing(star, spark):
    q, order = star
    model = fitted(q, order, Linear(q))
    theta = solve_exact(model, LAM)
    row = q.listing().limit(1).toPandas()
    row["l_returnflag"] = "never"
    got = predict.predict(model, theta, spark.createDataFrame(row)).first()
    assert np.isfinite(got.prediction) and features(model.layout)[0] == 3


def test_distributed_matvec(star, spark):
    model = fitted(*star, Linear(star[0]))
    g = np.random.default_rng(8).normal(size=model.width)
    gdf = spark.createDataFrame([(i, float(x)) for i, x in enumerate(g)], "i long, value double")
    got = {r.i: r.value for r in predict.matvec_table(predict.sigma_table(model.sigma, spark), gdf).collect()}
    assert np.allclose([got[i] for i in range(model.width)], model.sigma.matvec(g))


def test_several_dependencies(spark):
    rng = np.random.default_rng(9)
    import pandas as pd

    from joinlearn.plans.query import FeatureQuery

    u = pd.DataFrame({"u": range(8), "ua": rng.integers(0, 3, 8), "ub": rng.integers(0, 2, 8)})
    v = pd.DataFrame({"v": range(6), "va": rng.integers(0, 2, 6)})
    f = pd.DataFrame({"u": rng.integers(0, 8, 150), "v": rng.integers(0, 6, 150), "y": rng.normal(size=150)})
    rel = {n: spark.createDataFrame(d.astype({c: int for c in d.columns if c != "y"})) for n, d in (("f", f), ("du", u), ("dv", v))}
    q = FeatureQuery(rel, (), ("u", "ua", "ub", "v", "va"), "y")
    deps = [fd.Dependency("u", ("ua", "ub")), fd.Dependency("v", ("va",))]
    r = fd.reduce_query(q, deps)
    full, small = fitted(q, None, Linear(q, 2)), fitted(r, None, Linear(r, 2))
    pen = fd.merged_penalty_of_all(small, [(d, fd.groupings(q, d, small.layout)) for d in deps])
    a, b = solve_exact(full, LAM), solve_exact(small, LAM, pen)
    assert np.isclose(objective(small, b, LAM, pen), objective(full, a, LAM, Ridge(full.width)), rtol=1e-8)


def test_factor_scoring_matches_the_join_form(star):
    from joinlearn.functions.scoring import fm_scores

    q, order = star
    model = fitted(q, order, FactorizationMachine(q, 3))
    theta = np.random.default_rng(3).normal(0, 0.2, model.width)
    got = fm_scores(model, theta, predict.predict(model, theta, q.listing(), "by_join"), "by_factors").select("by_join", "by_factors").toPandas()
    assert np.allclose(got.by_join, got.by_factors)


@pytest.mark.parametrize("workload,pr2", [("W1", 311499), ("W4F", 450172)])
def test_degree_two_entry_counts(spark, sf, workload, pr2):
    from joinlearn.operators.moments import entry_counts

    q, order = workloads.star(spark, sf, workload)
    assert entry_counts(q, q.aggregates(2), order) == (541, pr2)


def test_blocks_full_of_entries_are_multiplied_as_matrices(spark, sf, monkeypatch):
    from joinlearn.functions import layout

    q, order = workloads.star(spark, sf, "W3", False, ("l_discount",), ("o_orderpriority", "c_mktsegment", "s_nationkey", "p_brand"))
    lay = FeatureLayout(moments(q, q.aggregates(2), order, kernel="sql"), q.feature_map(2))
    x = np.arange(lay.width) % 7.0
    listed = SigmaIndex(lay)
    monkeypatch.setattr(layout, "LISTED", 20)
    blocks = SigmaIndex(lay)
    dense = [b for b in blocks.blocks if isinstance(b, layout.DenseBlock)]
    assert dense and len(dense) < len(blocks.blocks)
    assert blocks.stored == listed.stored and np.allclose(blocks.dense(), listed.dense())
    assert np.allclose(blocks.matvec(x), listed.matvec(x)) and np.allclose(blocks.matvec(x), listed.dense() @ x)
    monkeypatch.setattr(layout, "ALL_DENSE", max(b.matrix.size for b in dense))
    assert 0 < sum(b.matrix.size for b in SigmaIndex(lay).blocks if isinstance(b, layout.DenseBlock)) <= layout.ALL_DENSE


@pytest.mark.parametrize("rows, threads", [(16, 1), (1 << 15, 3)])
def test_blocks_of_a_key_set_are_multiplied_together(spark, sf, monkeypatch, rows, threads):
    from joinlearn.functions import layout

    q, order = workloads.star(spark, sf, "W4", False, ("l_discount", "p_size"), ("l_returnflag", "p_brand", "partkey"))
    lay = FeatureLayout(moments(q, q.aggregates(2), order, kernel="sql"), q.feature_map(2))
    x = np.arange(lay.width) % 7.0
    want = SigmaIndex(lay).dense() @ x
    for name, value in (("LISTED", 20), ("TOGETHER", 20), ("DENSE", 0), ("CHUNK", 2 * rows), ("THREADS", threads)):
        monkeypatch.setattr(layout, name, value)
    sigma = SigmaIndex(lay)
    parts = [p for p in sigma._parts if isinstance(p, layout.Together)]
    assert len(parts) > 3 and sum(len(p.pairs) for p in parts) > 4 * len(parts)
    into = np.full(lay.width, np.nan)
    assert np.allclose(sigma.matvec(x), want) and np.array_equal(sigma.matvec(x, into), sigma.matvec(x))
