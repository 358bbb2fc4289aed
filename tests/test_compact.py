import tracemalloc
from types import SimpleNamespace

import numpy as np
import pandas as pd
import pytest

from joinlearn import workloads
from joinlearn.functions import bgd as descent
from joinlearn.functions import layout, models
from joinlearn.functions.models import FactorizationMachine, Linear
from joinlearn.operators import dependencies as fd
from joinlearn.operators.moments import Moments, moments
from joinlearn.plans.monomials import aggregate_monomials, by_keys
from joinlearn.plans.query import FeatureQuery


def _degree_two(spark, sf):
    q, order = workloads.star(spark, sf, "W4", False, ("l_discount",), ("l_returnflag", "partkey", "p_brand"))
    return q, moments(q, aggregate_monomials(Linear(q, 2).h, q.response), order)


def test_moments_hold_codes_and_narrow_counts(spark, sf):
    q, found = _degree_two(spark, sf)
    table = found.tables[("l_returnflag", "partkey")]
    assert all(isinstance(table[c].dtype, pd.CategoricalDtype) for c in ("l_returnflag", "partkey"))
    assert any(table[c].dtype.itemsize < 8 for c in table.columns if c.startswith("m"))
    lines = q.listing().groupBy("l_returnflag", "partkey").count().toPandas()
    mine = dict(zip(zip(table.l_returnflag, table.partkey, strict=True), found.column(_count_of(found, ("l_returnflag", "partkey"))), strict=True))
    assert mine == dict(zip(zip(lines.l_returnflag, lines.partkey, strict=True), lines["count"], strict=True))


def _count_of(found, keys):
    return next(m for m in found.monomials[keys] if not m.cont)


def test_held_blocks_multiply_like_the_listed_entries(spark, sf, monkeypatch):
    q, found = _degree_two(spark, sf)
    products = []
    for listed, chunk in ((10**9, 1 << 20), (0, 100)):
        monkeypatch.setattr(layout, "LISTED", listed)
        monkeypatch.setattr(layout, "CHUNK", chunk)
        model = Linear(q, 2)
        sigma = layout.SigmaIndex(layout.FeatureLayout(found, model.h))
        x = np.random.default_rng(1).normal(size=sigma.layout.width)
        assert bool(sigma.blocks) == (listed == 0)
        rows, cols, values = sigma.listing()
        assert np.allclose(np.bincount(rows, weights=values * x[cols], minlength=len(x)), sigma.matvec(x))
        products.append((sigma.matvec(x), sigma.diagonal(), sigma.stored))
    assert np.allclose(products[0][0], products[1][0]) and np.allclose(products[0][1], products[1][1]) and products[0][2] == products[1][2]


def test_factor_products_in_chunks(spark, sf, monkeypatch):
    from joinlearn.functions import models

    q, found = _degree_two(spark, sf)
    got = []
    for chunk in (1 << 20, 50):
        monkeypatch.setattr(models, "CHUNK", chunk)
        model = FactorizationMachine(q, 3)
        model.attach(layout.SigmaIndex(layout.FeatureLayout(found, model.h)))
        theta = model.start(2)
        got.append((model.g(theta), model.pull(theta, np.arange(model.layout.width) % 7.0)))
    assert all(np.allclose(a, b) for a, b in zip(*got, strict=True))


def test_groupings_take_no_row_objects(spark, sf, monkeypatch):
    q, found = _degree_two(spark, sf)
    lay = layout.FeatureLayout(found, Linear(q, 2).h)
    brand = {r.partkey: r.p_brand for r in q.relations["part"].collect()}

    def refused(self):
        raise AssertionError("rows of the determinant are not collected as objects")

    monkeypatch.setattr(type(q.relations["part"]), "collect", refused)
    got = fd.groupings(q, fd.Dependency("partkey", ("p_brand",)), lay)["p_brand"]
    number: dict = {}
    assert got.tolist() == [number.setdefault(brand[v], len(number)) for v in lay.levels["partkey"].tolist()]


def _made(model_of, n=20_000):
    """A model over moments of made rows, each level of a large category twice."""
    rows = pd.DataFrame({"key": np.repeat(np.arange(n), 2), "flag": np.tile(["a", "b"], n), "x": np.arange(2 * n) % 11 / 10.0, "y": np.arange(2 * n) % 7})
    q = FeatureQuery({"rows": SimpleNamespace(columns=list(rows))}, ("x",), ("key", "flag"), "y")
    model, tables = model_of(q), {}
    groups = by_keys(aggregate_monomials(model.h, "y"))
    for ks, wanted in groups.items():
        terms = pd.DataFrame({f"m{i}": np.prod([rows[v] ** e for v, e in m.cont], axis=0) * np.ones(len(rows)) for i, m in enumerate(wanted)})
        tables[ks] = terms.groupby([rows[k] for k in ks]).sum().reset_index() if ks else terms.sum().to_frame().T
        tables[ks] = tables[ks].astype({k: pd.CategoricalDtype(sorted(rows[k].unique(), key=str)) for k in ks})
    return model.attach(layout.SigmaIndex(layout.FeatureLayout(Moments(q, tables, groups), model.h)))


@pytest.mark.parametrize("kind", ["lr", "fm"])
def test_descent_holds_few_vectors(monkeypatch, kind):
    for module in (layout, models, descent):
        monkeypatch.setattr(module, "CHUNK", 2_000, raising=False)
    if kind == "lr":
        model, most, options = _made(Linear), 13, {"precondition": "diag", "tol": 1e-7}
        groups = {"g": np.arange(20_000) % 5, "h": np.arange(20_000) % 3}
        options["penalty"] = fd.merged_penalty(model, fd.Dependency("key", ("g", "h")), groups)
    else:
        model, most = _made(lambda q: fd.DependentFM(q, fd.Dependency("key", ("g", "h")), 4)), 7
        model.with_groups({"g": np.arange(20_000) % 5, "h": np.arange(20_000) % 3})
        options = {"tol": None, "seed": 1, "penalty": model}
    tracemalloc.start()
    try:
        fit = descent.bgd(model, 1e-3, max_iter=4, **options)
        held = tracemalloc.get_traced_memory()[1] / fit.theta.nbytes
    finally:
        tracemalloc.stop()
    assert fit.runs == 4 and fit.trace[-1][1] < fit.trace[0][1]
    assert held < most, held


def test_release_gives_freed_memory_back():
    from joinlearn.operators import measures

    def held():
        return next(int(line.split()[1]) for line in open("/proc/self/status") if line.startswith("RssAnon")) / 1024

    session = SimpleNamespace(sparkContext=SimpleNamespace(_jvm=SimpleNamespace(System=SimpleNamespace(gc=lambda: None))))
    small = [np.zeros(1_000) for _ in range(20_000)]  # 160 MB in pieces, as parts of moments come
    last = [np.zeros(1_000) for _ in range(5)]
    small.clear()
    before = held()
    measures.release(session)
    assert before - held() > 100, (before, held(), len(last))
