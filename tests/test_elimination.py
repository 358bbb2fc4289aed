import numpy as np

from joinlearn import workloads
from joinlearn.functions import bgd as solver
from joinlearn.functions.layout import FeatureLayout, SigmaIndex
from joinlearn.functions.models import Linear
from joinlearn.operators.moments import moments


def test_wide_categories_are_eliminated_not_made_dense(spark, sf, monkeypatch):
    q, order, _ = workloads.supplier_chain(spark, sf)
    model = Linear(q).attach(SigmaIndex(FeatureLayout(moments(q, q.aggregates(1), order, kernel="sql"), q.feature_map(1))))
    monkeypatch.setattr(solver, "DENSE_WIDTH", 10**9)
    want = solver.solve_exact(model, 1e-3)
    monkeypatch.setattr(solver, "DENSE_WIDTH", 3)  # in several pieces
    monkeypatch.setattr(SigmaIndex, "dense", lambda self: 1 / 0)
    assert np.allclose(solver.solve_exact(model, 1e-3), want, rtol=1e-8, atol=1e-10)
