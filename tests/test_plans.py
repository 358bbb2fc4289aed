import pytest

from joinlearn import workloads
from joinlearn.operators import measures
from joinlearn.operators.moments import lower, keyed_table
from joinlearn.plans.monomials import ONE, Monomial, aggregate_monomials, feature_monomials, variable
from joinlearn.plans.order import VariableOrder
from joinlearn.plans.registers import build_registers, explain, sharing


def test_dependencies_of_the_worked_example(spark):
    q, order = workloads.toy(spark)
    assert order.validate(q).dependencies(q) == {"A": [], "B": ["A"], "C": ["A", "B"], "D": ["B"], "E": ["A"]}
    assert order.ancestors("C") == ["A", "B"]


def test_registers_of_the_worked_example(spark):
    q, order = workloads.toy(spark)
    regs = build_registers(order, q.aggregates(1))
    assert {v: len(r.entries) for v, r in regs.items()} == {"A": 19, "B": 9, "C": 3, "D": 3, "E": 2}
    assert len(regs["A"].local) == 3 and len(regs["B"].local) == 2
    assert {str(m) for m in regs["B"].entries} == {"1", "[B]", "C", "D", "C*[B]", "D*[B]", "C^2", "C*D", "D^2"}
    assert all(f >= 1 for *_, f in sharing(regs, order)) and "A: 19 entries" in explain(regs, order)
    cd = regs["A"].entries[Monomial((("C", 1), ("D", 1)))]
    local, b, e = regs["A"].components[cd]
    assert local == 0 and list(regs["B"].entries)[b] == Monomial((("C", 1), ("D", 1))) and list(regs["E"].entries)[e] == ONE


def test_invalid_orders_are_rejected(spark):
    q, _ = workloads.toy(spark)
    for text in ("A(B(C), D, E)", "A(B(C, D))", "A(B(C, D), E, X)"):
        with pytest.raises(ValueError):
            VariableOrder.parse(text).validate(q)
    for text in ("A(B", "A)B", "A(A)", "(A)", "A(B;C)"):
        with pytest.raises(ValueError):
            VariableOrder.parse(text)


def test_suggested_orders_are_valid(spark, sf):
    for q in (workloads.toy(spark)[0], workloads.star(spark, sf)[0], workloads.many_to_many(spark, sf)[0], workloads.composite(spark, sf)[0]):
        VariableOrder.suggest(q).validate(q)


def test_monomial_counts():
    h = feature_monomials("abcdefgh", [f"c{i}" for i in range(8)])
    scalars = [m for m in aggregate_monomials(h, "y") if not m.cats]
    assert len(scalars) == 55 == measures.expected_scalars(8)
    h2 = feature_monomials("abcdefgh", [f"c{i}" for i in range(8)], 2)
    by = {}
    for m in aggregate_monomials(h2, "y"):
        by.setdefault(m.cats, []).append(m)
    assert [len(by[k]) for k in ((), ("c0",), ("c0", "c1"), ("c0", "c1", "c2"), ("c0", "c1", "c2", "c3"))] == [541, 174, 46, 9, 1]
    fm = {}
    for m in aggregate_monomials(feature_monomials("abcdefgh", [f"c{i}" for i in range(8)], 2, squares=False), "y"):
        fm.setdefault(m.cats, []).append(m)
    assert len(fm[()]) == 461 and len(fm[("c0",)]) == 166 and len(fm[("c0", "c1")]) == 46


def test_published_identities():
    assert [measures.expected_scalars(k) for k in (32,)] == [595]
    assert [measures.expected_lr_entries(o, 32, p) for o, p in ((55, 548), (1340, 65989), (3702, 31867), (3653, 20387))] == [2418, 111549, 157735, 144589]
    assert 562 * 563 // 2 == 158203 and 530 * 531 // 2 == 140715 and 3702 - 3653 == 49
    assert round(measures.speedup(50.63, 308.83, 490.13, 25.51, 0.02), 2) == 33.28
    assert round(measures.speedup(50.63, 74.72, 2762.50, 25.51, 0.02), 2) == 113.12
    assert round(measures.sparsity_gain(154595, 46_271_000)) == 258


def test_exact_anchor(spark, sf):
    q, order = workloads.star(spark, sf, "W2", exact=True)
    m = [ONE, variable("l_quantity", False), Monomial((("l_discount", 1), ("l_quantity", 1)))]
    got = {r.monomial: r.value for r in keyed_table(lower(q, m, order, eager=True)).collect()}
    assert got == {"1": 6000.0, "l_quantity": 152257.0, "l_discount*l_quantity": 771638.0}


def test_pushdown_and_pruning(spark, sf):
    q, order = workloads.star(spark, sf, "W1", False, ("l_discount",), ("l_returnflag",))
    plan = lower(q, q.aggregates(1), order, eager=False)[0][2]._jdf.queryExecution().toString()
    assert "l_tax" not in plan.split("Physical Plan")[1] and "PartitionFilters" in plan and "CartesianProduct" not in plan


def physical(roots):
    return keyed_table(roots)._jdf.queryExecution().executedPlan().toString()


def test_default_plans_group_below_the_join(spark, sf01):
    """Sums are grouped by the root's key before the join above them: an aggregate lies under a join, unlike over the listing."""
    for q, order in (workloads.star(spark, sf01, "W2", False, workloads.CONTINUOUS, ()), workloads.many_to_many(spark, sf01)):
        wanted = [m for m in q.aggregates(1) if not m.cats]
        below = lambda p: "Join" in p[: p.rindex("HashAggregate")]
        factorized, listed = physical(lower(q, wanted, order)), physical(lower(q, wanted, strategy="materialize"))
        assert below(factorized) and not below(listed)


def test_views_are_shared_between_key_sets(spark, sf01):
    q, order = workloads.star(spark, sf01, "W2")
    wanted = q.aggregates(1)
    views = lower(q, wanted, order).views
    assert sum(len(v.sets) for v in views) == 37 and len(views) == 3
    assert physical(lower(q, wanted, order)).count("FileScan") < 20  # the listing is read anew for each of 37 key sets


def test_one_pass_with_many_levels(spark):
    """Four keys of many levels in one batch: their codes cannot be multiplied in 64 bits."""
    import numpy as np
    import pandas as pd

    from joinlearn.operators.moments import one_pass

    n = 131_072
    rows = pd.DataFrame({k: np.r_[np.arange(n), np.random.default_rng(i).permutation(n)] for i, k in enumerate("abcd")} | {"m0": 1.0})
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 400_000)
    try:
        keys = ("a", "b", "c", "d")
        frame = spark.createDataFrame(rows).coalesce(1)
        assert one_pass(frame, keys, [ONE], {keys: [Monomial((), keys)]}).count() == 2 * n
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")


def test_limit_stops_the_one_pass_kernel_too(spark, sf):
    from joinlearn.operators.moments import moments

    q, order = workloads.star(spark, sf, "W2", False, (), ("l_returnflag", "p_brand"))
    with pytest.raises(MemoryError):
        moments(q, q.aggregates(1), order, kernel="arrow", limit=10)
