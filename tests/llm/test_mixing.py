import re

from joinlearn.llm import common, mixing, queries
from pyspark.sql import functions as F


def water(sizes, weights=(3, 1, 2), share=1.5, most=2.0):
    names = sorted(k for k in sizes if k is not None) + ([None] if None in sizes else [])
    w = {n: weights[i % 3] for i, n in enumerate(names)}
    left, open_, got = share * sum(sizes.values()), set(names), {}
    while open_:
        total = sum(w[n] for n in open_)
        full = {n for n in open_ if left * w[n] / total > most * sizes[n]}
        if not full:
            return got | {n: left * w[n] / total for n in open_}
        for n in full:
            got[n] = most * sizes[n]
        left -= sum(got[n] for n in full)
        open_ -= full
    return got


def test_query_meets_targets(spark, sf01):
    rows = queries.op10_mix(spark, sf01).collect()
    docs = {r.doc_id: r for r in common.table(spark, sf01, "documents").collect()}
    sizes = {}
    for d in docs.values():
        sizes[d.source] = sizes.get(d.source, 0) + len(re.findall(r"[^\x20\x09-\x0D]+", d.text or ""))
    want, taken = water(sizes), {}
    for r in rows:
        d = docs[r.doc_id]
        assert r.size == len(re.findall(r"[^\x20\x09-\x0D]+", d.text or "")) and r.source_size == sizes[d.source]
        assert abs(r.target - want[d.source]) < 1e-6 * max(1, want[d.source]) and 0 <= r.taken <= 2 * r.size
        taken[d.source] = taken.get(d.source, 0) + r.taken
    assert all(abs(taken[s] - want[s]) <= max(0.02 * want[s], 50) for s in want)
    again = {r.doc_id: r.taken for r in queries.op10_mix(spark.newSession(), sf01).collect()}
    assert again == {r.doc_id: r.taken for r in rows}


def test_rates_solve_the_dual(spark):
    cells = spark.createDataFrame([("a", s, 10) for s in range(1, 50)], "source string, size long, n long")
    words = sum(10 * s for s in range(1, 50))
    for share in (0.3, 1.0, 1.7):
        goals = spark.createDataFrame([("a", share * words, 25.0)], "source string, target double, mean double")
        lam = mixing.multipliers(cells, goals).first().lam
        got = cells.select(F.sum(F.col("n") * F.col("size") * F.least(F.lit(2.0), F.exp(lam * F.col("size") / 25.0)))).first()[0]
        assert abs(got - share * words) < 1e-3


def test_odd_rows(odd_docs, no_docs):
    rows = mixing.mix(odd_docs, ["doc_id", "size"]).collect()
    assert len(rows) == odd_docs.count()
    assert mixing.mix(no_docs, ["doc_id"]).count() == 0


def test_rounding_settles_beside_a_giant(spark):
    cases = {"giant": ([(100_000, 1), (500, 100)], 75_000.0, {100_000: 0.253, 500: 0.993}), "many": ([(s, 1) for s in range(1, 400)], 60_000.0, {s: 0.75 for s in range(1, 400)}), "low": ([(1000, 1), (7, 3)], 1010.0, {1000: 0.9, 7: 1.9})}
    rows = [(name, s, n, t, r[s]) for name, (cells, t, r) in cases.items() for s, n in cells]
    got = mixing._rounded(spark.createDataFrame(rows, "source string, size long, n long, target double, rate double")).collect()
    for name, (_, target, _) in cases.items():
        mine = [r for r in got if r.source == name]
        copies = {r.size: r.n * int(r.rate) + r.extra for r in mine}
        assert all(0 <= copies[r.size] <= 2 * r.n for r in mine)
        gap = target - sum(s * c for s, c in copies.items())
        left = [r.size for r in mine if r.size < 2 * abs(gap) and (copies[r.size] < 2 * r.n if gap > 0 else copies[r.size] > 0)]
        assert not left and abs(gap) <= 0.01 * target, (name, gap)
