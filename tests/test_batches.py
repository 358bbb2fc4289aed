import numpy as np
import pytest
from pyspark.sql.classic.dataframe import DataFrame

from joinlearn.baselines import design, stochastic


@pytest.fixture(scope="module")
def sparse(spark):
    made = spark.range(2_503).selectExpr("id", "CAST(id % 7 AS double) AS x", "concat('c', id % 3) AS c", "CAST(id % 11 AS double) AS y").repartition(3, "id").sortWithinPartitions("id").cache()
    return design.sparse_rows(made, ["x"], ["c"], "y")


@pytest.mark.parametrize("size", [1, 100, 5_000])
def test_batches_keep_every_row_in_order(sparse, size, monkeypatch):
    rows, width = sparse
    want = [(r.label, list(zip(r.indices, r["values"], strict=True))) for r in rows.collect()]
    real = DataFrame.toLocalIterator

    def packed(self, *a, **k):
        assert self.columns == ["part"], "rows come to the driver one by one"
        return real(self, *a, **k)

    monkeypatch.setattr(DataFrame, "toLocalIterator", packed)
    got = []
    for y, row, at, x in stochastic.batches(rows, size):
        assert len(y) == size or len(got) + len(y) == len(want)
        got += [(label, [(i + 1, v) for r, i, v in zip(row, at, x, strict=True) if r == k]) for k, label in enumerate(y)] if size < 5_000 else [(label, None) for label in y]
    assert width == 4 and [g[0] for g in got] == [w[0] for w in want]
    assert size == 5_000 or got == want


def test_epoch_equals_steps_by_hand(sparse):
    rows, width = sparse
    z, n = np.zeros(width + 1), np.zeros(width + 1)
    data = rows.collect()
    for low in range(0, len(data), 500):
        part = data[low : low + 500]
        w, g = -z / ((1.0 + np.sqrt(n)) / 0.1), np.zeros(width + 1)
        for r in part:
            at = np.array(r.indices)
            e = w[0] + np.array(r["values"]) @ w[at] - r.label
            g[0] += e
            g[at] += e * np.array(r["values"])
        g /= len(part)
        z, n = z + g - (np.sqrt(n + g * g) - np.sqrt(n)) / 0.1 * w, n + g * g
    got, count = stochastic.sgd_ftrl(rows, width, 500)
    assert count == 6 and np.allclose(got, -z / ((1.0 + np.sqrt(n)) / 0.1))


def test_experiment_sends_packed_batches(spark, sf, monkeypatch):
    from joinlearn import experiments

    seen, real = [], DataFrame.toLocalIterator
    monkeypatch.setattr(DataFrame, "toLocalIterator", lambda self, *a, **k: seen.append(self.columns) or real(self, *a, **k))
    got = experiments.minibatch_sizes(spark, sf).collect()
    assert seen and all(c == ["part"] for c in seen) and sorted({(r.batch, r.batches) for r in got}) == [(100, 60), (1000, 6), (10_000, 1)]
