from itertools import product
from random import Random

from joinlearn.operators import joins


def test_triangles_move_edges_not_pairs(spark, monkeypatch):
    rng = Random(3)
    made = [[(rng.randrange(12), rng.randrange(12)) for _ in range(90)] + [(None, 1), (2, None)] for _ in range(3)]
    r, s, t = map(set, made)
    want = sum((a, b) in r and (b, c) in s and (a, c) in t for a, b, c in product(range(12), repeat=3))
    frames = [spark.createDataFrame(rows, f"{names[0]} long, {names[1]} long") for rows, names in zip(made, ("ab", "bc", "ac"), strict=True)]
    for cell in (2_000_000, 10):
        monkeypatch.setattr(joins, "CELL", cell)
        found = joins.triangles(*frames)
        assert found.first().n == want > 0
        assert "Join" not in found._jdf.queryExecution().executedPlan().toString()
    none = joins.triangles(frames[0].where("a > 99"), *frames[1:])
    assert none.first().n == 0
