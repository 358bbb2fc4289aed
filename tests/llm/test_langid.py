import numpy as np

from joinlearn.llm import common, langid, queries
from pyspark.sql import functions as F


def test_held_out_accuracy(spark, sf01):
    lang = {r.doc_id: r.lang for r in common.table(spark, sf01, "documents").collect()}
    held = [r for r in queries.op9_language(spark, sf01).collect() if r.held_out]
    assert sum(r.lang_pred == lang[r.doc_id] for r in held) / len(held) > 0.95


def test_temperature_and_sparsity():
    rng = np.random.default_rng(0)
    rows = []
    for y in (0, 1):
        for _ in range(60):
            at = np.unique(np.concatenate([rng.integers(100 * y, 100 * y + 50, 10), rng.integers(1000, 2000, 10)]))
            rows.append((at, np.full(len(at), 1 / np.sqrt(len(at))), y))
    w = langid.fit_ftrl(rows, 2, l1=0.3)
    assert (w[5000:] == 0).all() and (w[:200] != 0).any() and (w[1000:2000] == 0).mean() > 0.3
    logits = np.array([[2.0, 0.0], [0.0, 2.0], [2.0, 0.0], [2.0, 0.0]])
    assert langid.temperature(logits, np.array([0, 1, 0, 1])) > 1.0


def test_pieces_do_not_change_counts(monkeypatch):
    text = "abc déf " * 500
    whole = langid.term_counts(text)
    monkeypatch.setattr(langid, "_PIECE", 97)
    assert (langid.term_counts(text) == whole).all()


def test_odd_rows(odd_docs, no_docs):
    model = langid.learn(odd_docs, F.lit(True))
    got = langid.predict(odd_docs, model).collect()
    assert len(got) == odd_docs.count()
    assert {r.lang_pred for r in got} <= {"en", "de", "fr", "es", "und"}
    assert all(r.score == 0.0 for r in got if r.lang_pred == "und") and sum(r.lang_pred == "und" for r in got) == 5
    assert langid.predict(no_docs, langid.learn(no_docs, F.lit(True))).count() == 0
