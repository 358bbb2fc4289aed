from joinlearn.llm import licenses


def test_notices_texts_and_near_misses(spark):
    mit = licenses.TEMPLATES[4][1]
    rows = [(1, "prose\nReleased under the MIT License.\nmore"), (2, mit.upper().replace(",", " ")), (3, mit.replace("granted", "given")), (4, "License to walk the dog"), (5, None), (6, ""), (7, "# Licensed under CC BY-NC 4.0")]
    got = {r.doc_id: r for r in licenses.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[i].license for i in range(1, 8)] == ["MIT", "MIT", "MIT", None, None, None, "CC-BY-NC-4.0"]
    assert got[2].dice == 1.0 and 0.9 < got[3].dice < 1.0


def test_size_bounds_lose_nothing(spark):
    texts = [" ".join(t.split()[: int(len(t.split()) * f)]) + " extra words here" * k for _, t in licenses.TEMPLATES for f in (0.6, 0.8, 1.0) for k in (0, 1, 3)]
    got = {r.doc_id: r for r in licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    for i, t in enumerate(texts):
        a = set(licenses.bigrams_of(t))
        scores = [2 * len(a & set(b)) / (len(a) + len(b)) for _, x in licenses.TEMPLATES for b in [licenses.bigrams_of(x)]] if a else [0]
        best = max(scores)
        assert got[i].dice == (round(best, 6) if best >= 0.8 else 0.0)


def test_odd_rows(odd_docs, no_docs):
    assert licenses.scan(odd_docs).count() == odd_docs.count() and licenses.scan(no_docs).count() == 0
