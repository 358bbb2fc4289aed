import re

from joinlearn.llm import common, quality, queries


def brute(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text)
    lines, seen, dup = text.split("\n"), set(), 0
    for x in lines:
        if re.search(r"[^\x20\x09-\x0D]", x):
            dup += x in seen
            seen.add(x)
    grams = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    hit = set()
    for i, g in enumerate(grams):
        if grams.count(g) > 1:
            hit |= {i, i + 1, i + 2}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), dup, len(hit)


def test_features_match_brute_force(spark, sf):
    texts = ["", " ", "a b c a b c a b c", "a\na\n\n\nb\x1cb c", "x " * 10, "#$ <b> a b c d a b c"] + [r.text for r in common.table(spark, sf, "documents").limit(60).collect() if r.text and len(r.text) < 3000]
    for t in texts:
        assert quality.features(t) == brute(t), t


def test_hosts_are_shrunk_and_joined(spark):
    good, bad = " ".join(f"w{i}" for i in range(80)), "too short"
    rows = [(i, good, "fine") for i in range(200)] + [(1000 + i, bad if i < 190 else good, "poor") for i in range(200)] + [(2000, bad, "tiny"), (2001, good, None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r.doc_id: r for r in quality.judge(docs).collect()}
    assert got[0].kept and not got[1199].kept and not got[1199].base_failed and got[2001].kept and not got[2000].kept
    rate = got[2000].shrunk_rate
    assert 0 < rate < 1


def test_clean_documents_stay(spark, sf01):
    rows = queries.op4_host_quality(spark, sf01).collect()
    assert all(r.kept != r.base_failed for r in rows)


def test_odd_rows(odd_docs, no_docs):
    assert quality.judge(odd_docs).count() == odd_docs.count() and quality.judge(no_docs).count() == 0


def test_long_texts_count_alike():
    import random

    for seed in range(20):
        ws = random.Random(seed).choices("abcd", k=60)
        assert quality.repeated_words([w.encode() for w in ws]) == brute(" ".join(ws))[4]
