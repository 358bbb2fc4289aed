import hashlib
import re

import numpy as np

from joinlearn.llm import common, decontam, queries


def words(t):
    t = "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", t)


def brute(text, items, window=10):
    ws, hit, found = words(text), set(), set()
    for name, body in items:
        b = words(body)
        n = min(window, len(b))
        if not n:
            continue
        grams = {tuple(b[i : i + n]) for i in range(len(b) - n + 1)}
        for i in range(len(ws) - n + 1):
            if tuple(ws[i : i + n]) in grams:
                hit |= set(range(i, i + n))
                found.add(str(name))
    return len(ws), len(hit), sorted(found)


def longest(text, items, window=10):
    """Longest common run of words with each item that shares a window, by all pairs of places."""
    ws, best = words(text), {}
    for name, body in items:
        b = words(body)
        least = min(window, len(b))
        for i in range(len(ws)):
            for j in range(len(b)):
                n = 0
                while i + n < len(ws) and j + n < len(b) and ws[i + n] == b[j + n]:
                    n += 1
                if least and n >= least and n > best.get(str(name), (0, 0))[1]:
                    best[str(name)] = i, n
    return sorted(((k, *v) for k, v in best.items()), key=lambda x: (x[1], x[0]))


def test_suffix_array_is_sorted():
    rng = np.random.default_rng(0)
    block = decontam.Block([("i", " ".join(map(str, rng.integers(0, 3, 300)))), ("j", "0 1 2")], 4)
    ids = np.array([block.vocabulary[str(x).encode()] for x in rng.integers(0, 3, 500)])
    for size, (order, names) in block.suffix_array(ids).items():
        keys = [tuple(ids[i : i + size]) for i in order]
        assert keys == sorted(keys) and all((a == b) == (m == n) for a, b, m, n in zip(keys, keys[1:], names, names[1:], strict=False))


def test_longest_matches_are_those_of_one_place(monkeypatch):
    a = [f"w{i}" for i in range(30)]
    item = " ".join([*a[:12], "gap", *a[10:22]])
    text = " ".join(["x", *a[:15], "y"])
    (_, _, found), = decontam.Block([("1", item)]).search([decontam.words_of(text)])
    assert found == [("1", 1, 12)]  # the windows of both places make 15 words in a row, no place of the item has more than 12
    import random

    rng = random.Random(7)
    for pairs in (2_000_000, 5, 40):
        monkeypatch.setattr(decontam, "PAIRS", pairs)
        items = [(str(i), " ".join(rng.choices("abc", k=rng.choice([0, 3, 9, 12, 40])))) for i in range(6)] + [("same", "a " * 25)]
        docs = [" ".join(rng.choices("abc", k=n)) + " " + items[n % 6][1] for n in (5, 200, 90)] + ["a " * 60]
        for d, (_, names, got) in zip(docs, decontam.Block(items).search([decontam.words_of(d) for d in docs]), strict=True):
            assert got == longest(d, items) and names == sorted(i for i, *_ in got)


def test_query_matches_brute_force(spark, sf):
    items = [(r.item_id, r.text) for r in common.table(spark, sf, "benchmark").collect()]
    docs = {r.doc_id: r.text for r in common.table(spark, sf, "documents").collect()}
    for r in queries.op5_decontaminate(spark, sf).collect():
        n, hit, found = brute(docs[r.doc_id], items)
        assert (r.n_words, r.n_hit, r.n_items) == (n, hit, len(found))
        assert r.items_sha256 == hashlib.sha256(",".join(found).encode()).hexdigest() and r.contaminated == (hit > 0)


def test_short_items_overlaps_blocks_and_lengths(spark, monkeypatch):
    items = [(1, "alpha beta"), (2, "Alpha, beta gamma"), (3, ""), (4, None), (5, " ".join(f"w{i}" for i in range(30))), (None, "omega")]
    docs = spark.createDataFrame([(1, "x ALPHA beta y alpha-beta gamma"), (2, "w5 " + " ".join(f"w{i}" for i in range(3, 25)) + " end"), (3, None), (4, "nothing"), (5, "the omega")], "doc_id long, text string")
    bench = spark.createDataFrame(items, "item_id long, text string")
    plain = {r.doc_id: r for r in decontam.contaminated(docs, bench).collect()}
    assert plain[1].items == ["1", "2"] and sum(s.end - s.start for s in plain[1].spans) == 5
    assert max(m.words for m in plain[2].longest) == 22 and plain[5].items == [""]
    monkeypatch.setattr(decontam, "BLOCK_BYTES", 80)
    monkeypatch.setattr(decontam.blocks_of, "__defaults__", ("item_id", "text", 80))
    parts = {r.doc_id: r for r in decontam.contaminated(docs, bench).collect()}
    assert all(parts[i].items == plain[i].items and parts[i].spans == plain[i].spans for i in plain)
    assert {r.doc_id for r in decontam.remove(docs, bench).collect()} == {3, 4}


def test_odd_rows(odd_docs, no_docs, spark):
    bench = spark.createDataFrame([(1, "hello world this is")], "item_id long, text string")
    assert decontam.contaminated(odd_docs, bench).count() == odd_docs.count()
    kept = decontam.remove(odd_docs, bench)
    assert kept.columns == odd_docs.columns and kept.count() == odd_docs.count() - 2
    assert decontam.remove(no_docs, bench).count() == 0 and decontam.remove(odd_docs, bench.limit(0)).count() == odd_docs.count()


def test_documents_beyond_a_shard(monkeypatch):
    import random

    rng = random.Random(4)
    items = [(str(i), " ".join(rng.choices("abcde", k=rng.choice([3, 9, 12, 15])))) for i in range(6)]
    docs = [" ".join(rng.choices("abcde", k=n)) + " " + items[n % 6][1] for n in (5, 200, 90)]
    monkeypatch.setattr(decontam, "SHARD_WORDS", 40)
    got = decontam.Block(items).search([decontam.words_of(d) for d in docs])
    for d, (spans, found, _) in zip(docs, got, strict=True):
        n, hit, want = brute(d, items)
        assert sum(b - a for a, b in spans) == hit and found == want
