import numpy as np
import xxhash

from joinlearn.llm import common, queries, simhash


def brute_fp(text):
    t = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    ws = [w for w in t.replace("\t", " ").replace("\n", " ").replace("\v", " ").replace("\f", " ").replace("\r", " ").split(" ") if w]
    if not ws:
        return 0
    sh = [" ".join(ws[i : i + 3]) for i in range(len(ws) - 2)] or [" ".join(ws)]
    hs = [xxhash.xxh64_intdigest(s.encode(), 42) for s in sh]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def classes(values, radius=3):
    parent = list(range(len(values)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(values)):
        for j in range(i):
            if bin(values[i] ^ values[j]).count("1") <= radius:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return [find(i) for i in range(len(values))]


def test_query_matches_brute_force(spark, sf):
    docs = sorted((r.doc_id, r.text) for r in common.table(spark, sf, "documents").collect())
    fps = [brute_fp(t) for _, t in docs]
    want = {d[0]: (f"{f:016x}", docs[c][0]) for d, f, c in zip(docs, fps, classes(fps), strict=True)}
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in queries.op7_near_duplicates(spark, sf).collect()}
    assert got == want


def test_tiles_and_large_groups_lose_no_link(spark):
    rng = np.random.default_rng(3)
    seeds = rng.integers(0, 2**63, 40, dtype=np.uint64)
    values = set()
    for s in seeds:
        for _ in range(12):
            x = int(s)
            for b in rng.integers(0, 64, rng.integers(0, 4)):
                x ^= 1 << int(b)
            values.add(x)
    hot = int(seeds[0]) & ~0xFFFF
    values |= {hot | int(v) for v in rng.integers(0, 2**16, 300)}
    values = sorted(values)
    signed = np.array(values, np.uint64).view(np.int64).tolist()
    df = spark.createDataFrame([(v,) for v in signed], "fp long")
    for tile in (16, 4096):
        roots = {r.u: r.root for r in simhash.components(simhash.links(df, 3, tile)).collect()}
        got = [roots.get(v, v) for v in signed]
        want = classes(values)
        assert len({(a, b) for a, b in zip(got, want, strict=True)}) == len(set(got)) == len(set(want))


def test_long_chain_of_links(spark):
    chain = [(1 << k) - 1 for k in range(0, 63, 3)]
    df = spark.createDataFrame([(v,) for v in chain], "fp long")
    roots = simhash.components(simhash.links(df)).collect()
    assert len(roots) == len(chain) - 1 and len({r.root for r in roots}) == 1


def test_odd_rows(odd_docs, no_docs):
    rows = simhash.labelled(odd_docs).collect()
    assert len(rows) == odd_docs.count()
    kept = simhash.deduplicate(odd_docs)
    ids = sorted((r.doc_id for r in kept.collect()), key=lambda i: (i is None, i))
    assert kept.columns == odd_docs.columns
    assert ids == [1, 2, 5, 7, 7, 8, 9, None]  # 2, 3, 4 and an id-less row have no words; 5 and 6 are copies
    assert simhash.labelled(no_docs).count() == 0 and simhash.deduplicate(no_docs).count() == 0
