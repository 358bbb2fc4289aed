import zlib

import numpy as np

from joinlearn.llm import common, queries, sharding


def test_permutation_is_one_for_any_size():
    for n in (1, 2, 3, 7, 100, 1023, 1024, 1025, 50_000):
        got = sharding.permute(np.arange(n), n, 5)
        assert sorted(got) == list(range(n))
    assert list(sharding.permute(np.arange(100), 100, 1)) != list(sharding.permute(np.arange(100), 100, 2))


def test_query_law_and_digests(spark, sf01):
    rows = queries.op3_shards(spark, sf01).toPandas()
    docs = {r.doc_id: r.text or "" for r in common.table(spark, sf01, "documents").collect()}
    counts = rows.groupby("shard").size()
    assert counts.max() - counts.min() <= 1 and len(counts) == 16 and len(rows) == len(docs)
    assert all(sorted(g) == list(range(len(g))) for _, g in rows.groupby("shard").slot)
    for r in rows.itertuples():
        t = docs[r.doc_id].encode()
        assert r.size == len(t) + 1 and r.text_crc32 == zlib.crc32(t)
    again = queries.op3_shards(spark.newSession(), sf01).toPandas()
    assert rows.sort_values("doc_id").reset_index(drop=True).equals(again.sort_values("doc_id").reset_index(drop=True))


def test_odd_rows(odd_docs, no_docs):
    n = odd_docs.count()
    rows = sharding.assignments(odd_docs, 4).collect()
    assert sorted(r.row_number for r in rows) == list(range(n))
    whole = sharding.shard_rows(odd_docs, 4)
    assert whole.count() == n and len(whole.columns) == len(set(whole.columns))
    assert sorted((r.shard, r.slot) for r in whole.collect()) == sorted((r.shard, r.slot) for r in rows)
    assert sharding.assignments(no_docs).count() == 0 and sharding.shard_rows(no_docs).count() == 0


def test_rows_without_ids_and_hot_copies(spark, monkeypatch):
    """A third of the rows has no id, another third is one row over and over."""
    monkeypatch.setattr(sharding, "SPREAD", 7)
    rows = [(None, f"text {i}", i) for i in range(200)] + [(5, "same", 1)] * 190 + [(5, "same", 2)] * 10 + [(i, "own", 0) for i in range(200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, extra int")
    keys = docs.select("doc_id", sharding.size_of().alias("size"), sharding.crc_of().alias("text_crc32"))
    starts, total = sharding.numbered(keys, ["doc_id", "size", "text_crc32"], 64)
    assert total == 600 and starts.where("doc_id is null").selectExpr("pmod(xxhash64(doc_id, size, text_crc32), 64) b").distinct().count() > 30
    whole = sharding.shard_rows(docs, 4).collect()
    assert sorted((r.text, r.extra, r.doc_id or -1) for r in whole) == sorted((t, e, i or -1) for i, t, e in rows)
    assert sorted((r.shard, r.slot) for r in whole) == [(s, n) for s in range(4) for n in range(150)]


def test_places_follow_the_permutation(spark, sf):
    rows = sharding.assignments(common.table(spark, sf, "documents")).toPandas()
    at = sharding.permute(rows.row_number.to_numpy(), len(rows), 42)
    assert sorted(rows.row_number) == list(range(len(rows))) and (rows.shard == at % 16).all() and (rows.slot == at // 16).all()
