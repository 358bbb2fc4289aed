import corpus_pipeline
from joinlearn.llm import common, decontam, mixing, simhash
from tests.llm.test_decontam import brute
from tests.llm.test_simhash import brute_fp, classes


def test_stages_against_brute_force(spark, sf):
    docs = common.table(spark, sf, "documents")
    names = docs.columns
    clean = common.cut(corpus_pipeline.drop_toxic(spark, docs, sf))
    assert clean.columns == names
    single = common.cut(corpus_pipeline.drop_near_duplicates(spark, clean, sf))
    rows = sorted((r.doc_id, r.text) for r in clean.collect())
    fps = [brute_fp(t) for _, t in rows]
    assert {r.doc_id for r in single.collect()} == {rows[c][0] for c in classes(fps)}
    kept = common.cut(corpus_pipeline.drop_benchmark(spark, single, sf))
    items = [(r.item_id, r.text) for r in common.table(spark, sf, "benchmark").collect()]
    assert {r.doc_id for r in kept.collect()} == {r.doc_id for r in single.collect() if not brute(r.text, items)[1]}
    mixed = common.cut(corpus_pipeline.mix_sources(spark, kept, sf))
    copies = {r.doc_id: r.copies for r in mixing.mix(kept, ["doc_id"]).collect()}
    got = {r.doc_id: r["count"] for r in mixed.groupBy("doc_id").count().collect()}
    assert got == {k: v for k, v in copies.items() if v} and mixed.columns == names
    out = corpus_pipeline.shard(spark, mixed, sf).toPandas()
    sizes = out.groupby("shard").size()
    assert len(out) == mixed.count() and sizes.max() - sizes.min() <= 1
    assert out.columns.tolist() == [*names, "shard", "slot", "law"]
    assert decontam and simhash


def test_stages_on_odd_rows(spark, odd_docs, no_docs, sf):
    for docs in (odd_docs, no_docs):
        now = docs
        for _, stage in corpus_pipeline.STAGES:
            now = common.cut(stage(spark, now, sf))
        assert set(docs.columns) <= set(now.columns) | {"law"}
