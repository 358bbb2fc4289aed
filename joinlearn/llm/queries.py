"""Queries and SQL of the corpus operators: thin digests of what the operators return."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common, decontam, htmltext, langid, licenses, mixing, quality, secrets, sharding, simhash, toxicity


def op1_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = secrets.find_secrets(common.table(spark, sf_dir, "documents"))
    text = lambda s: F.concat_ws(":", s.kind, s.start, s.end)
    base = F.filter("spans", lambda s: s.kind.isin(*secrets.BASE))
    number = lambda k: F.size(F.filter("spans", lambda s: s.kind == k)).cast("long")
    return rows.select(
        "doc_id",
        *[number(k).alias(f"n_{k}") for k in secrets.BASE],
        F.sha2(F.concat_ws(",", F.transform(base, text)), 256).alias("base_sha256"),
        F.concat_ws(",", F.transform("spans", text)).alias("spans"),
        F.round(F.coalesce(F.array_max(F.transform("spans", lambda s: s.score)), F.lit(0.0)), 6).alias("top_score"),
    )


def op2_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = htmltext.extract(common.table(spark, sf_dir, "pages"))
    return rows.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))


def op3_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = sharding.assignments(common.table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op4_host_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = quality.judge(common.table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", F.round("shrunk_rate", 9).alias("host_rate"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = decontam.contaminated(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))
    hit = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s.end - s.start)
    return rows.select(
        "doc_id",
        "n_words",
        hit.alias("n_hit"),
        F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", "items"), 256).alias("items_sha256"),
        (hit > 0).alias("contaminated"),
        F.coalesce(F.array_max(F.transform("longest", lambda m: m["words"])), F.lit(0)).cast("long").alias("longest_match"),
    )


def op6_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(common.table(spark, sf_dir, "documents"))


def op7_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = simhash.labelled(common.table(spark, sf_dir, "documents"))
    return rows.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    held = common.crc_mod("doc_id", 3) == 1
    model = toxicity.learn(docs, common.table(spark, sf_dir, "labels").where(~held))
    rows = toxicity.score(docs, model, ["doc_id"])
    return rows.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= toxicity.THRESHOLD).cast("int").alias("predicted"))


def op9_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    held = common.crc_mod("doc_id", 4) == 2
    rows = langid.predict(docs, langid.learn(docs, ~held))
    return rows.select("doc_id", held.alias("held_out"), "lang_pred", "score")


def op10_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mixing.mix(common.table(spark, sf_dir, "documents"), ["doc_id"])
    return rows.select("doc_id", "size", "source_size", "target", (F.col("copies") * F.col("size")).cast("long").alias("taken"), "copies")


def queries() -> dict:
    ops = (op1_secrets, op2_main_text, op3_shards, op4_host_quality, op5_decontaminate, op6_licenses, op7_near_duplicates, op8_toxicity, op9_language, op10_mix)
    return {f.__name__: f for f in ops}


def oracle_sql() -> dict[str, str]:
    return {"op4_host_quality": quality.oracle(), "op5_decontaminate": decontam.oracle(), "op6_licenses": licenses.oracle()}
