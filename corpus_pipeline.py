"""A corpus pipeline of five stages over `documents`; each works on all that the one before it kept.

Defined results of every stage: an empty table gives an empty one; nulls, empty and very long texts, ties, repeated rows and
extra columns are handled as the stage's operator says in its docstring. What a stage writes in the shared folder is deleted
once the next stage's rows are written."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from joinlearn.llm import common, decontam, mixing, sharding, simhash, toxicity


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity model rejects go. It learns from labelled rows of docs outside the held-out third."""
    marks = common.table(spark, sf_dir, "labels").where(common.crc_mod("doc_id", 3) != 1)
    model = toxicity.learn(docs, marks)
    return toxicity.accepted(docs, model)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each component of linked fingerprints stays; texts without words are one component."""
    return simhash.deduplicate(docs)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text holds a window of a benchmark item go; rows without words stay."""
    return decontam.remove(docs, common.table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as the mix takes it."""
    return mixing.replicated(docs)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row with its shard, slot and the law; repeated rows get slots of their own."""
    return sharding.shard_rows(docs)


STAGES = [("toxicity", drop_toxic), ("near_duplicates", drop_near_duplicates), ("decontamination", drop_benchmark), ("mixing", mix_sources), ("sharding", shard)]

#: The toxicity model is learned, which SQL cannot express; tests hold every stage against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    mine: list[str] = []
    for at, (_, stage) in enumerate(STAGES):
        before = common.written()
        docs = stage(spark, docs, sf_dir)
        if at < len(STAGES) - 1:
            docs = common.cut(docs)
            made = [p for p in common.written() if p not in before]
            common.drop_written(spark, [*mine, *made[:-1]])  # the last one holds this stage's rows
            mine = made[-1:]
    return docs
