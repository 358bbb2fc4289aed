"""Readers and writers around the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NAMES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register(spark: SparkSession, sf_dir: str) -> None:
    """Every table that is there as a temporary view of its name."""
    for name in NAMES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def renamed(df: DataFrame, **names: str) -> DataFrame:
    """Only the named columns, under new names: variable=column."""
    return df.select(*[F.col(c).alias(v) for v, c in names.items()])


def read_csv(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.csv(path, schema=schema, header=True)


def read_json(spark: SparkSession, path: str, schema: str) -> DataFrame:
    return spark.read.json(path, schema=schema)


def read_libsvm(spark: SparkSession, path: str, width: int) -> DataFrame:
    return spark.read.format("libsvm").option("numFeatures", str(width)).load(path)


def write_csv(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").csv(path, header=True)


def write_sparse(rows: DataFrame, path: str) -> None:
    """Zero-suppressed rows (label, indices, values) as text lines ``label index:value ...``."""
    pairs = F.zip_with("indices", "values", lambda i, v: F.concat_ws(":", i.cast("string"), v.cast("string")))
    rows.select(F.concat_ws(" ", F.col("label").cast("string"), F.array_join(pairs, " "))).write.mode("overwrite").text(path)


def write_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int) -> None:
    """A table bucketed and sorted by join keys, so that later joins on them need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)
