"""Competing least-squares learners over the materialised, encoded join."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .design import DesignLimitError, RankError

VALUE_LIMIT = 2**31 - 1
COLUMN_LIMIT = 1600
_FLAT = T.StructType([T.StructField("n", T.LongType()), T.StructField("flat", T.ArrayType(T.DoubleType()))])
_ARROW = to_arrow_schema(_FLAT)


def _matrix(batch: pa.RecordBatch) -> np.ndarray:
    return np.column_stack([np.ones(batch.num_rows), *(c.to_numpy(zero_copy_only=False).astype(float) for c in batch.columns)])


def _row(n: int, m: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([m.ravel()], _ARROW.field("flat").type)], schema=_ARROW)


def gram(df: DataFrame, columns: list[str], response: str) -> tuple[float, np.ndarray]:
    """Row count and Gram matrix of [1, columns, response]; tasks add up their batches, then entries are summed by place."""

    def task(batches):
        total, n = None, 0
        for b in batches:
            if b.num_rows:
                x = _matrix(b)
                total = x.T @ x if total is None else total + x.T @ x
                n += b.num_rows
        if total is not None:
            yield _row(n, total)

    k = len(columns) + 2
    partial = df.select(*columns, response).mapInArrow(task, _FLAT)
    got = partial.select("n", F.posexplode("flat").alias("at", "v")).groupBy("at").agg(F.sum("v").alias("v"), F.sum("n").alias("n")).toPandas()
    g = np.zeros(k * k)
    g[got["at"].to_numpy(np.int64)] = got["v"].to_numpy(float)
    return (float(got["n"].max()) if len(got) else 0.0), g.reshape(k, k)


def closed_form(df: DataFrame, columns: list[str], response: str, lam: float = 0.0, max_columns: int = COLUMN_LIMIT) -> np.ndarray:
    """Ordinary or ridge least squares from the normal equations; least-norm where columns are dependent."""
    if len(columns) + 1 > max_columns:
        raise DesignLimitError(f"{len(columns) + 1} columns, at most {max_columns}")
    n, g = gram(df, columns, response)
    a, c = g[:-1, :-1] / n, g[:-1, -1] / n
    return np.linalg.solve(a + lam * np.eye(len(a)), c) if lam else np.linalg.lstsq(a, c, rcond=1e-12)[0]


def by_qr(df: DataFrame, columns: list[str], response: str, value_limit: int = VALUE_LIMIT, rank_tol: float = 1e-9) -> np.ndarray:
    """Least squares from tall-skinny QR: each task keeps one triangle, triangles merge in rounds of eight."""
    rows = df.count()
    if rows * (len(columns) + 1) > value_limit:
        raise DesignLimitError(f"{rows * (len(columns) + 1)} values, at most {value_limit}")
    k = len(columns) + 2

    def first(batches):
        r, n = None, 0
        for b in batches:
            if b.num_rows:
                x = _matrix(b)
                r = np.linalg.qr(x if r is None else np.vstack([r, x]), mode="r")
                n += b.num_rows
        if r is not None:
            yield _row(n, np.vstack([r, np.zeros((k - len(r), k))]))

    def merge(batches):
        parts, n = [], 0
        for b in batches:
            parts += [np.array(x).reshape(k, k) for x in b.column(1).to_pylist()]
            n += sum(b.column(0).to_pylist())
        if parts:
            r = np.linalg.qr(np.vstack(parts), mode="r")
            yield _row(n, np.vstack([r, np.zeros((k - len(r), k))]))

    tri = df.select(*columns, response).mapInArrow(first, _FLAT)
    width = tri.rdd.getNumPartitions()
    while width > 8:
        width = -(-width // 8)
        tri = tri.repartition(width).mapInArrow(merge, _FLAT)
    parts = [np.array(r.flat).reshape(k, k) for r in tri.collect()]  # eight triangles at most
    r = np.linalg.qr(np.vstack(parts), mode="r")
    a, c = r[: k - 1, : k - 1], r[: k - 1, -1]
    d = np.abs(np.diag(a))
    if (d < rank_tol * max(1.0, d.max())).any():
        raise RankError("dependent columns")
    return np.linalg.solve(a, c)


def chunk_ranks(df: DataFrame, columns: list[str], chunk_rows: int = 10_000) -> DataFrame:
    """(chunk_rows, rank, columns): numerical rank of every chunk of rows, as a disk-backed tool would meet them."""
    out = T._parse_datatype_string("n long, rank int, width int")
    arrow = to_arrow_schema(out)

    def ranks(x: np.ndarray) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([len(x)], pa.int64()), pa.array([int(np.linalg.matrix_rank(x))], pa.int32()), pa.array([x.shape[1]], pa.int32())], schema=arrow)

    def task(batches):
        held: list[np.ndarray] = []
        for b in batches:
            held.append(_matrix(b))
            while sum(map(len, held)) >= chunk_rows:
                x = np.vstack(held)
                yield ranks(x[:chunk_rows])
                held = [x[chunk_rows:]]
        x = np.vstack(held) if held else np.zeros((0, 1))
        if len(x):
            yield ranks(x)

    return df.select(*columns).mapInArrow(task, out)


def chunked(df: DataFrame, columns: list[str], response: str, chunk_rows: int = 10_000, strict: bool = True) -> np.ndarray:
    """Least squares over chunks; strict: a chunk with dependent columns ends it, as in the tool compared with."""
    if strict and not chunk_ranks(df, columns, chunk_rows).where("rank < width").isEmpty():
        raise RankError("a chunk has dependent columns")
    return closed_form(df, columns, response, max_columns=10**9)


def glm(df: DataFrame, columns: list[str], response: str, lam: float = 0.0, max_iter: int = 25) -> np.ndarray:
    """Gaussian generalised linear model, iteratively reweighted."""
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.regression import GeneralizedLinearRegression

    data = VectorAssembler(inputCols=columns, outputCol="features").transform(df.select(*columns, F.col(response).cast("double").alias("label")))
    fit = GeneralizedLinearRegression(family="gaussian", regParam=lam, maxIter=max_iter).fit(data)
    return np.array([fit.intercept, *fit.coefficients.toArray()])


def gradient_through_joins(fact: DataFrame, dimensions: list[tuple[DataFrame, str, list[str]]], features: list[str], response: str, theta: dict[str, float]) -> DataFrame:
    """(feature, gradient): one gradient of half the mean squared error over a star, without aggregates kept between runs.

    Partial predictions are made in each dimension and residual sums by key go back to it; the fact is read once a run."""
    scored = fact.withColumn("__p", F.lit(theta["1"]) + sum((F.lit(theta[f]) * F.col(f) for f in features), F.lit(0.0)))
    for dim, key, columns in dimensions:
        part = dim.select(key, sum((F.lit(theta[c]) * F.col(c) for c in columns), F.lit(0.0)).alias("__d"))
        scored = scored.join(part, key).withColumn("__p", F.col("__p") + F.col("__d")).drop("__d")
    scored = scored.withColumn("__r", F.col("__p") - F.col(response))
    n = F.count(F.lit(1))
    own = scored.agg(*[(F.sum(F.col("__r") * (F.lit(1.0) if f == "1" else F.col(f))) / n).alias(f) for f in ["1", *features]])
    out = own.select(F.explode(F.array(*[F.struct(F.lit(f).alias("feature"), F.col(f).alias("gradient")) for f in ["1", *features]])).alias("e")).select("e.*")
    total = scored.agg(n.alias("__n"))
    for dim, key, columns in dimensions:
        sums = scored.groupBy(key).agg(F.sum("__r").alias("__s")).join(dim.select(key, *columns), key)
        agg = sums.agg(*[F.sum(F.col("__s") * F.col(c)).alias(c) for c in columns]).crossJoin(F.broadcast(total))
        out = out.unionByName(agg.select(F.explode(F.array(*[F.struct(F.lit(c).alias("feature"), (F.col(c) / F.col("__n")).alias("gradient")) for c in columns])).alias("e")).select("e.*"))
    return out
