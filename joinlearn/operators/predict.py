"""Scoring rows with fitted coefficients: one join for each categorical block, broadcast only where the block is small."""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.models import Linear, coefficients
from ..plans.views import power

#: Blocks of at most so many rows are broadcast (two numbers or keys a row).
BROADCAST_ROWS = 200_000


def predict(model: Linear, theta: np.ndarray, rows: DataFrame, name: str = "prediction") -> DataFrame:
    """rows with a prediction; category combinations that training did not see contribute nothing."""
    spark, kept = rows.sparkSession, rows.columns
    by_keys: dict[tuple, list] = {}
    terms: list[Column] = []
    for m, value in coefficients(model, theta).items():
        if m.cats:
            by_keys.setdefault(m.cats, []).append((m, value))
        else:
            terms.append(F.lit(value) * reduce(lambda a, b: a * b, [power(v, e) for v, e in m.cont], F.lit(1.0)))
    out = rows
    for i, (keys, blocks) in enumerate(by_keys.items()):
        tuples = list(blocks[0][1])
        names = [f"__b{i}_{j}" for j in range(len(blocks))]
        data = [(*t, *(float(v[t]) for _, v in blocks)) for t in tuples]
        schema = ", ".join([*(f"__k{i}_{j} {rows.schema[k].dataType.simpleString()}" for j, k in enumerate(keys)), *(f"{n} double" for n in names)])
        params = spark.createDataFrame(data, schema)
        if len(data) <= BROADCAST_ROWS:
            params = F.broadcast(params)
        on = reduce(lambda a, b: a & b, [out[k].eqNullSafe(params[f"__k{i}_{j}"]) for j, k in enumerate(keys)])
        out = out.join(params, on, "left")
        terms += [F.coalesce(F.col(n), F.lit(0.0)) * reduce(lambda a, b: a * b, [power(v, e) for v, e in m.cont], F.lit(1.0)) for n, (m, _) in zip(names, blocks, strict=True)]
    return out.select(*kept, reduce(lambda a, b: a + b, terms).alias(name))


def sigma_table(sigma, spark) -> DataFrame:
    """(i, j, value): both halves of the second moments as a table."""
    import pandas as pd

    rows, cols, values = sigma.listing()
    return spark.createDataFrame(pd.DataFrame({"i": rows, "j": cols, "value": values}))


def matvec_table(sigma: DataFrame, g: DataFrame) -> DataFrame:
    """(i, value): Sigma times g(i, value), for moments beyond the driver. One shuffle by row after the join by column."""
    return sigma.join(g.select(F.col("i").alias("j"), F.col("value").alias("x")), "j").groupBy("i").agg(F.sum(F.col("value") * F.col("x")).alias("value"))
