"""Row-wise forms of the models: a vectorised scorer for wide factorization machines, and monomial expansion as a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .models import FactorizationMachine


def fm_scores(model: FactorizationMachine, theta: np.ndarray, rows: DataFrame, name: str = "prediction") -> DataFrame:
    """rows with FM predictions in time linear in attributes times rank, the model broadcast (its size is the parameter count).

    The pair term is taken over attributes: half of (square of the factor sum less the sum of factor squares), without the
    squares of single attributes. Pairs of levels that training never saw together contribute by their factors."""
    w, v = model.split(theta)
    lay, query = model.layout, model.query
    singles = [m for m in model.h if m.degree == 1]
    shared = rows.sparkSession.sparkContext.broadcast(
        (w, v, [(m.cont[0][0] if m.cont else m.cats[0], bool(m.cats), lay.offset[m], {k[0]: i for i, k in enumerate(lay.keys_of(m))} if m.cats else None) for m in singles])
    )

    @F.pandas_udf("double")
    def score(parts: Iterator[pd.DataFrame]) -> Iterator[pd.Series]:
        w, v, attributes = shared.value
        for df in parts:
            total, sums, squares = np.full(len(df), w[0]), np.zeros((len(df), v.shape[1])), np.zeros(len(df))
            for column, categorical, offset, places in attributes:
                if categorical:
                    at = np.array([places.get(x, -1) for x in df[column].tolist()])
                    x = (at >= 0).astype(float)
                    at = np.maximum(at, 0) + offset
                else:
                    x, at = df[column].to_numpy(float), np.full(len(df), offset)
                f = v[at - 1] * x[:, None]
                total += w[at] * x
                sums += f
                squares += (f**2).sum(1)
            yield pd.Series(total + 0.5 * ((sums**2).sum(1) - squares))

    return rows.withColumn(name, score(F.struct(*query.features)))


def expand(row_features: list[tuple[str, Column]], degree: int = 2) -> Column:
    """All products of at most two named features of a row as an array of (monomial, value), for exploding: built-in functions only."""
    out = [F.struct(F.lit("1").alias("monomial"), F.lit(1.0).alias("value"))]
    for i, (a, x) in enumerate(row_features):
        out.append(F.struct(F.lit(a).alias("monomial"), x.cast("double").alias("value")))
        if degree == 2:
            out += [F.struct(F.lit(f"{a}*{b}" if a != b else f"{a}^2").alias("monomial"), (x * y).cast("double").alias("value")) for b, y in row_features[i:]]
    return F.array(*out)
