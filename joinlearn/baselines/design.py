"""Design matrices: one-hot encoding, zero-suppressed rows, and the limits that competing tools run into."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


class DesignLimitError(ValueError):
    """More columns or values than a tool can hold."""


class RankError(ValueError):
    """A design (or one chunk of it) whose columns are dependent."""


def levels_of(df: DataFrame, name: str) -> list:
    return [r[0] for r in df.select(name).distinct().orderBy(name).collect()]


def onehot_encode(df: DataFrame, cats: list[str], drop_first: bool = False, max_columns: int | None = None) -> tuple[DataFrame, list[str]]:
    """Categories as 0/1 columns, JVM-side. The dictionary is one distinct a category; max_columns guards it."""
    made, names = [], []
    for c in cats:
        found = levels_of(df, c)[1 if drop_first else 0 :]
        if max_columns is not None and len(names) + len(found) > max_columns:
            raise DesignLimitError(f"{c} takes the design over {max_columns} columns")
        for i, v in enumerate(found):
            names.append(f"{c}__{i}")
            made.append(F.when(F.col(c).eqNullSafe(F.lit(v)), 1.0).otherwise(0.0).alias(names[-1]))
    return df.select(*[c for c in df.columns if c not in cats], *made), names


def dictionaries(df: DataFrame, cats: list[str]) -> DataFrame:
    """(attribute, level, code): dense codes by attribute, then level."""
    each = [F.struct(F.lit(i).alias("at"), F.lit(c).alias("attribute"), F.col(c).cast("string").alias("level")) for i, c in enumerate(cats)]
    rows = df.select(F.explode(F.array(*each)).alias("e")).select("e.*").distinct()
    return rows.withColumn("code", F.row_number().over(Window.orderBy("at", "level"))).select("attribute", "level", "code")


def to_sparse_rows(df: DataFrame, continuous: list[str], cats: list[str], response: str, codes: DataFrame | None = None) -> DataFrame:
    """(label, indices, values) with 1-based indices, continuous columns first, zeros left out. codes: dictionaries that are at hand."""
    codes = dictionaries(df, cats) if cats and codes is None else codes
    out, parts = df, [(F.lit(i + 1), F.col(c).cast("double")) for i, c in enumerate(continuous)]
    for k, c in enumerate(cats):
        mine = codes.where(F.col("attribute") == c).select(F.col("level").alias(f"__l{k}"), (F.col("code") + len(continuous)).alias(f"__i{k}"))
        out = out.join(mine, out[c].cast("string").eqNullSafe(F.col(f"__l{k}")))
        parts.append((F.col(f"__i{k}"), F.lit(1.0)))
    pairs = F.filter(F.array(*[F.struct(i.cast("int").alias("i"), v.alias("v")) for i, v in parts]), lambda p: p.v != 0)
    return out.select(F.col(response).cast("double").alias("label"), F.transform(pairs, lambda p: p.i).alias("indices"), F.transform(pairs, lambda p: p.v).alias("values"))


def sparse_rows(df: DataFrame, continuous: list[str], cats: list[str], response: str) -> tuple[DataFrame, int]:
    """`to_sparse_rows` and the number of slots; the dictionaries are made once and go to every task."""
    found = dictionaries(df, cats).toArrow()
    codes = df.sparkSession.createDataFrame(found)
    return to_sparse_rows(df, continuous, cats, response, F.broadcast(codes)), len(continuous) + found.num_rows
