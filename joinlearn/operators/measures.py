"""Measures: sizes of the join, counts of features and aggregates, timings and ratios."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.monomials import ONE
from ..plans.order import VariableOrder
from ..plans.query import FeatureQuery
from ..plans.views import Views
from .dealt import trimmed


def count_query(query: FeatureQuery, order: VariableOrder | None = None, eager=None) -> DataFrame:
    """(n): rows of the join, from pushed-down counts."""
    return next(Views(query, order or VariableOrder.suggest(query), eager).roots([ONE]))[2].select(F.coalesce("m0", F.lit(0.0)).cast("long").alias("n"))


def listing_size(query: FeatureQuery, order: VariableOrder | None = None) -> int:
    return count_query(query, order).first().n * len(query.variables())


def semi_reduced(query: FeatureQuery, rounds: int = 2) -> dict[str, DataFrame]:
    """Relations without dangling rows: semi-joins along shared variables, forth and back."""
    rel = {r: query.bound(r) for r in query.relations}
    names = list(rel)
    for _ in range(rounds):
        for order in (names, names[::-1]):
            for i, a in enumerate(order):
                for b in order[:i]:
                    on = [c for c in rel[a].columns if c in rel[b].columns]
                    if on:
                        rel[a] = rel[a].join(rel[b].select(*on).distinct(), on, "left_semi")
    return rel


def factorized_sizes(query: FeatureQuery, order: VariableOrder) -> DataFrame:
    """(variable, n): distinct values of each variable for each assignment of what it depends on, over the join."""
    rel, deps = semi_reduced(query, 1), order.validate(query).dependencies(query)
    parts = []
    for v in order.parent:
        wanted = [*deps[v], v]
        owner = next((r for r in rel if set(wanted) <= set(rel[r].columns)), None)
        rows = rel[owner] if owner else query.listing()
        parts.append(rows.select(*wanted).distinct().agg(F.count(F.lit(1)).alias("n")).select(F.lit(v).alias("variable"), "n"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def compression(query: FeatureQuery, order: VariableOrder) -> DataFrame:
    """(listing, factorized, ratio)."""
    f = factorized_sizes(query, order).agg(F.sum("n").alias("factorized"))
    n = count_query(query, order).select((F.col("n") * len(query.variables())).alias("listing"))
    return n.crossJoin(f).select("listing", "factorized", F.round(F.col("listing") / F.col("factorized"), 6).alias("ratio"))


def variable_counts(query: FeatureQuery, order: VariableOrder, grouped: bool = False) -> DataFrame:
    """One count a variable over the join: its rows, or (grouped) how many distinct values it has there."""
    total = count_query(query, order)
    rel = semi_reduced(query)
    parts = []
    for v in query.variables():
        if grouped:
            owner = next(r for r in rel if v in rel[r].columns)
            parts.append(rel[owner].agg(F.count_distinct(v).alias("n")).select(F.lit(v).alias("variable"), "n"))
        else:
            parts.append(total.select(F.lit(v).alias("variable"), "n"))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def dangling(query: FeatureQuery, relation: str, other: str) -> DataFrame:
    """Rows of a relation that meet none of another."""
    a, b = query.bound(relation), query.bound(other)
    on = [c for c in a.columns if c in b.columns]
    return a.join(b.select(*on), on, "left_anti")


def sparsity_gain(width: int, entries: int) -> float:
    """Dense index pairs (upper half with diagonal) for each stored aggregate."""
    return width * (width + 1) / 2 / max(1, entries)


def expected_lr_entries(onehot: int, continuous: int, pairs: int) -> int:
    """Grouped aggregates of linear regression: a count, the response and each continuous sum a level, and occurring pairs."""
    return onehot * (continuous + 2) + pairs


def expected_scalars(continuous: int) -> int:
    n = continuous + 1
    return (n + 1) * (n + 2) // 2


def speedup(join: float, export: float, learn: float, aggregate: float, converge: float) -> float:
    return (join + export + learn) / (aggregate + converge)


def timed(action: Callable) -> tuple[object, float]:
    began = time.time()
    return action(), time.time() - began


def release(spark: SparkSession) -> None:
    """Let go of the shuffle files of plans that nothing refers to any more, and of freed memory, before the next large plan
    makes its own."""
    trimmed(spark)


def time_noop(df: DataFrame) -> float:
    return timed(lambda: df.write.format("noop").mode("overwrite").save())[1]


def status_of(action: Callable, timeout_s: float | None = None) -> tuple[str, object]:
    """('ok', result), or a marker of what a method ran into: 'limit', 'memory', 'rank', 'diverged'."""
    from ..baselines.design import DesignLimitError, RankError

    try:
        got = action()
    except DesignLimitError:
        return "limit", None
    except RankError:
        return "rank", None
    except MemoryError:
        return "memory", None
    except FloatingPointError:
        return "diverged", None
    return "ok", got


def table_of(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)
