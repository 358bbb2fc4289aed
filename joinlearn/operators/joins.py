"""Joins that features need and Spark lacks as operators: as-of and banded joins, and a reduced cyclic bag."""

from __future__ import annotations

import math
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def as_of(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """left with the last right value at or before its time, by key: one sort of both sides, no pairs.

    Ties at one time: the largest value. No earlier row gives null."""
    a = left.select("*", F.lit(1).alias("__side"), F.lit(None).cast(right.schema[value].dataType).alias("__v"))
    own = [c for c in left.columns if c not in (key, time)]
    b = right.groupBy(key, time).agg(F.max(value).alias("__v")).select(key, time, *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in own], F.lit(0).alias("__side"), "__v")
    both = a.unionByName(b)
    last = F.last("__v", ignorenulls=True).over(Window.partitionBy(key).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn(f"{value}_as_of", last).where("__side = 1").select(*left.columns, f"{value}_as_of")


def banded(left: DataFrame, right: DataFrame, left_at: str, right_at: str, width: float) -> DataFrame:
    """Pairs whose positions differ by at most width: an equi-join on bands with the neighbours, then the exact test."""
    a = left.withColumn("__band", F.floor(F.col(left_at) / width))
    b = right.withColumn("__band", F.explode(F.array(*[F.floor(F.col(right_at) / width) + d for d in (-1, 0, 1)])))
    return a.join(b, "__band").where(F.abs(F.col(left_at) - F.col(right_at)) <= width).drop("__band")


#: Edges of each relation that one cell of `triangles` is to hold.
CELL = 2_000_000


def triangles(r: DataFrame, s: DataFrame, t: DataFrame, rows: int | None = None) -> DataFrame:
    """(n): results of the cyclic join R(a,b), S(b,c), T(a,c), each a set, over whole numbers; a null joins nothing.

    Each variable's values are dealt into k parts; a cell of the k^3 meets the edges of its parts. An edge goes to the k cells that
    differ in the variable it lacks, so nothing is moved but edges: no pairs of them are. rows: about how many edges there are."""
    k = max(1, math.ceil(math.sqrt((rows if rows is not None else max(x.count() for x in (r, s, t))) / CELL)))
    kinds = [x.select(F.lit(i).cast("byte").alias("kind"), F.col(p).cast("long").alias("x"), F.col(q).cast("long").alias("y")) for i, (x, p, q) in enumerate(((r, "a", "b"), (s, "b", "c"), (t, "a", "c")))]
    edges = reduce(DataFrame.unionByName, kinds).where("x IS NOT NULL AND y IS NOT NULL")
    hx, hy = (F.pmod(F.xxhash64(c), F.lit(k)).cast("int") for c in ("x", "y"))
    free = F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("free")
    dealt = edges.select("kind", "x", "y", hx.alias("hx"), hy.alias("hy"), free)
    cell = F.expr(f"CASE kind WHEN 0 THEN (hx * {k} + hy) * {k} + free WHEN 1 THEN (free * {k} + hx) * {k} + hy ELSE (hx * {k} + free) * {k} + hy END")
    return dealt.select(cell.alias("cell"), "kind", "x", "y").groupBy("cell").applyInArrow(_closed, "n long").agg(F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("n"))


def _pairs(x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct pairs in order."""
    order = np.lexsort((y, x))
    x, y = x[order], y[order]
    new = np.r_[True, (x[1:] != x[:-1]) | (y[1:] != y[:-1])] if len(x) else np.zeros(0, bool)
    return x[new], y[new]


def _closed(edges: pa.Table) -> pa.Table:
    """Triangles of one cell: for each a, its b's with its c's, looked up among the pairs (b, c)."""
    kind, x, y = (edges[c].to_numpy() for c in ("kind", "x", "y"))
    (ra, rb), (sb, sc), (ta, tc) = (_pairs(x[kind == i], y[kind == i]) for i in range(3))
    if not (len(ra) and len(sb) and len(ta)):
        return pa.table({"n": pa.array([0], pa.int64())})
    bs, cs = np.unique(sb), np.unique(sc)
    known = np.searchsorted(bs, sb) * len(cs) + np.searchsorted(cs, sc)  # in order, as sb and sc are
    keep = np.isin(rb, bs)
    ra, rb = ra[keep], np.searchsorted(bs, rb[keep])
    keep = np.isin(tc, cs) & np.isin(ta, ra)
    ta, tc = ta[keep], np.searchsorted(cs, tc[keep])
    first, last = np.searchsorted(ra, ta, "left"), np.searchsorted(ra, ta, "right")
    ends, n, low = np.cumsum(last - first), 0, 0
    while low < len(ta):  # about a million pairs at once; those of one edge (a, c) are together
        done = int(ends[low - 1]) if low else 0
        high = max(low + 1, int(np.searchsorted(ends, done + 1_000_000, "right")))
        size = last[low:high] - first[low:high]
        at = np.arange(size.sum()) - np.repeat(ends[low:high] - size - done, size) + np.repeat(first[low:high], size)
        code = rb[at] * len(cs) + np.repeat(tc[low:high], size)
        place = np.minimum(np.searchsorted(known, code), len(known) - 1)
        n += int((known[place] == code).sum())
        low = high
    return pa.table({"n": pa.array([n], pa.int64())})
