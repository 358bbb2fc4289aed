"""Reproducible shuffle into shards by a Feistel permutation with cycle walking over global row numbers.

Law ``rows``: row number n of N becomes position P(n) of N, shard = position mod shards, slot = position div shards, so
shard sizes differ by one row at most, slots have no gaps, and both are computable from the row number alone.

Row numbers follow (bucket of the key, key); the key is id, size and crc of the text and, where whole rows are placed, a hash
of all columns. Equal keys are counted before they are numbered, so a key that holds a third of all rows is one row in the
numbering and is spread out again afterwards, SPREAD rows at a time; rows without an id are bucketed by the rest of their key.

Defined results: a null text has no bytes (size 1, crc 0) as has an empty one; null ids come first in a bucket; repeated rows
get numbers of their own; a very long text counts by its size alone and is never held in Python; an empty table gives an empty
result.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

# An odd multiplier pair and shifts for mixing 64-bit words (the public splitmix finaliser constants).
MIX = (0xBF58476D1CE4E5B9, 0x94D049BB133111EB, 30, 27, 31)
ROUNDS = 6
#: Range buckets in which rows are numbered side by side; each is one window partition.
BUCKETS = 4096
#: Most rows that one row of a key with many copies is spread out to in one step.
SPREAD = 100_000


def _mix(x: np.ndarray) -> np.ndarray:
    a, b, p, q, r = MIX
    x = (x ^ (x >> np.uint64(p))) * np.uint64(a)
    x = (x ^ (x >> np.uint64(q))) * np.uint64(b)
    return x ^ (x >> np.uint64(r))


def permute(numbers: np.ndarray, n: int, seed: int) -> np.ndarray:
    """Where a seeded permutation of 0..n-1 puts the given numbers; the domain is the next even power of two, walked."""
    if n <= 1:
        return np.zeros(len(numbers), np.int64)
    half = np.uint64((max(2, (n - 1).bit_length()) + 1) // 2)
    mask = np.uint64((1 << int(half)) - 1)
    keys = _mix(np.arange(1, ROUNDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(seed & (2**64 - 1)))
    x = np.asarray(numbers).astype(np.uint64)
    todo = np.arange(len(x))
    with np.errstate(over="ignore"):
        while len(todo):
            left, right = x[todo] >> half, x[todo] & mask
            for k in keys:
                left, right = right, left ^ (_mix(right ^ k) & mask)
            x[todo] = (left << half) | right
            todo = todo[x[todo] >= np.uint64(n)]
    return x.astype(np.int64)


def size_of(text: str = "text") -> Column:
    return F.octet_length(common.text_or_empty(text)).cast("long") + F.lit(1)


def crc_of(text: str = "text") -> Column:
    return F.crc32(common.text_or_empty(text).cast("binary"))


def numbered(keys: DataFrame, columns: list[str], buckets: int = BUCKETS) -> tuple[DataFrame, int]:
    """Distinct keys with their count and the number of their first row; and the number of rows in all.

    keys are numbered by (hash bucket of the columns, columns): bucket totals (at most `buckets` rows) become
    offsets, and inside a bucket a running sum over distinct keys goes on from there."""
    counts = common.cut(keys.groupBy(*columns).agg(F.count(F.lit(1)).alias("copies")).withColumn("bucket", F.pmod(F.xxhash64(*columns), F.lit(buckets))))
    totals = counts.groupBy("bucket").agg(F.sum("copies").alias("rows"))
    offsets = totals.withColumn("offset", F.coalesce(F.sum("rows").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    total = counts.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0]
    order = Window.partitionBy("bucket").orderBy(*[F.asc_nulls_first(c) for c in columns])
    running = F.coalesce(F.sum("copies").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    # at most `buckets` rows of two numbers are broadcast
    out = counts.withColumn("before", running).join(F.broadcast(offsets.select("bucket", "offset")), "bucket")
    return out.select(*columns, "copies", (F.col("before") + F.col("offset")).alias("start")), total


def _copies(rows: DataFrame, columns: list[str]) -> DataFrame:
    """Each row as often as its `copies` says, with its `copy` from 0: first in parts of SPREAD, dealt out, then one by one."""
    parts = rows.withColumn("__part", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("copies") - 1) / SPREAD))))
    first = F.col("__part") * SPREAD
    last = F.least(first + SPREAD, F.col("copies")) - 1
    return parts.hint("rebalance").select(*columns, F.explode(F.sequence(first, last)).alias("copy"))


def _placed(keys: DataFrame, columns: list[str], shards: int, seed: int) -> DataFrame:
    """The key columns, copies, copy, row_number, shard and slot: one row for each row of keys."""
    starts, total = numbered(keys, columns)
    rows = _copies(starts, [*columns, "copies", "start"])
    kinds = ", ".join(f"{c} {keys.schema[c].dataType.simpleString()}" for c in columns)

    def run(cols: dict) -> dict:
        at = permute(np.array(cols["row_number"], np.int64), total, seed)
        return cols | {"shard": (at % shards).tolist(), "slot": (at // shards).tolist()}

    picked = [*columns, "copies", "copy", (rows.start + rows.copy).alias("row_number")]
    return common.map_columns(rows, picked, run, f"{kinds}, copies long, copy long, row_number long, shard int, slot long", text=None)


def assignments(docs: DataFrame, shards: int = 16, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, size, text_crc32, copy, row_number, shard, slot), one row for each row of docs.

    Rows alike in these three columns are interchangeable and told apart by `copy`, 0 upwards."""
    keys = docs.select(F.col(id_col).alias("doc_id"), size_of(text_col).alias("size"), crc_of(text_col).alias("text_crc32"))
    return _placed(keys, ["doc_id", "size", "text_crc32"], shards, seed).drop("copies")


def shard_rows(docs: DataFrame, shards: int = 16, seed: int = 42, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with shard and slot: whole rows, numbered by id, size, crc and two 64-bit hashes of the whole row.

    Rows that share this key are alike: they are counted before anything is moved and spread out again at the end, so texts are
    shuffled once, each repeated row once. An input column called shard, slot or law gives way to the new one. Columns must be
    of types that can be grouped by (no maps)."""
    own = docs.drop("shard", "slot", "law")
    names = common.masked(own)
    base = own.select(*[own[c].alias(k) for c, k in names.items()])
    key = ["__id", "__none", "__size", "__crc", "__row", "__again"]
    number = F.col(names[id_col])
    keyed = base.withColumns({
        "__id": F.coalesce(number.cast("string"), F.lit("")), "__none": number.isNull(), "__size": size_of(names[text_col]), "__crc": crc_of(names[text_col]),
        "__row": F.xxhash64(*base.columns), "__again": F.xxhash64(F.lit(seed), *reversed(base.columns)),
    })
    starts, total = numbered(keyed.select(*key), key)
    starts = starts.select(*[F.col(k).alias(f"{k}_") for k in key], "copies", "start")
    # grouped by the key alone, so that the join finds the rows shuffled as it needs them
    rows = keyed.groupBy(*key).agg(F.first(F.struct(*base.columns)).alias("__whole"))
    rows = rows.join(starts, [rows[k] == starts[f"{k}_"] for k in key]).select("__whole.*", "copies", "start")
    few = rows.where(F.col("copies") <= SPREAD).select(*base.columns, "start", F.explode(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1)).alias("copy"))
    each = few.unionByName(_copies(rows.where(F.col("copies") > SPREAD), [*base.columns, "start"]))

    @F.pandas_udf("long")
    def place(at: pd.Series) -> pd.Series:
        return pd.Series(permute(at.to_numpy(np.int64), total, seed))

    placed = each.withColumn("__at", place(F.col("start") + F.col("copy")))
    return placed.select(*[F.col(k).alias(c) for c, k in names.items()], (F.col("__at") % shards).cast("int").alias("shard"), F.floor(F.col("__at") / shards).cast("long").alias("slot"), F.lit("rows").alias("law"))
