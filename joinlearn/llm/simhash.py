"""SimHash near-duplicates: exact tiled comparison by exclusive-or and bit counts.

Distinct fingerprints are laid out in groups that share one of four 16-bit segments: two fingerprints within three bits
agree on one segment at least, so every link lies inside a group. A group is compared in tiles ordered by population
count, and pairs of tiles whose counts differ beyond the radius are skipped. Groups above a tile are split into tiles by
count and hash, and each pair of tiles is a row of its own, so no task holds a whole large group. There is no cap.

Within a tile pair, links are reduced to a star for each set of linked fingerprints, which keeps components whole and
edges linear. Components follow by alternating star contractions over tables in the shared folder.

Defined results: texts without words (null, empty) have fingerprint zero and link like any other; repeated rows and
copies share a fingerprint and so a component; a component without any id has a null component id.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from . import common

RADIUS = 3
SEGMENTS = 4
TILE = 2048
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_CHUNK = 1 << 16


def fingerprint(text: str | None, shingle: int = 3) -> int:
    words = text.encode("utf-8", "surrogatepass").translate(_FOLD).split() if text else []
    if not words:
        return 0
    n = max(1, len(words) - shingle + 1)
    digest = xxhash.xxh64_intdigest
    set_bits = np.zeros(64, np.int64)
    for i in range(0, n, _CHUNK):
        near = words[i : i + min(_CHUNK, n - i) + shingle - 1]  # shingles are made piece by piece, however long the text
        parts = map(b" ".join, zip(*(near[k:] for k in range(shingle)), strict=False)) if len(near) >= shingle else [b" ".join(near)]
        h = np.array([digest(p, 42) for p in parts], "<u8")
        set_bits += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * set_bits > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, fp): fp is the fingerprint as a signed long."""

    def run(cols: dict) -> dict:
        made = np.array([fingerprint(t) for t in cols["text"]], np.uint64).view(np.int64)
        return {"doc_id": cols["doc_id"], "fp": made.tolist()}

    kind = docs.schema[id_col].dataType.simpleString()
    return common.map_columns(docs, [docs[id_col].alias("doc_id"), docs[text_col].cast("string").alias("text")], run, f"doc_id {kind}, fp long")


def linked_pairs(a: np.ndarray, b: np.ndarray | None, radius: int, tile: int = 256) -> tuple[np.ndarray, np.ndarray]:
    """Indices (into a, into b or a) of pairs within the radius; rows and columns are tiles by population count."""
    one = b is None
    ca = np.bitwise_count(a)
    ia = np.argsort(ca, kind="stable")
    ib, cb = (ia, ca) if one else (np.argsort(np.bitwise_count(b), kind="stable"), np.bitwise_count(b))
    xa, xb, pa_, pb = a[ia], (a if one else b)[ib], ca[ia].astype(int), cb[ib].astype(int)
    left, right = [], []
    for i in range(0, len(xa), tile):
        rows = xa[i : i + tile]
        low = i if one else int(np.searchsorted(pb, pa_[i] - radius, "left"))
        high = int(np.searchsorted(pb, pa_[min(i + tile, len(xa)) - 1] + radius, "right"))
        for j in range(low, high, 4096):
            r, c = np.nonzero(np.bitwise_count(rows[:, None] ^ xb[None, j : min(j + 4096, high)]) <= radius)
            keep = (r + i < c + j) if one else slice(None)
            left.append(ia[r[keep] + i])
            right.append(ib[c[keep] + j])
    none = [np.zeros(0, np.int64)]
    return np.concatenate(left or none), np.concatenate(right or none)


def stars(values: np.ndarray, left: np.ndarray, right: np.ndarray) -> list[tuple[int, int]]:
    """(member, smallest member) for each set of linked values, without the smallest itself."""
    if not len(left):
        return []
    used, at = np.unique(np.concatenate([left, right]), return_inverse=True)
    root = values[used].copy()
    a, b = at[: len(left)], at[len(left) :]
    while True:  # smallest neighbour until nothing changes
        before = root.copy()
        low = np.minimum(root[a], root[b])
        np.minimum.at(root, a, low)
        np.minimum.at(root, b, low)
        if (root == before).all():
            break
    mine = values[used]
    return [(int(v), int(r)) for v, r in zip(mine, root, strict=True) if v != r]


def _edges(tiles: DataFrame, radius: int) -> DataFrame:
    """Star edges (u, v), v < u, from rows of one tile `a` and, if not null, another `b`."""
    out = T._parse_datatype_string("u long, v long")
    arrow = to_arrow_schema(out)

    def task(batches):
        for batch in batches:
            made: list[tuple[int, int]] = []
            for a, b in zip(batch.column(0), batch.column(1), strict=True):
                x = a.values.to_numpy(zero_copy_only=False)
                if b.is_valid:
                    y = b.values.to_numpy(zero_copy_only=False)
                    l, r = linked_pairs(x.view(np.uint64), y.view(np.uint64), radius)
                    made += stars(np.concatenate([x, y]), l, r + len(x))
                elif len(x) > 1:
                    made += stars(x, *linked_pairs(x.view(np.uint64), None, radius))
            u, v = map(list, zip(*made, strict=True)) if made else ([], [])
            yield pa.RecordBatch.from_arrays([pa.array(u, pa.int64()), pa.array(v, pa.int64())], schema=arrow)

    return tiles.mapInArrow(task, out)


def links(distinct: DataFrame, radius: int = RADIUS, tile: int = TILE) -> DataFrame:
    """Edges (u, v) that join all linked fingerprints of column fp (each value once)."""
    width = 64 // SEGMENTS
    keyed = distinct.select("fp", F.explode(F.array(*[F.lit(i) for i in range(SEGMENTS)])).alias("s"))
    keyed = keyed.select("fp", (F.shiftleft(F.col("s"), width) + F.expr(f"cast(shiftrightunsigned(fp, s * {width}) & {2**width - 1} as int)")).alias("k"))
    sizes = keyed.groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    large = common.cut(sizes.where(F.col("n") > tile).select("k"))
    alone = keyed.join(large, "k", "left_anti").groupBy("k").agg(F.collect_list("fp").alias("a"))  # at most `tile` values each
    edges = _edges(alone.where(F.size("a") > 1).select("a", F.lit(None).cast("array<long>").alias("b")), radius)
    if large.isEmpty():
        return edges.distinct()
    hot = keyed.join(large, "k", "left_semi").withColumn("p", F.bit_count("fp"))
    counts = common.cut(hot.groupBy("k", "p").agg(F.ceil(F.count(F.lit(1)) / tile).alias("m")))
    placed = hot.join(counts, ["k", "p"]).withColumn("t", F.pmod(F.xxhash64("fp"), F.col("m")))
    tiles = common.cut(placed.groupBy("k", "p", "t").agg(F.collect_list("fp").alias("a")))
    reach = tiles.select("k", F.explode(F.sequence(F.col("p"), F.col("p") + radius)).alias("p"), F.col("p").alias("p1"), F.col("t").alias("t1"), F.col("a"))
    other = tiles.select("k", "p", F.col("t").alias("t2"), F.col("a").alias("b"))
    pairs = reach.join(other, ["k", "p"]).where((F.col("p1") < F.col("p")) | (F.col("t1") <= F.col("t2")))
    pairs = pairs.select("a", F.when((F.col("p1") == F.col("p")) & (F.col("t1") == F.col("t2")), F.lit(None)).otherwise(F.col("b")).alias("b"))
    return edges.unionByName(_edges(pairs.hint("rebalance"), radius)).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(u, root) for every vertex of edges (u, v) but the roots: each round is a large and a small star, then a table."""
    now, mark = common.cut(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))), None
    while True:  # until a round changes nothing; rounds grow with the logarithm of the vertices
        state = tuple(now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if state == mark or state[0] == 0:
            break
        mark = state
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(least, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        now = common.cut(small.unionByName(least.select("u", F.col("m").alias("v"))).distinct())
    return now.select("u", F.col("v").alias("root"))


def labelled(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """(doc_id, fp, component_id, class) for each row: class is the root fingerprint of its component."""
    rows = common.cut(fingerprints(docs, id_col, text_col))
    reps = common.cut(rows.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = common.cut(components(links(reps.select("fp"), radius)))
    member = roots.select(F.col("u").alias("fp"), "root").unionByName(roots.select(F.col("root").alias("fp"), "root").distinct())
    firsts = member.join(reps, "fp").groupBy("root").agg(F.min("least").alias("first"))
    known = member.join(firsts, "root").select("fp", "root", "first")
    names = common.cut(reps.join(known, "fp", "left").select("fp", F.when(F.col("root").isNull(), F.col("least")).otherwise(F.col("first")).alias("component_id"), F.coalesce("root", "fp").alias("class")))
    return rows.join(names, "fp").select("doc_id", "fp", "component_id", "class")


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", radius: int = RADIUS) -> DataFrame:
    """One row of each component stays, that of its smallest id; columns as they came.

    Rows are dropped by id. Where ids are null or occur twice, those rows alone are decided by id and fingerprint."""
    names = docs.columns
    found = common.cut(labelled(docs, id_col, text_col, radius))
    gone = common.cut(found.where(~F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("__gone")).distinct())
    odd = common.cut(found.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1 or doc_id is null").select(F.col("doc_id").alias("__odd")))
    if odd.isEmpty():
        return docs.join(gone, docs[id_col] == gone["__gone"], "left_anti")
    plain = docs.join(odd, docs[id_col].eqNullSafe(odd["__odd"]), "left_anti")
    plain = plain.join(gone, plain[id_col] == gone["__gone"], "left_anti")
    again = docs.join(odd, docs[id_col].eqNullSafe(odd["__odd"]), "left_semi")
    kinds = {c: docs.schema[c].dataType.simpleString() for c in names}
    shown = {c: f"k{i}" for i, c in enumerate(names)}

    def run(cols: dict) -> dict:
        return cols | {"fp": np.array([fingerprint(t) for t in cols[shown[text_col]]], np.uint64).view(np.int64).tolist()}

    marked = common.map_columns(again, [again[c].alias(k) for c, k in shown.items()], run, ", ".join([*(f"{shown[c]} {kinds[c]}" for c in names), "fp long"]), text=shown[text_col] if kinds[text_col] == "string" else None)
    classes = found.select("fp", "component_id", "class").distinct()
    joined = marked.join(classes, "fp").where(F.col(shown[id_col]).eqNullSafe(F.col("component_id")))
    first = Window.partitionBy("class").orderBy("fp", *[F.xxhash64(F.col(k).cast("string")) for c, k in shown.items() if kinds[c] in ("string", "bigint", "int", "double")])
    kept = joined.withColumn("__n", F.row_number().over(first)).where("__n = 1").select(*[F.col(k).alias(c) for c, k in shown.items()])
    return plain.unionByName(kept)
