"""Moments of a feature query: sums of all aggregate monomials by categorical key, under several strategies.

factorized: shared views over a variable order (sums pushed past the join where that shrinks them). materialize: over the
join itself, a grouping for each key set. individual: one job for each aggregate (no sharing). onehot: categories turned
into 0/1 columns of the relations, then factorized (the linear-only prototype). order_per_keys: a variable order of its own
for every key set."""

from __future__ import annotations

import gc
import json
from collections.abc import Callable, Iterator, Mapping, Sequence
from dataclasses import dataclass, field
from functools import cached_property, reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from ..plans.monomials import ONE, Monomial, by_keys
from ..plans.order import VariableOrder
from ..plans.query import FeatureQuery
from ..plans.statistics import Statistics
from ..plans.views import WIDEST, View, Views, plain, power, product
from . import dealt
from .dealt import NO_NUMBER, narrow

#: Payloads of more pieces of WIDEST columns than this are served by the one-pass kernel: each piece is a join of its own.
MANY_PIECES = 6
#: Most entries that are collected to the driver; beyond, moments stay a table (see `long_table`).
DRIVER_ENTRIES = 200_000_000
#: Categories of more levels than this are counted by a grouping, others by sets in each task.
SET_LEVELS = 1_000
#: Views over a relation of so many rows are evaluated one after the other, as the shuffles of all together take much more disk.
APART = 5_000_000

Keys = tuple[str, ...]
Root = tuple[Keys, list[Monomial], DataFrame]


class Lowered(Sequence):
    """Lazy results of the factorized strategy: the shared views, and (made when asked for) one DataFrame a key set."""

    def __init__(self, views: Views, monomials: list[Monomial]) -> None:
        self.plans, self.monomials = views, monomials

    @cached_property
    def views(self) -> list[View]:
        return self.plans.results(self.monomials)

    @cached_property
    def _roots(self) -> list[Root]:
        return list(self.plans.roots(self.monomials))

    def __len__(self) -> int:
        return len(self._roots)

    def __getitem__(self, i):
        return self._roots[i]


Roots = Sequence[Root]


@dataclass
class Moments:
    """Driver form: for each key set a pandas table of keys and columns m0, m1, ... of raw sums.

    Keys are pandas categories in the order of the layout (a null is no category); whole sums may be held as integers."""

    query: FeatureQuery
    tables: Mapping[tuple[str, ...], pd.DataFrame]
    monomials: dict[tuple[str, ...], list[Monomial]]
    seconds: float = 0.0
    strategy: str = ""
    _at: dict[Monomial, tuple[tuple[str, ...], str]] = field(default_factory=dict)

    def __post_init__(self) -> None:
        self._at = {m: (k, f"m{i}") for k, ms in self.monomials.items() for i, m in enumerate(ms)}

    def column(self, m: Monomial) -> np.ndarray:
        return self.held(m).astype(float, copy=False)

    def held(self, m: Monomial) -> np.ndarray:
        """The column as it is held, maybe in integers."""
        keys, name = self._at[m]
        return self.tables[keys][name].to_numpy()

    def scalar(self, m: Monomial) -> float:
        values = self.column(m)
        return float(values[0]) if len(values) and np.isfinite(values[0]) else 0.0

    @property
    def rows(self) -> float:
        return self.scalar(ONE)

    def entries(self) -> tuple[int, int]:
        """Scalar and grouped aggregates: distinct entries over all key sets."""
        scalar = len(self.monomials.get((), ()))
        rows = self.tables.lengths() if isinstance(self.tables, dealt.Tables) else {k: len(t) for k, t in self.tables.items()}
        return scalar, sum(n * len(self.monomials[k]) for k, n in rows.items() if k)

    def wide(self, keys: Keys) -> dealt.Wide | None:
        """Counts of the key set that are held as a matrix."""
        return self.tables.wide.get(keys) if isinstance(self.tables, dealt.Tables) else None


def lower(query: FeatureQuery, monomials: list[Monomial], order: VariableOrder | None = None, strategy: str = "factorized", eager=None) -> Roots:
    """Lazy DataFrames, one a key set, for the strategies that are plain plans. eager: see `Views`."""
    if strategy == "factorized":
        return Lowered(Views(query, order or VariableOrder.suggest(query), eager), monomials)
    if strategy == "order_per_keys":
        out: list[Root] = []
        for keys, wanted in by_keys(monomials).items():
            shaped = FeatureQuery(query.relations, query.continuous, tuple(keys), query.response, query.where, query.set_semantics, query.null_policy, query.scale, tuple(c for c in query.categorical if c not in keys))
            out += Views(shaped, VariableOrder.suggest(shaped), eager).roots(wanted)
        return out
    if strategy in ("materialize", "individual"):
        rows, exact, out = query.listing(), query.scale is not None, []
        cast = (lambda c: F.sum(c).cast("decimal(38,0)")) if exact else F.sum
        groups = by_keys(monomials).items() if strategy == "materialize" else [(m.cats, [m]) for m in monomials]
        for keys, wanted in groups:
            for i in range(0, len(wanted), WIDEST):
                part = wanted[i : i + WIDEST]
                sums = [cast(product([power(v, e) for v, e in m.cont], exact)).alias(f"m{j}") for j, m in enumerate(part)]
                out.append((tuple(keys), part, rows.groupBy(*keys).agg(*sums)))
        return out
    raise ValueError(f"unknown strategy {strategy!r}")


def _codes(batch: pa.RecordBatch, keys: tuple[str, ...], levels: list[dict]) -> list[np.ndarray]:
    out = []
    for i, _ in enumerate(keys):
        d = batch.column(i).dictionary_encode()
        known = levels[i]
        mapped = np.array([known.setdefault(v, len(known)) for v in d.dictionary.to_pylist()] or [0], np.int64)
        out.append(mapped[d.indices.to_numpy(zero_copy_only=False)])
    return out


def one_pass(frame: DataFrame, keys: tuple[str, ...], payloads: list[Monomial], groups: dict[tuple[str, ...], list[Monomial]]) -> DataFrame:
    """All key sets in one pass: each task groups its rows for every key set, then one shuffle merges what tasks have.

    frame: keys, then payload columns m0, m1, ... of the continuous parts. Result: (set INT, key STRING, sums ARRAY<DOUBLE>);
    key is the JSON array of the key values as text. The shuffle carries distinct local keys, not rows times key sets."""
    sets = list(groups.items())
    at = {m: i for i, m in enumerate(payloads)}
    picks = [[at[Monomial(m.cont, ())] for m in wanted] for _, wanted in sets]
    columns = [[keys.index(k) for k in ks] for ks, _ in sets]
    out = T._parse_datatype_string("set int, key string, sums array<double>")
    arrow = to_arrow_schema(out)
    n_keys = len(keys)

    def task(batches):
        levels: list[dict] = [{} for _ in range(n_keys)]
        held: list[dict] = [{} for _ in sets]
        size = 0

        def flush():
            names = [list(x) for x in levels]
            ids, texts, sums = [], [], []
            for s, found in enumerate(held):
                cols = columns[s]
                for code, row in found.items():
                    ids.append(s)
                    texts.append(json.dumps([names[c][v] for c, v in zip(cols, code, strict=True)]))
                    sums.append(row)
                found.clear()
                if len(ids) >= 50_000:
                    yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.array(texts), pa.array(sums, arrow.field("sums").type)], schema=arrow)
                    ids, texts, sums = [], [], []
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), pa.array(texts), pa.array(sums, arrow.field("sums").type)], schema=arrow)

        for batch in batches:
            if not batch.num_rows:
                continue
            codes = _codes(batch, keys, levels)
            values = np.column_stack([batch.column(n_keys + i).to_numpy(zero_copy_only=False) for i in range(len(payloads))]).astype(float)
            for s, cols in enumerate(columns):
                x = values[:, picks[s]]
                if not cols:
                    distinct, sums = [()], x.sum(0, keepdims=True)
                else:
                    joined = codes[cols[0]]
                    for c in cols[1:]:  # dense again after each key: level codes grow over a task and their product could overflow
                        joined = np.unique(joined, return_inverse=True)[1].astype(np.int64) * (int(codes[c].max()) + 1) + codes[c]
                    _, first, inverse = np.unique(joined, return_index=True, return_inverse=True)
                    sums = np.column_stack([np.bincount(inverse, weights=x[:, j], minlength=len(first)) for j in range(x.shape[1])])
                    distinct = list(zip(*(codes[c][first].tolist() for c in cols), strict=True))
                found = held[s]
                for code, row in zip(distinct, sums, strict=True):
                    if code in found:
                        found[code] += row
                    else:
                        found[code] = row
                        size += len(row) + 8
            if size > 20_000_000:
                yield from flush()
                size = 0
        yield from flush()

    partial = frame.mapInArrow(task, out)
    width = max(len(p) for p in picks)
    merged = partial.groupBy("set", "key").agg(*[F.sum(F.get("sums", F.lit(i))).alias(f"s{i}") for i in range(width)]) if width <= WIDEST else _merge_wide(partial)
    return merged if width > WIDEST else merged.select("set", "key", F.array(*[f"s{i}" for i in range(width)]).alias("sums"))


def _merge_wide(partial: DataFrame) -> DataFrame:
    """Sums of long arrays position by position, for payloads wider than a grouping should be."""
    each = partial.select("set", "key", F.posexplode("sums").alias("at", "v")).groupBy("set", "key", "at").agg(F.sum("v").alias("v"))
    rows = each.groupBy("set", "key").agg(F.sort_array(F.collect_list(F.struct("at", "v"))).alias("x"))
    return rows.select("set", "key", F.transform("x", lambda e: e.v).alias("sums"))


def _packed(by: list[str]) -> Callable:
    """Each batch as one compressed value, beside the rows that share the values of the columns `by`."""
    counted = pa.list_(pa.struct([("at", pa.list_(pa.int32())), ("n", pa.int64())]))

    def task(parts):
        for p in parts:
            if p.num_rows:
                out = pa.BufferOutputStream()
                with pa.ipc.new_stream(out, p.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as writer:
                    writer.write_batch(p)
                at, n = np.unique(np.column_stack([np.zeros(p.num_rows, np.int32), *[p.column(c).to_numpy() for c in by]]), axis=0, return_counts=True)
                counts = [{"at": x[1:], "n": k} for x, k in zip(at.tolist(), n.tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array([counts], counted), pa.array([out.getvalue().to_pybytes()], pa.binary())], ["counts", "part"])

    return task


def _guarded(df: DataFrame, by: list[str], entries: Callable[..., tuple[int, Keys]], limit: int) -> Iterator[pa.Table]:
    """The rows on the driver, part by part, after their entries were counted and found within the limit. What waits is compressed.

    entries: width and key set of the rows that share the values of the columns `by`."""
    yield from _within(df.mapInArrow(_packed(by), dealt.PACKED), entries, limit)


def _within(packed: DataFrame, entries: Callable[..., tuple[int, Keys]], limit: int, most: Callable[..., int] | None = None) -> Iterator[pa.Table]:
    """most: rows that are left of those that share their values, once equal keys are merged."""
    held, total = packed.persist(), 0
    try:
        for at, rows in held.select(F.explode("counts").alias("c")).groupBy("c.at").agg(F.sum("c.n")).collect():
            width, keys = entries(*at)
            total += (min(rows, most(*at)) if most else rows) * width
            if total > limit:
                raise MemoryError(f"key set {keys} takes the moments over {limit} entries; use long_table()")
        yield from _opened(held)
    finally:
        held.unpersist()


def _opened(packed: DataFrame) -> Iterator[pa.Table]:
    for r in packed.select("part").toLocalIterator(prefetchPartitions=True):
        yield pa.ipc.open_stream(r.part).read_all()


def packed_parts(df: DataFrame) -> Iterator[pa.Table]:
    """The rows on the driver, part by part in columns."""
    return _opened(df.mapInArrow(_packed([]), dealt.PACKED))


class _Gathered:
    """Rows of key sets as they come in. Keys are held as codes of their levels, whole numbers as they are; sums are narrowed."""

    def __init__(self) -> None:
        self.known: dict[str, dict] = {}
        self.numbers: set[str] = set()
        self.keys: dict[tuple, dict[str, list[np.ndarray]]] = {}
        self.sums: dict[tuple, list[list[np.ndarray]]] = {}

    def encoded(self, name: str, column: pa.ChunkedArray | pa.Array) -> np.ndarray:
        if pa.types.is_null(column.type):
            return np.full(len(column), -1)
        if pa.types.is_integer(column.type):
            self.numbers.add(name)
            return column.cast(pa.int64()).fill_null(NO_NUMBER).to_numpy()
        d = (column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column).dictionary_encode()
        known = self.known.setdefault(name, {})
        codes = np.array([known.setdefault(v, len(known)) for v in d.dictionary.to_pylist()] + [-1])
        return codes[d.indices.fill_null(-1).to_numpy()]

    def add(self, at: tuple, ks: Keys, keys: dict[str, np.ndarray], sums: np.ndarray) -> None:
        held = self.keys.setdefault(at, {k: [] for k in ks})
        for k in ks:
            held[k].append(narrow(keys[k]) if k in self.numbers else keys[k].astype(np.int32))
        columns = self.sums.setdefault(at, [[] for _ in range(sums.shape[1])])
        for j, column in enumerate(columns):
            column.append(narrow(sums[:, j]).copy())

    def levels(self) -> dict[str, tuple[pd.CategoricalDtype, np.ndarray]]:
        """Of each key its levels in order of their text and, for whole numbers, them in order of size with the places that they take."""
        out: dict[str, tuple[pd.CategoricalDtype, np.ndarray]] = {}
        for name in {k for held in self.keys.values() for k in held}:
            if name in self.numbers:
                found = np.unique(np.concatenate([np.unique(np.concatenate(held[name])) for held in self.keys.values() if name in held]))
                found = found[found != NO_NUMBER].astype(np.int64)
                order = np.argsort(found.astype("S20"), kind="stable")
                place = np.empty(len(found), np.int32)
                place[order] = np.arange(len(found), dtype=np.int32)
                out[name] = pd.CategoricalDtype(pd.Index(found[order])), np.stack([found, place])
            else:
                known = list(self.known.get(name, {}))
                order = sorted(range(len(known)), key=lambda i: str(known[i]))
                place = np.empty(len(known) + 1, np.int32)
                place[order] = np.arange(len(known), dtype=np.int32)
                place[-1] = -1
                out[name] = pd.CategoricalDtype(pd.Index([known[i] for i in order], dtype=object)), place
        return out

    def frames(self) -> Iterator[tuple[tuple, pd.DataFrame]]:
        levels = self.levels()
        for at in list(self.keys):
            columns: dict = {}
            for k, parts in self.keys.pop(at).items():
                kind, place = levels[k]
                values = np.concatenate(parts)
                parts.clear()
                if k in self.numbers:
                    found, places = place
                    code = places[np.minimum(np.searchsorted(found, values), len(found) - 1)] if len(found) else np.full(len(values), -1)
                    code = np.where(values == NO_NUMBER, -1, code) if values.dtype == np.int64 else code
                else:
                    code = place[values]
                columns[k] = pd.Categorical.from_codes(code.astype(np.min_scalar_type(-len(kind.categories) - 1)), dtype=kind)
            for j, parts in enumerate(self.sums.pop(at)):
                columns[f"m{j}"] = np.concatenate(parts)
                parts.clear()
            yield at, pd.DataFrame(columns, copy=False)


def _stacked(views: list[View]) -> tuple[DataFrame, list[str]]:
    """All views as one frame (__v: place of the view, __n: key set, keys, __p: sums), so that one job evaluates them."""
    keys = sorted({k for v in views for k in v.keys})
    frames = [v.frame.select(F.lit(i).alias("__v"), F.col(v.number).alias("__n"), *[F.col(k) if k in v.keys else F.lit(None).alias(k) for k in keys], F.col(v.packed).alias("__p")) for i, v in enumerate(views)]
    return reduce(DataFrame.unionByName, frames), keys


def _matrix(column: pa.ChunkedArray, width: int | None) -> np.ndarray:
    """An array column of sums as rows by width (None: as wide as they are)."""
    flat = pa.chunked_array([c.flatten() for c in column.chunks], column.type.value_type)
    return flat.cast(pa.float64()).to_numpy().reshape(len(column), -1 if width is None else width)


def _slices(table: pa.Table, by: list[str]) -> Iterator[tuple[tuple[int, ...], np.ndarray]]:
    """Places of the rows of each combination of numbers in the columns `by`."""
    numbers = np.column_stack([table[c].to_numpy() for c in by])
    order = np.lexsort(numbers.T[::-1])
    numbers = numbers[order]
    starts = np.flatnonzero(np.r_[True, (numbers[1:] != numbers[:-1]).any(1)]) if len(numbers) else np.zeros(0, int)
    for low, high in zip(starts, [*starts[1:], len(numbers)], strict=False):
        yield tuple(int(x) for x in numbers[low]), order[low:high]


def _frame_of(keys: Keys, columns: dict, sums: np.ndarray) -> pd.DataFrame:
    return pd.DataFrame({k: columns[k] for k in keys} | {f"m{i}": sums[:, i] for i in range(sums.shape[1])})


def _dealable(query: FeatureQuery, groups: dict[Keys, list[Monomial]], strategy: str, eager, wide: bool = False) -> bool:
    """Whether the one pass over dealt rows serves: for a large category beside others, where groupings would repeat the join's
    rows for each of them, over the join itself, and for wide payloads, whose sums it holds in columns."""
    if strategy not in ("factorized", "materialize") or query.scale is not None or eager is not None:
        return False
    large = dealt.split(query, Statistics.of(query), list(groups))
    return large is not False and (wide or strategy == "materialize" or any(large in ks and len(ks) > 1 for ks in groups))


def moments(query: FeatureQuery, monomials: list[Monomial], order: VariableOrder | None = None, strategy: str = "factorized", kernel: str = "auto", eager=None, limit: int = DRIVER_ENTRIES) -> Moments:
    """Evaluate and collect. kernel: 'sql' (shared views, or a grouping for each key set), 'arrow' (one pass over the join for
    all key sets), 'dealt' (one pass over the join, dealt out by its large category if it has one), 'auto' (views, unless their
    payloads are very wide or a large category meets others; then 'dealt', or 'arrow' where rows cannot be dealt). Entries are
    counted before they are collected: over `limit` of them raise MemoryError."""
    import time

    began = time.time()
    groups = by_keys(monomials)
    wide = sum(-(-len(f) // WIDEST) for f in {tuple(sorted(map(plain, ms))) for ms in groups.values()}) > MANY_PIECES
    if kernel == "auto":
        wide = wide and strategy in ("factorized", "materialize") and query.scale is None
        kernel = "dealt" if _dealable(query, groups, strategy, eager, wide) else "arrow" if wide else "sql"
    found: dict[Keys, list[tuple[pd.DataFrame, list[Monomial]]]] = {ks: [] for ks in groups}
    gathered, at = _Gathered(), {}
    if kernel == "dealt":
        sets, statistics = list(groups.items()), Statistics.of(query)
        numbers = sorted({v for m in monomials for v, _ in m.cont})
        rows = dealt.coded(query, statistics, dealt.split(query, statistics, list(groups)) or None, numbers)
        came = dealt.Gathered(rows, sets)
        for part in _within(dealt.sums(rows, sets, wide), lambda s: (len(sets[s][1]), sets[s][0]), limit, came.most):
            came.add(part)
        tables, session = came.tables(), rows.frame.sparkSession
        del came, rows
        dealt.trimmed(session)
        return Moments(query, tables, groups, time.time() - began, f"{strategy}/dealt")
    if kernel == "arrow":
        keys = tuple(sorted({k for g in groups for k in g}))
        if strategy == "factorized":
            frame, payloads = Views(query, order or VariableOrder.suggest(query), eager).finest(monomials)
        else:
            payloads = list(dict.fromkeys(map(plain, monomials)))
            frame = query.listing().select(*keys, *[product([power(v, e) for v, e in m.cont], False).alias(f"m{i}") for i, m in enumerate(payloads)])
        sets, whole = list(groups.items()), {f.name for f in frame.schema if isinstance(f.dataType, T.IntegralType)}
        for part in _guarded(one_pass(frame, keys, payloads, groups), ["set"], lambda s: (len(sets[s][1]), sets[s][0]), limit):
            texts, packed = part["key"].to_pylist(), part["sums"].combine_chunks()
            for (s,), rows in _slices(part, ["set"]):
                ks, wanted = sets[s]
                parsed = [json.loads(texts[i]) for i in rows]
                mine = {k: gathered.encoded(k, pa.array([p[i] for p in parsed], pa.int64() if k in whole else None)) for i, k in enumerate(ks)}
                at[(s,)] = ks, wanted
                gathered.add((s,), ks, mine, _matrix(pa.chunked_array([packed.take(pa.array(rows))]), None)[:, : len(wanted)])
    else:
        roots = lower(query, monomials, order, strategy, eager)
        if isinstance(roots, Lowered):
            views = roots.views
            named = [{n: ks for ks, n in v.sets.items()} for v in views]
            apart = eager is None and max(roots.plans.statistics.rows.values()) >= APART
            left = limit
            for first, some in [(i, [v]) for i, v in enumerate(views)] if apart else [(0, views)]:
                frame, keys = _stacked(some)
                for part in _guarded(frame, ["__v", "__n"], lambda v, n, first=first: (len(views[first + v].payloads), named[first + v][n]), left):
                    codes = {k: gathered.encoded(k, part[k]) for k in keys}
                    packed = part["__p"].combine_chunks()
                    for (i, n), rows in _slices(part, ["__v", "__n"]):
                        i += first
                        ks, wanted = named[i][n], views[i].payloads
                        left -= len(rows) * len(wanted) if apart else 0
                        at[i, n] = ks, [Monomial(m.cont, ks) for m in wanted]
                        gathered.add((i, n), ks, {k: codes[k][rows] for k in ks}, _matrix(pa.chunked_array([packed.take(pa.array(rows))]), len(wanted)))
                if apart:
                    session = frame.sparkSession
                    del frame
                    gc.collect()
                    session.sparkContext._jvm.System.gc()  # shuffles of the view before
        else:
            left = limit
            for r, (ks, wanted, df) in enumerate(roots):
                at[(r,)] = tuple(ks), wanted
                for part in _guarded(df, [], lambda ks=ks, wanted=wanted: (len(wanted), ks), left):
                    left -= part.num_rows * len(wanted)
                    gathered.add((r,), ks, {k: gathered.encoded(k, part[k]) for k in ks}, np.column_stack([part[f"m{i}"].cast(pa.float64()).to_numpy() for i in range(len(wanted))]))
                gc.collect()
                df.sparkSession.sparkContext._jvm.System.gc()  # shuffles of the key set before
    for place, table in gathered.frames():
        ks, wanted = at[place]
        found[ks].append((table, wanted))
    tables: dict = {}
    kept: dict = {}
    for ks, parts in found.items():
        kept[ks] = [m for _, wanted in parts for m in wanted] or groups[ks]
        tables[ks] = _beside(ks, [t for t, _ in parts]) if parts else _frame_of(ks, dict.fromkeys(ks, []), np.zeros((0, len(kept[ks]))))
    return Moments(query, tables, kept, time.time() - began, f"{strategy}/{'arrow' if kernel == 'arrow' else 'sql'}")


def _beside(keys: Keys, parts: list[pd.DataFrame]) -> pd.DataFrame:
    """Payload pieces of one key set in one table, rows matched by key."""
    out = parts[0]
    for p in parts[1:]:
        n = len(out.columns) - len(keys)
        p = p.rename(columns={c: f"m{n + i}" for i, c in enumerate(c for c in p.columns if c not in keys)})
        out = out.merge(p, on=list(keys)) if keys else pd.concat([out, p], axis=1)
    return out


def combination_counts(query: FeatureQuery, sets: list[Keys], order: VariableOrder | None = None) -> dict[Keys, int]:
    """How many key combinations of each key set occur in the join, counted in place: in one pass over its rows if they can be
    dealt out by the large category, else from views."""
    statistics = Statistics.of(query) if query.scale is None else None
    large = dealt.split(query, statistics, sets) if statistics else False
    if large is not False:
        return dealt.combinations(dealt.coded(query, statistics, large, []), sets)
    found = {}
    for v in lower(query, [Monomial((), k) for k in sets], order).views:
        named = {n: ks for ks, n in v.sets.items()}
        found |= {named[n]: rows for n, rows in v.frame.groupBy(v.number).count().collect()}
    return {ks: found.get(ks, 0) for ks in sets}


def entry_counts(query: FeatureQuery, monomials: list[Monomial], order: VariableOrder | None = None, counts: dict[Keys, int] | None = None) -> tuple[int, int]:
    """Scalar and grouped aggregates that moments() would hold, from the occurring key combinations alone (counts: if known)."""
    groups = by_keys(monomials)
    sets = [ks for ks in groups if ks]
    counts = combination_counts(query, sets, order) if counts is None and sets else counts or {}
    return len(groups.get((), ())), sum(counts[ks] * len(groups[ks]) for ks in sets)


def occurrences(query: FeatureQuery, order: VariableOrder | None = None, pairs: bool = True) -> tuple[int, dict[Keys, int]]:
    """Rows of the join, and how many levels each category and level pairs each two of them have there; nothing is collected.

    Small categories are counted from the sets that tasks hold, the others from one grouping by each."""
    views = Views(query, order or VariableOrder.suggest(query))
    cats = sorted(query.categorical)
    levels = {c: max((d[c] for d in views.statistics.distinct.values() if c in d), default=0) for c in cats}
    large = [c for c in cats if levels[c] > SET_LEVELS]
    frame, _ = views.finest([Monomial((), tuple(cats))], large[0] if large else None)
    small = [c for c in cats if c not in large]
    sets: list[Keys] = [(c,) for c in small] + ([(a, b) for i, a in enumerate(small) for b in small[i + 1 :]] if pairs else [])

    def size(ks: Keys):
        return F.size(F.collect_set(F.struct(*ks))).cast("long")

    parts = [frame.agg(F.count(F.lit(1)).alias("n"), F.array(*[size(ks) for ks in sets]).cast("array<bigint>").alias("found"))]
    asked = [sets]
    for i, a in enumerate(large):
        beside = small if pairs else []
        by = frame.groupBy(a).agg(F.count(F.lit(1)).alias("r"), *[size((c,)).alias(f"s{j}") for j, c in enumerate(beside)])
        parts.append(by.agg(F.coalesce(F.sum("r"), F.lit(0)).alias("n"), F.array(F.count(F.lit(1)), *[F.coalesce(F.sum(f"s{j}"), F.lit(0)) for j in range(len(beside))]).alias("found")))
        asked.append([(a,), *[tuple(sorted((a, c))) for c in beside]])
        for b in large[i + 1 :] if pairs else ():
            parts.append(frame.select(a, b).distinct().agg(F.lit(0).cast("long").alias("n"), F.array(F.count(F.lit(1))).alias("found")))
            asked.append([tuple(sorted((a, b)))])
    rows = reduce(DataFrame.unionByName, [p.select(F.lit(i).alias("at"), "n", "found") for i, p in enumerate(parts)]).collect()
    got = {r.at: r for r in rows}
    return got[0].n, {ks: n for i, mine in enumerate(asked) for ks, n in zip(mine, got[i].found, strict=True)}


def linear_entries(query: FeatureQuery, counts: dict[Keys, int]) -> tuple[int, int, int]:
    """Scalar and grouped aggregates of a degree-one model and its parameters, from `occurrences` of at least its categories."""
    groups = by_keys(query.aggregates(1))
    grouped = sum(counts[tuple(sorted(ks))] * len(ms) for ks, ms in groups.items() if ks)
    return len(groups[()]), grouped, 1 + len(query.continuous) + sum(counts[(c,)] for c in query.categorical)


def rolled_up(finer: DataFrame, keys: list[str], sums: list[str]) -> DataFrame:
    """A coarser key set's view from a finer one: sums of sums."""
    return finer.groupBy(*keys).agg(*[F.sum(c).alias(c) for c in sums])


def _entries(roots: Roots) -> Iterator[tuple[Keys, DataFrame]]:
    """(keys, DataFrame of the keys, monomial STRING and value DOUBLE): every entry, nothing collected."""
    if isinstance(roots, Lowered):
        for v in roots.views:
            rows = [f"array({', '.join(repr(str(Monomial(m.cont, ks))) for m in v.payloads)})" for ks in v.sets]  # in order of number
            each = v.frame.select(v.number, *v.keys, F.posexplode(v.packed).alias("__at", "value"))
            yield v.keys, each.select(*v.keys, F.expr(f"array({', '.join(rows)})[`{v.number}`][__at] AS monomial"), F.col("value").cast("double").alias("value"))
    else:
        for keys, wanted, df in roots:
            each = F.explode(F.array(*[F.struct(F.lit(str(m)).alias("monomial"), F.col(f"m{i}").cast("double").alias("value")) for i, m in enumerate(wanted)])).alias("e")
            yield keys, df.select(*keys, each).select(*keys, "e.monomial", "e.value")


def long_table(roots: Roots) -> DataFrame:
    """(monomial STRING, keys MAP<STRING,STRING>, value DOUBLE): all entries as one table, nothing collected.

    A null in a map means a key that the monomial lacks or a null level of one that it has."""

    def one(keys: Keys, df: DataFrame) -> DataFrame:
        named = F.map_from_arrays(F.array(*[F.lit(k) for k in keys]).cast("array<string>"), F.array(*[F.col(k).cast("string") for k in keys]).cast("array<string>"))
        own = F.map_filter(named, lambda k, _: F.contains(F.col("monomial"), F.concat(F.lit("["), k, F.lit("]"))))
        return df.select("monomial", own.alias("keys"), "value")

    return reduce(DataFrame.unionByName, [one(keys, df) for keys, df in _entries(roots)])


def save(roots: Roots, path: str) -> None:
    long_table(roots).write.mode("overwrite").partitionBy("monomial").parquet(path)


def keyed_table(roots: Roots) -> DataFrame:
    """(monomial, k STRING, value): keys as one text, for comparisons."""
    return reduce(DataFrame.unionByName, [df.select("monomial", F.concat_ws("|", *[F.col(k).cast("string") for k in keys]).alias("k"), "value") for keys, df in _entries(roots)])


def category_levels(query: FeatureQuery, name: str) -> DataFrame:
    """Dictionary of a categorical variable over its relation: level and a dense code in order of the level."""
    owner = next(r for r in query.relations if name in query.relations[r].columns)
    levels = query.bound(owner).select(F.col(name).alias("level")).distinct()
    return levels.withColumn("code", F.row_number().over(Window.orderBy("level")) - 1)


def onehot_query(spark: SparkSession, query: FeatureQuery) -> FeatureQuery:
    """Every categorical feature as 0/1 columns of its relation, now continuous: the linear-only baseline's input."""
    relations, new = dict(query.relations), []
    for c in query.categorical:
        owner = next(r for r in relations if c in relations[r].columns)
        levels = [r.level for r in category_levels(query, c).orderBy("level").select("level").collect()]
        names = [f"{c}__{i}" for i in range(len(levels))]
        relations[owner] = relations[owner].select("*", *[(F.col(c) == F.lit(v)).cast("int").alias(n) for n, v in zip(names, levels, strict=True)])
        new += names
    return FeatureQuery(relations, (*query.continuous, *new), (), query.response, query.where, query.set_semantics, query.null_policy, query.scale)
