"""Moments and counts in one pass over the join where at most one category is large.

The small categories of a row travel as one whole number. Rows are dealt out by the large category, so that a task holds all rows
of its levels: it groups them by every key set at once, and entries of the large category leave it finished. What tasks hold of
the other key sets is small and is merged where it arrives."""

from __future__ import annotations

import ctypes
import gc
import json
from collections.abc import Iterator, Mapping
from contextlib import suppress
from dataclasses import dataclass
from math import prod

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.monomials import Monomial
from ..plans.order import VariableOrder
from ..plans.query import FeatureQuery
from ..plans.statistics import Statistics
from ..plans.views import Views

#: Categories of more levels than this are large.
SMALL_LEVELS = 1_000
#: Most combinations of small categories that a key set may have, and most places of one grouping that are counted without sorting.
COMBINATIONS, PLACES = 2_000_000, 1 << 23
#: Rows that a task groups at once, and most numbers that it holds of products of their columns.
ROWS, PRODUCTS = 1 << 18, 1 << 23
#: Tasks for each core that send sums of all key sets.
TASKS = 2
#: Most sums that a task holds by place, one place for each combination of small categories; others are held for those that occur.
HELD = 1 << 24
#: The packed small categories of a row.
CODE = "__code"

#: What stands for a null among whole numbers.
NO_NUMBER = np.iinfo(np.int64).min

Keys = tuple[str, ...]


def narrow(x: np.ndarray) -> np.ndarray:
    """The same numbers in the narrowest type that holds all of them: counts are small and whole."""
    if not len(x):
        return x
    low, high = x.min(), x.max()
    for t in (np.uint8, np.uint16, np.uint32) if low >= 0 else (np.int32,):
        if low >= np.iinfo(t).min and high <= np.iinfo(t).max:
            return x.astype(t) if x.dtype.kind in "iu" or (np.floor(x) == x).all() else x
    return x


@dataclass
class Coded:
    """Joined rows: the large category, the numbers that are summed, and the small categories as one whole number.

    A small category's digit is (code // stride) % base: 0 for a null, else one more than the place of its level."""

    frame: DataFrame
    large: str | None
    levels: dict[str, list]
    base: dict[str, int]
    stride: dict[str, int]
    kinds: dict[str, T.DataType]


def _kind(query: FeatureQuery, name: str) -> T.DataType:
    return next(query.bound(r).schema[name].dataType for r in query.relations if name in query.attributes(r))


def split(query: FeatureQuery, statistics: Statistics, sets: list[Keys]) -> str | None | bool:
    """The large category (None: there is none), or False where the rows cannot be dealt so."""
    cats = query.categorical
    if not all(isinstance(_kind(query, c), T.IntegralType | T.StringType) for c in cats):
        return False
    count = {c: max((d[c] for d in statistics.distinct.values() if c in d), default=0.0) for c in cats}
    large = [c for c in cats if count[c] > SMALL_LEVELS]
    small = [c for c in cats if c not in large]
    if len(large) > 1 or prod(1.1 * count[c] + 3 for c in small) >= 2**62:
        return False
    if any(prod(1.1 * count[c] + 3 for c in ks if c in small) > COMBINATIONS for ks in sets):
        return False
    return large[0] if large else None


def coded(query: FeatureQuery, statistics: Statistics, large: str | None, numbers: list[str]) -> Coded:
    small = [c for c in query.categorical if c != large]
    owner = {c: next(r for r in query.relations if c in query.attributes(r)) for c in small}
    kinds = {c: _kind(query, c) for c in query.categorical}
    levels: dict[str, list] = {}
    for r in dict.fromkeys(owner.values()):
        mine = [c for c in small if owner[c] == r]
        row = query.bound(r).agg(*[F.sort_array(F.collect_set(c)).alias(c) for c in mine]).first()
        levels |= {c: list(row[c]) for c in mine}
    base = {c: len(levels[c]) + 1 for c in small}
    stride, at = {}, 1
    for c in small:
        stride[c] = at
        at *= base[c]
    joins, relations, codes, splits = query.joins(), {}, [], {}
    for r in query.relations:
        rows, mine = query.bound(r), [c for c in small if owner[c] == r]
        keep = [c for c in rows.columns if c in joins or c in numbers or c == large]
        columns = [F.col(c) for c in keep]
        if mine:
            digits = [F.coalesce(F.array_position(F.array(*[F.lit(v) for v in levels[c]]), F.col(c)), F.lit(0)) * F.lit(stride[c]) if levels[c] else F.lit(0) for c in mine]
            codes.append(f"__code{len(codes)}")
            columns.append(sum(digits[1:], digits[0]).cast("long").alias(codes[-1]))
        relations[r] = rows.select(*columns)
        splits[tuple(relations[r].columns)] = statistics.splits.get(tuple(rows.columns), 0)
    plain = FeatureQuery(relations, tuple(n for n in query.continuous if n in numbers), (large,) if large else (), query.response if query.response in numbers else None, extra=tuple(codes))
    known = Statistics(statistics.rows, statistics.distinct, {k: v or 1 << 30 for k, v in splits.items()})
    frame = Views(plain, VariableOrder.suggest(plain), statistics=known).joined(large, large is not None)
    code = sum((F.col(c) for c in codes[1:]), F.col(codes[0])) if codes else F.lit(0).cast("long")
    return Coded(frame.select(*([large] if large else []), *numbers, code.alias(CODE)), large, levels, base, stride, kinds)


def _grouped(key: np.ndarray | None, n_keys: int, code: np.ndarray, digits: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Occurring combinations as mixed numbers (the large category's place first), their rows, and each row's combination."""
    mixed, places = (np.zeros(len(code), np.int64), 1) if key is None else (key.astype(np.int64), n_keys)
    for stride, base in digits:
        mixed *= base
        mixed += code // stride % base
        places *= base
    if places <= max(PLACES, 8 * len(code)):
        n = np.bincount(mixed, minlength=places)
        found = np.flatnonzero(n)
        at = np.zeros(places, np.int32)
        at[found] = np.arange(len(found), dtype=np.int32)
        return found, n[found], at[mixed]
    found, inverse, n = np.unique(mixed, return_inverse=True, return_counts=True)
    return found, n, inverse


def _chunks(batches, rows: int | None = None) -> Iterator[pa.Table]:
    held, n = [], 0
    for b in batches:
        held.append(b)
        n += b.num_rows
        if n >= (rows or ROWS):
            yield pa.Table.from_batches(held)
            held, n = [], 0
    if n:
        yield pa.Table.from_batches(held)


def _large(table: pa.Table, large: str) -> tuple[pa.Array, np.ndarray]:
    """The large category's levels in the rows (a null is one) and each row's place among them."""
    d = table[large].combine_chunks().dictionary_encode(null_encoding="encode")
    return d.dictionary, d.indices.to_numpy()


def packed(columns: dict, at: list[int]) -> pa.RecordBatch:
    """Columns as one compressed value, marked with `at`, beside the number of their rows."""
    table = pa.table(columns)
    table = table.replace_schema_metadata({"at": json.dumps(at)})
    out = pa.BufferOutputStream()
    with pa.ipc.new_stream(out, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as writer:
        writer.write_table(table)
    counted = pa.list_(pa.struct([("at", pa.list_(pa.int32())), ("n", pa.int64())]))
    return pa.RecordBatch.from_arrays([pa.array([[{"at": at, "n": table.num_rows}]], counted), pa.array([out.getvalue().to_pybytes()], pa.binary())], ["counts", "part"])


PACKED = "counts array<struct<at: array<int>, n: bigint>>, part binary"


class _Products(dict):
    """Products of a chunk's columns by their factors, each made from a shorter one."""

    def __init__(self, values: dict[str, np.ndarray], n: int) -> None:
        self.values = values
        self[()] = np.ones(n)

    def __missing__(self, factors: tuple[str, ...]) -> np.ndarray:
        own = self.values[factors[-1]]
        self[factors] = own if len(factors) == 1 else self[factors[:-1]] * own
        return self[factors]


def _factors(m: Monomial) -> tuple[str, ...]:
    return tuple(v for v, e in m.cont for _ in range(e))


def _regrouped(parts: list[tuple[pa.Array | None, np.ndarray, np.ndarray]]) -> tuple[pa.Array | None, np.ndarray, np.ndarray]:
    """Groups (levels of the large category, codes, sums) of several parts of one key set as one."""
    if len(parts) == 1:
        return parts[0]
    code = np.concatenate([p[1] for p in parts])
    total = np.concatenate([p[2] for p in parts])
    if parts[0][0] is None:
        found, inverse = np.unique(code, return_inverse=True)
        levels, own = None, found
    else:
        d = pa.chunked_array([p[0] for p in parts]).combine_chunks().dictionary_encode(null_encoding="encode")
        width = int(code.max(initial=0)) + 1
        found, inverse = np.unique(d.indices.to_numpy().astype(np.int64) * width + code, return_inverse=True)
        levels, own = d.dictionary.take(pa.array(found // width)), found % width
    return levels, own, np.column_stack([np.bincount(inverse, weights=total[:, j], minlength=len(found)) for j in range(total.shape[1])])


def sums(rows: Coded, sets: list[tuple[Keys, list[Monomial]]], wide: bool = False) -> DataFrame:
    """Packed parts (see `packed`; at: place of the key set) of the keys (small ones as digits) and m0, m1, ...

    Entries of the large category are finished, those of the other key sets are what each task has. wide: sums of small categories
    are held by place and, where there is no large category, merged in one shuffle, so that they are finished too."""
    large, base, stride = rows.large, rows.base, rows.stride
    plans = [([c for c in ks if c != large], large in ks, wanted) for ks, wanted in sets]
    places = [prod(base[c] for c in small) for small, _, _ in plans]
    left, by_place = HELD, set()
    for s in sorted(range(len(plans)), key=lambda s: places[s] * (1 + len(plans[s][2]))):
        small, dealt, wanted = plans[s]
        left -= places[s] * (1 + len(wanted))
        if wide and small and not dealt and left >= 0:
            by_place.add(s)
    factors = [[_factors(m) for m in wanted] for _, _, wanted in plans]
    products = {f[:i] for s, found in enumerate(factors) if sets[s][0] for f in found for i in range(2, len(f) + 1)}
    at_once = min(ROWS, max(1 << 14, PRODUCTS // (1 + len(products))))

    def scalars(known: _Products, wanted: list[tuple[str, ...]]) -> np.ndarray:
        """Sums of products over all rows of a chunk; many of them as inner products of their halves."""
        if not wide:
            return np.array([known[f].sum() for f in wanted])
        halves = [(f[: len(f) // 2], f[len(f) // 2 :]) for f in wanted]
        at = {h: i for i, h in enumerate(dict.fromkeys(h for pair in halves for h in pair))}
        gram = np.stack([known[h] for h in at])
        gram = gram @ gram.T
        return np.array([gram[at[a], at[b]] for a, b in halves])

    def part(s: int, levels: pa.Array | None, code: np.ndarray, total: np.ndarray) -> pa.RecordBatch:
        small, dealt, wanted = plans[s]
        columns: dict = {large: levels} if dealt else {}
        for c in reversed(small):
            columns[c] = (code % base[c]).astype(np.min_scalar_type(base[c]))
            code = code // base[c]
        whole = [(total[:, j].astype(np.uint32) if not m.cont and total[:, j].max(initial=0) < 2**32 else total[:, j]) for j, m in enumerate(wanted)]
        return packed(columns | {f"m{j}": x for j, x in enumerate(whole)}, [s])

    def found_of(s: int, n: np.ndarray, total: np.ndarray) -> tuple[None, np.ndarray, np.ndarray]:
        """What occurs of sums held by place."""
        found = np.flatnonzero(n)
        return None, found, np.column_stack([total[j][found] if f else n[found] for j, f in enumerate(factors[s])])

    def task(batches):
        held: list[list] = [[] for _ in plans]
        total: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        for table in _chunks(batches, at_once):
            code = table[CODE].to_numpy()
            levels, key = _large(table, large) if large else (None, None)
            known = _Products({n: table[n].to_numpy().astype(float, copy=False) for n in table.column_names if n not in (large, CODE)}, len(code))
            digit = {c: code // stride[c] % base[c] for c in stride} if by_place else {}
            mixed: dict[Keys, np.ndarray] = {}
            for s, (small, dealt, wanted) in enumerate(plans):
                if s in by_place:
                    first, last = tuple(small[:-1]), small[-1]
                    here = digit[last] if not first else (mixed[first] if first in mixed else _mixed(first, digit, base)) * base[last] + digit[last]
                    mixed[tuple(small)] = here
                    if s not in total:
                        total[s] = np.zeros(places[s], np.int64), np.zeros((len(wanted), places[s]))
                    n, sums_of = total[s]
                    n += np.bincount(here, minlength=places[s])
                    for j, f in enumerate(factors[s]):
                        if f:
                            sums_of[j] += np.bincount(here, weights=known[f], minlength=places[s])
                    continue
                if not (small or dealt):
                    held[s].append((None, np.zeros(1, np.int64), scalars(known, factors[s])[None, :]))
                    continue
                found, n, at = _grouped(key if dealt else None, len(levels) if dealt else 1, code, [(stride[c], base[c]) for c in small])
                out = np.empty((len(found), len(wanted)))
                for j, f in enumerate(factors[s]):
                    out[:, j] = np.bincount(at, weights=known[f], minlength=len(found)) if f else n
                held[s].append((levels.take(pa.array(found // places[s])) if dealt else None, found % places[s], out))
            if len(max(held, key=len)) > 4:
                held = [[_regrouped(parts)] if parts else [] for parts in held]
        for s, parts in enumerate(held):
            parts = [found_of(s, *total.pop(s))] if s in total else parts
            if parts:
                levels, code, mine = _regrouped(parts)
                yield part(s, levels, code, mine) if large or not wide else packed({"code": narrow(code)} | {f"m{j}": narrow(x) for j, x in enumerate(mine.T)}, [s])

    def merged(batches):
        total: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        held: dict[int, list] = {}
        for b in batches:
            for p in b.column("part"):
                came = pa.ipc.open_stream(p.as_py()).read_all()
                (s,) = json.loads(came.schema.metadata[b"at"])
                code, columns = came["code"].to_numpy().astype(np.int64), [came[f"m{j}"].to_numpy() for j in range(len(plans[s][2]))]
                if s in by_place:
                    if s not in total:
                        total[s] = np.zeros(places[s], bool), np.zeros((len(columns), places[s]))
                    n, sums_of = total[s]
                    n[code] = True
                    for j, x in enumerate(columns):
                        sums_of[j][code] += x
                else:
                    held[s] = [_regrouped([*held.get(s, []), (None, code, np.column_stack(columns).astype(float, copy=False))])]
        for s, (n, sums_of) in total.items():
            code = np.flatnonzero(n)
            yield part(s, None, code, sums_of[:, code].T)
        for s, ((_, code, mine),) in held.items():
            yield part(s, None, code, mine)

    if large or not wide:
        return rows.frame.mapInArrow(task, PACKED)
    # each task sends sums of its own: few tasks of many rows each
    sent = rows.frame.coalesce(TASKS * rows.frame.sparkSession.sparkContext.defaultParallelism).mapInArrow(task, PACKED)
    return sent.repartition(F.col("counts")[0]["at"][0]).mapInArrow(merged, PACKED)


def _mixed(small: Keys, digit: dict[str, np.ndarray], base: dict[str, int]) -> np.ndarray:
    out = digit[small[0]]
    for c in small[1:]:
        out = out * base[c] + digit[c]
    return out


def combinations(rows: Coded, sets: list[Keys]) -> dict[Keys, int]:
    """How many key combinations of each key set occur in the join.

    A task holds the distinct codes of its rows, for each level of the large category: what it finds of key sets with that is
    finished and is sent as a number, of the others it sends one bit for each place, and those are united."""
    large, base, stride = rows.large, rows.base, rows.stride
    plans = [([(stride[c], base[c]) for c in ks if c != large], large in ks) for ks in sets]
    out = "at int, n bigint, bits binary"

    def task(batches):
        pairs: list[tuple[pa.Array | None, np.ndarray, np.ndarray]] = []
        for table in _chunks(batches):
            levels, key = _large(table, large) if large else (None, np.zeros(table.num_rows, np.int64))
            pairs.append(_distinct([(levels, key, table[CODE].to_numpy())]))
            if len(pairs) > 4:
                pairs = [_distinct(pairs)]
        if not pairs:
            return
        _, key, code = _distinct(pairs)
        n_keys = int(key.max()) + 1
        for s, (digits, finished) in enumerate(plans):
            found, _, _ = _grouped(key if finished else None, n_keys if finished else 1, code, digits)
            bits = None
            if not finished:
                places = np.zeros(prod(b for _, b in digits), bool)
                places[found] = True
                bits = np.packbits(places).tobytes()
            yield pa.RecordBatch.from_arrays([pa.array([s], pa.int32()), pa.array([len(found) if finished else 0], pa.int64()), pa.array([bits], pa.binary())], ["at", "n", "bits"])

    united: dict[int, np.ndarray] = {}
    count = dict.fromkeys(sets, 0)
    sent = rows.frame.mapInArrow(task, out).persist()
    try:
        sent.count()  # all tasks at once; what they send comes one part at a time
        for r in sent.toLocalIterator(prefetchPartitions=True):
            if r.bits is None:
                count[sets[r.at]] += r.n
            else:
                mine = np.frombuffer(r.bits, np.uint8)
                united[r.at] = united[r.at] | mine if r.at in united else mine
    finally:
        sent.unpersist()
    return count | {sets[s]: int(np.unpackbits(x).sum()) for s, x in united.items()}


def _distinct(parts: list[tuple[pa.Array | None, np.ndarray, np.ndarray]]) -> tuple[pa.Array | None, np.ndarray, np.ndarray]:
    """Distinct pairs of a large level and a code, of several parts: levels, the place of each pair's level, and its code."""
    code = np.concatenate([p[2] for p in parts])
    if parts[0][0] is None:
        code = np.unique(code)
        return None, np.zeros(len(code), np.int64), code
    d = pa.chunked_array([p[0].take(pa.array(p[1])) for p in parts]).combine_chunks().dictionary_encode(null_encoding="encode")
    known, place = np.unique(code, return_inverse=True)
    found = np.unique(d.indices.to_numpy().astype(np.int64) * len(known) + place)
    return d.dictionary, found // len(known), known[found % len(known)]


@dataclass
class Wide:
    """Counts of a large category's levels (down) beside a small one's (across), where that is less to hold than entries."""

    keys: Keys
    down: str
    kinds: dict[str, pd.CategoricalDtype]
    counts: np.ndarray

    def table(self) -> pd.DataFrame:
        places = dict(zip((self.down, *(c for c in self.keys if c != self.down)), np.nonzero(self.counts), strict=True))
        codes = {c: places[c].astype(np.min_scalar_type(-len(self.kinds[c].categories) - 1)) for c in self.keys}
        return pd.DataFrame({c: pd.Categorical.from_codes(codes[c], dtype=self.kinds[c]) for c in self.keys} | {"m0": self.counts[self.counts > 0]}, copy=False)


class Tables(Mapping):
    """Tables by key set; those of wide counts are made when they are asked for and not kept."""

    def __init__(self, held: dict[Keys, pd.DataFrame | Wide]) -> None:
        self.held = held
        self.wide = {ks: t for ks, t in held.items() if isinstance(t, Wide)}

    def __getitem__(self, ks: Keys) -> pd.DataFrame:
        return self.wide[ks].table() if ks in self.wide else self.held[ks]

    def __iter__(self) -> Iterator[Keys]:
        return iter(self.held)

    def __len__(self) -> int:
        return len(self.held)

    def lengths(self) -> dict[Keys, int]:
        return {ks: int(np.count_nonzero(t.counts)) if ks in self.wide else len(t) for ks, t in self.held.items()}


class Gathered:
    """What tasks sent of each key set, as it comes in: large levels as they are, small ones as digits, sums narrow."""

    def __init__(self, rows: Coded, sets: list[tuple[Keys, list[Monomial]]]) -> None:
        self.rows, self.sets = rows, sets
        self.parts: list[list[dict[str, np.ndarray]]] = [[] for _ in sets]
        self.texts: dict = {}

    def most(self, s: int) -> int:
        """Rows that a key set can have once those of all tasks are merged."""
        ks = self.sets[s][0]
        return 1 << 62 if self.rows.large in ks else prod(self.rows.base[c] for c in ks)

    def add(self, part: pa.Table) -> None:
        (s,) = json.loads(part.schema.metadata[b"at"])
        ks, wanted = self.sets[s]
        out = {c: part[c].to_numpy() for c in ks if c != self.rows.large}
        if self.rows.large in ks:
            column = part[self.rows.large].combine_chunks()
            if pa.types.is_integer(column.type):
                out[self.rows.large] = narrow(column.cast(pa.int64()).fill_null(NO_NUMBER).to_numpy())
            else:
                out[self.rows.large] = np.array([self.texts.setdefault(v, len(self.texts)) for v in column.to_pylist()], np.int32)
        self.parts[s].append(out | {f"m{j}": narrow(part[f"m{j}"].to_numpy()).copy() for j in range(len(wanted))})

    def _places(self, name: str, seen: np.ndarray) -> tuple[pd.CategoricalDtype, np.ndarray]:
        """Of the digits of a small category, or the texts of the large one: those seen in order of their text, and where each is (a null: -1)."""
        known = [None, *self.rows.levels[name]] if name in self.rows.levels else list(self.texts)
        order = sorted((i for i in seen.tolist() if known[i] is not None), key=lambda i: str(known[i]))
        place = np.full(len(known), -1, np.min_scalar_type(-len(order) - 1))
        place[order] = np.arange(len(order))
        whole = isinstance(self.rows.kinds[name], T.IntegralType)
        return pd.CategoricalDtype(pd.Index([known[i] for i in order], dtype=np.int64 if whole else object)), place

    def tables(self) -> Tables:
        large, kinds = self.rows.large, {}
        for c in self.rows.kinds:
            seen = [np.unique(np.concatenate([p[c] for p in parts])) for (ks, _), parts in zip(self.sets, self.parts, strict=True) if ks == (c,) and parts]
            seen = seen or [np.unique(np.concatenate([p[c] for p in parts])) for (ks, _), parts in zip(self.sets, self.parts, strict=True) if c in ks and parts]
            seen = np.unique(np.concatenate(seen)) if seen else np.zeros(0, np.int64)
            if c == large and isinstance(self.rows.kinds[c], T.IntegralType):
                found = seen[seen != NO_NUMBER].astype(np.int64) if seen.dtype == np.int64 else seen.astype(np.int64)
                order = np.argsort(found.astype("S20"), kind="stable")
                place = np.empty(len(found), np.int32)
                place[order] = np.arange(len(found), dtype=np.int32)
                kinds[c] = pd.CategoricalDtype(pd.Index(found[order])), (found, place)
            else:
                kinds[c] = self._places(c, seen)
        out: dict[Keys, pd.DataFrame | Wide] = {}
        for s, (ks, wanted) in enumerate(self.sets):
            parts, self.parts[s] = self.parts[s], []
            wide = self._wide(ks, wanted, parts, kinds)
            if wide is not None:
                out[ks] = wide
                continue
            columns = {c: np.concatenate([p.pop(c) for p in parts]) if parts else np.zeros(0) for c in (*ks, *(f"m{j}" for j in range(len(wanted))))}
            for c in ks:
                columns[c] = _code(columns[c], kinds[c][1]).astype(np.min_scalar_type(-len(kinds[c][0].categories) - 1), copy=False)
            if large in ks or (ks and len(parts) == 1):  # in the layout's order, so that sums over levels walk through memory
                order = np.lexsort([columns[c] for c in reversed(ks)]).astype(np.min_scalar_type(len(columns[ks[0]])))
                for c in columns:
                    columns[c] = columns[c][order]
                del order
            for c in ks:
                columns[c] = pd.Categorical.from_codes(columns[c], dtype=kinds[c][0])
            table = pd.DataFrame(columns, copy=False)
            out[ks] = table if large in ks or len(parts) == 1 else _merged(table, ks)
            if large in ks:
                del parts
                trimmed()  # else what came in small parts stays beside the tables until all are made
        return Tables(out)

    def _wide(self, ks: Keys, wanted: list[Monomial], parts: list[dict], kinds: dict) -> Wide | None:
        if len(ks) != 2 or self.rows.large not in ks or len(wanted) != 1 or wanted[0].cont or not parts:
            return None
        (small,) = (c for c in ks if c != self.rows.large)
        kind = np.result_type(*(p["m0"].dtype for p in parts))
        shape = len(kinds[self.rows.large][0].categories), len(kinds[small][0].categories)
        if shape[0] * shape[1] * kind.itemsize > sum(len(p["m0"]) for p in parts) * (5 + kind.itemsize):
            return None
        codes = [(_code(p[self.rows.large], kinds[self.rows.large][1]), _code(p[small], kinds[small][1])) for p in parts]
        if any((x < 0).any() for pair in codes for x in pair):  # a null has no place across or down
            return None
        counts = np.zeros(shape, kind)
        for (down, across), p in zip(codes, parts, strict=True):
            counts[down, across] = p["m0"]
        return Wide(ks, self.rows.large, {c: kinds[c][0] for c in ks}, counts)


def trimmed(session: SparkSession | None = None) -> None:
    """Give freed memory back: many small parts have come in and gone. session: also what the JVM's heap holds for nothing, and
    shuffles that nothing refers to any more."""
    gc.collect()
    if session is not None:
        session.sparkContext._jvm.System.gc()
    pa.default_memory_pool().release_unused()
    with suppress(OSError, AttributeError):  # only some C libraries have it
        ctypes.CDLL(None).malloc_trim(0)


def _code(values: np.ndarray, place: np.ndarray | tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Places of levels, -1 for a null."""
    if not len(values):
        return np.zeros(0, np.int32)
    if not isinstance(place, tuple):
        return place[values]
    found, at = place
    code = at[np.minimum(np.searchsorted(found.astype(values.dtype), values), len(found) - 1)] if len(found) else np.full(len(values), -1)
    return np.where(values == NO_NUMBER, np.int32(-1), code) if values.dtype == np.int64 else code


def _merged(table: pd.DataFrame, ks: Keys) -> pd.DataFrame:
    """Rows of several tasks as one for each key."""
    sums = [c for c in table.columns if c not in ks]
    if not ks:
        return pd.DataFrame({c: [table[c].sum()] for c in sums}) if len(table) else table
    if not len(table):
        return table
    return table.groupby(list(ks), observed=True, dropna=False, sort=False, as_index=False)[sums].sum()
