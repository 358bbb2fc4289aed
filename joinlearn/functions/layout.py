"""Where each block of the feature map lives in the parameter vector, and the sparse second-moment matrix over it."""

from __future__ import annotations

import os
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from functools import cache
from itertools import chain

import numpy as np
import pandas as pd

from ..operators.dealt import narrow
from ..operators.moments import Moments
from ..plans.monomials import Monomial, variable

#: Aggregates of more entries than this are multiplied where they are held, not listed.
LISTED = 2_000
#: Entries of a held aggregate that are multiplied at once.
CHUNK = 1 << 16
#: Blocks of a key set with more entries than this are multiplied together.
TOGETHER = 1 << 14
#: Threads that multiply them.
THREADS = min(3, os.cpu_count() or 1)
#: Most places of an aggregate that is written out as a matrix, and of all such matrices.
DENSE, ALL_DENSE = 1 << 20, 1 << 24


class FeatureLayout:
    """Blocks of h in order: one slot for a scalar monomial, one for each occurring key tuple of a categorical one."""

    def __init__(self, moments: Moments, h: list[Monomial]) -> None:
        self.h = h
        self.moments = moments
        self.levels: dict[str, np.ndarray] = {}
        for c in sorted({c for m in h for c in m.cats}):
            own = moments.tables[(c,)][c].astype("category")
            found = own.cat.categories
            if own.hasnans:
                found = np.array([*found, None], object)
            elif not isinstance(moments.tables[(c,)][c].dtype, pd.CategoricalDtype):
                found = np.array(sorted(found, key=str), object)
            self.levels[c] = np.asarray(found)
        self._sorted: dict[tuple[str, ...], np.ndarray] = {}
        self._positions: dict[tuple, np.ndarray] = {}
        self.offset: dict[Monomial, int] = {}
        self.size: dict[Monomial, int] = {}
        at = 0
        for m in h:
            self.offset[m], self.size[m] = at, len(self.codes(m.cats)) if m.cats else 1
            at += self.size[m]
        self.width = at

    def _level(self, keys: tuple[str, ...], c: str) -> np.ndarray:
        """For each row of the key set's table, the place of its level of c. Tables that moments() makes hold just that."""
        column, n = self.moments.tables[keys][c], len(self.levels[c])
        if isinstance(column.dtype, pd.CategoricalDtype) and len(column.dtype.categories) + (self.levels[c][-1:] == [None]).sum() == n:
            code = column.array.codes
            return np.where(code < 0, n - 1, code.astype(np.int64)) if column.hasnans else code
        known = {v: i for i, v in enumerate(self.levels[c].tolist())}
        return np.array([known[None if v != v else v] for v in column.tolist()], np.int64)

    def _mixed(self, keys: tuple[str, ...], subset: tuple[str, ...]) -> np.ndarray:
        code = np.zeros(len(self.moments.tables[keys]), np.int64)
        for c in subset:
            code *= len(self.levels[c]) + 1
            code += self._level(keys, c)
        return code

    def codes(self, keys: tuple[str, ...]) -> np.ndarray:
        """Sorted codes of the key tuples of a key set; a tuple's place in it is its place in the block."""
        if len(keys) == 1:
            return np.arange(len(self.levels[keys[0]]))
        if keys not in self._sorted:
            self._sorted[keys] = np.sort(narrow(self._mixed(keys, keys)))
        return self._sorted[keys]

    def positions(self, keys: tuple[str, ...], subset: tuple[str, ...]) -> np.ndarray:
        """For each row of the key set's table, the place of its part on `subset` in that block, in a type that may be narrow."""
        at = (keys, subset)
        if at not in self._positions:
            n = len(self.moments.tables[keys])
            if not subset:
                self._positions[at] = np.zeros(n, np.int8)
            elif len(subset) == 1:
                self._positions[at] = self._level(keys, subset[0])
            else:
                codes = self.codes(subset)
                self._positions[at] = np.searchsorted(codes, self._mixed(keys, subset).astype(codes.dtype, copy=False)).astype(np.int32)
        return self._positions[at]

    def block(self, m: Monomial) -> slice:
        return slice(self.offset[m], self.offset[m] + self.size[m])

    def keys_of(self, m: Monomial) -> list[tuple]:
        """The key tuples of a block in order of place."""
        order = np.argsort(self.positions(m.cats, m.cats), kind="stable")
        return list(zip(*(self.levels[c][self._level(m.cats, c)[order]].tolist() for c in m.cats), strict=True))


@dataclass
class Block:
    """Entries of one aggregate for one pair of blocks of h: the layout's places, the sums as the moments hold them."""

    values: np.ndarray
    rows: np.ndarray
    cols: np.ndarray
    at: slice
    beside: slice
    #: Whether rows (cols) are just 0, 1, ...: entries then are the block's, one after the other.
    rows_in_order: bool = False
    cols_in_order: bool = False

    @property
    def diagonal(self) -> bool:
        return self.at == self.beside

    def halves(self) -> Iterator[tuple[np.ndarray, slice, np.ndarray, slice]]:
        yield self.rows, self.at, self.cols, self.beside
        if not self.diagonal:
            yield self.cols, self.beside, self.rows, self.at

    def multiply(self, g: np.ndarray, out: np.ndarray, n: float) -> None:
        for low in range(0, len(self.values), CHUNK):
            part = slice(low, low + CHUNK)
            v = self.values[part] / n
            for (r, into, c, of), (direct, given) in zip(self.halves(), ((self.rows_in_order, self.cols_in_order), (self.cols_in_order, self.rows_in_order)), strict=False):
                weighted = v * (g[of.start] if of.stop - of.start == 1 else g[of][part] if given else g[of].take(c[part]))
                if into.stop - into.start == 1:
                    out[into.start] += weighted.sum()
                elif direct:
                    out[into][part] += weighted
                else:
                    at = r[part]
                    first = at.min()  # places that are near each other need no sums over the whole block
                    found = np.bincount((at - first).astype(np.intp), weights=weighted)
                    out[into][first : first + len(found)] += found


@dataclass
class DenseBlock(Block):
    """A block most of whose places are entries: it is multiplied as a matrix."""

    def __post_init__(self) -> None:
        self.matrix = np.zeros((self.at.stop - self.at.start, self.beside.stop - self.beside.start))
        self.matrix[self.rows, self.cols] = self.values

    def multiply(self, g: np.ndarray, out: np.ndarray, n: float) -> None:
        down, across = self.matrix @ (g[self.beside] / n), (g[self.at] / n) @ self.matrix
        out[self.at] += down
        out[self.beside] += across


@dataclass
class WideBlock:
    """Counts of two categories as a matrix, where most of their pairs occur."""

    counts: np.ndarray
    at: slice
    beside: slice

    diagonal = False

    @property
    def values(self) -> np.ndarray:
        return self.counts[self.counts > 0]

    def halves(self) -> Iterator[tuple[np.ndarray, slice, np.ndarray, slice]]:
        rows, cols = np.nonzero(self.counts)
        yield rows, self.at, cols, self.beside
        yield cols, self.beside, rows, self.at

    def multiply(self, g: np.ndarray, out: np.ndarray, n: float) -> None:
        across, down, of, into = np.zeros(self.counts.shape[1]), out[self.at], g[self.at], g[self.beside] / n
        rows = max(1, CHUNK // (8 * self.counts.shape[1]))
        for low in range(0, len(self.counts), rows):
            part = slice(low, low + rows)
            x = self.counts[part].astype(float)
            down[part] += x @ into
            across += of[part] @ x
        out[self.beside] += across / n


class Together:
    """The blocks of one key set: for some rows of its table at once, coefficients are fetched once for each block of h, sums read
    once for each aggregate, and products added once to each block of h.

    Where all rows at hand lie in one place of a block, as under a small category that the table is sorted by, its coefficient is
    one number, and what such blocks give and get is one matrix product."""

    def __init__(self, blocks: list[tuple[Monomial, Block]]) -> None:
        aggregates: dict[Monomial, int] = {}
        members: dict[int, int] = {}
        self.sums: list[np.ndarray] = []
        #: Of each block of h: where it lies, which array of places it has, and whether its places are just 0, 1, ...
        self.members: list[tuple[slice, int, bool]] = []
        self.places: list[np.ndarray] = []
        #: Ordered pairs: what takes part, by aggregate, in which blocks' products with which coefficients.
        self.pairs: list[tuple[int, int, int]] = []
        arrays: dict[int, int] = {}

        def member(of: slice, places: np.ndarray, ordered: bool) -> int:
            if of.start not in members:
                members[of.start] = len(self.members)
                if id(places) not in arrays:
                    arrays[id(places)] = len(self.places)
                    self.places.append(places)
                self.members.append((of, arrays[id(places)], ordered))
            return members[of.start]

        for m, b in blocks:
            if m not in aggregates:
                aggregates[m] = len(self.sums)
                self.sums.append(b.values)
            i, j = member(b.at, b.rows, b.rows_in_order), member(b.beside, b.cols, b.cols_in_order)
            self.pairs += [(aggregates[m], i, j)] if b.diagonal else [(aggregates[m], i, j), (aggregates[m], j, i)]
        self.n_rows, self.at_once = len(self.sums[0]), CHUNK // 2
        self.spans = [[self._span(x[low : low + self.at_once]) for x in self.places] for low in range(0, self.n_rows, self.at_once)]

    @staticmethod
    def _span(x: np.ndarray) -> tuple[int, int, bool]:
        """First and last place of some rows, and whether each place is met once, in order."""
        return int(x.min()), int(x.max()), bool((x[1:] > x[:-1]).all())

    def _products(self, chunk: int, g: np.ndarray, n: float) -> list[tuple[slice, object, np.ndarray | float]]:
        """What some rows add, block of h by block of h: where it lies, places in it, none of them twice, and summands."""
        low = chunk * self.at_once
        part, spans = slice(low, min(low + self.at_once, self.n_rows)), self.spans[chunk]
        v = np.empty((len(self.sums), part.stop - low))
        for k, x in enumerate(self.sums):
            np.multiply(x[part], 1 / n, out=v[k])
        at = [None if first == last else x[part].astype(np.intp) for x, (first, last, _) in zip(self.places, spans, strict=True)]
        moving = {i: r for r, i in enumerate(i for i, (_, p, _) in enumerate(self.members) if at[p] is not None)}
        fixed = {i: g[of.start + spans[p][0]] for i, (of, p, _) in enumerate(self.members) if at[p] is None}
        own = np.empty((len(moving), v.shape[1]))
        for i, row in moving.items():
            of, p, ordered = self.members[i]
            if ordered:
                own[row] = g[of][part]
            else:
                np.take(g[of], at[p], out=own[row], mode="clip")
        weights = np.zeros((len(moving), len(v)))
        for k, i, j in self.pairs:
            if i in moving and j in fixed:
                weights[moving[i], k] += fixed[j]
        got, inner, product = weights @ v, v @ own.T, np.empty(v.shape[1])
        numbers = dict.fromkeys(fixed, 0.0)
        for k, i, j in self.pairs:
            if i in fixed:
                numbers[i] += inner[k, moving[j]] if j in moving else v[k].sum() * fixed[j]
            elif j in moving:
                np.multiply(v[k], own[moving[j]], out=product)
                got[moving[i]] += product
        found = [(self.members[i][0], spans[self.members[i][1]][0], x) for i, x in numbers.items()]
        for i, row in moving.items():
            of, p, ordered = self.members[i]
            first, last, once = spans[p]
            if ordered or once:
                found.append((of, part if ordered else at[p], got[row]))
            elif last - first < 4 * self.at_once:
                sums = np.bincount(at[p] - first, weights=got[row])
                found.append((of, slice(first, first + len(sums)), sums))
            else:
                places, inverse = np.unique(at[p], return_inverse=True)
                found.append((of, places, np.bincount(inverse, weights=got[row])))
        return found

    def multiply(self, g: np.ndarray, out: np.ndarray, n: float) -> None:
        """Rows are multiplied by several threads and added by one, in their order, so that the same sums come out each time."""
        chunks = len(self.spans)
        if chunks < 2 * THREADS:
            waves = [map(lambda c: self._products(c, g, n), range(chunks))]
        else:
            waves = (_threads().map(lambda c: self._products(c, g, n), range(low, min(low + 2 * THREADS, chunks))) for low in range(0, chunks, 2 * THREADS))
        for wave in waves:
            for found in wave:
                for of, at, x in found:
                    out[of][at] += x


@cache
def _threads() -> ThreadPoolExecutor:
    return ThreadPoolExecutor(THREADS)


class SigmaIndex:
    """Second moments as coordinates: each distinct aggregate is read once for all index pairs of blocks that it fills."""

    def __init__(self, layout: FeatureLayout) -> None:
        self.layout, mom = layout, layout.moments
        n = self.n = mom.rows
        self.pairs: dict[Monomial, list[tuple[int, int]]] = {}
        for i, a in enumerate(layout.h):
            for j in range(i, len(layout.h)):
                self.pairs.setdefault(a * layout.h[j], []).append((i, j))
        #: Large aggregates stay as they are; the entries of the others are written out as one list.
        self.blocks: list[Block | WideBlock] = []
        listed: list[Block] = []
        together: dict[tuple[str, ...], list[tuple[Monomial, Block]]] = {}
        ordered: dict[tuple, bool] = {}
        left = ALL_DENSE

        def in_order(m: Monomial, a: Monomial, at: np.ndarray) -> bool:
            if (m.cats, a.cats) not in ordered:
                ordered[m.cats, a.cats] = len(at) == layout.size[a] and bool((np.diff(at) == 1).all()) and not at[:1].any()
            return ordered[m.cats, a.cats]

        for m, where in self.pairs.items():
            wide = mom.wide(m.cats)
            if wide is not None and all({layout.h[i], layout.h[j]} == {variable(c, True) for c in m.cats} for i, j in where):
                ((down, across),) = [(variable(wide.down, True), variable(c, True)) for c in m.cats if c != wide.down]
                self.blocks += [WideBlock(wide.counts, layout.block(down), layout.block(across)) for _ in where]
                continue
            value = mom.held(m) if m.cats else np.array([mom.scalar(m)])
            for i, j in where:
                a, b = layout.h[i], layout.h[j]
                r, c = (layout.positions(m.cats, x.cats) if m.cats else np.zeros(1, np.int8) for x in (a, b))
                places = layout.size[a] * layout.size[b]
                dense = LISTED < len(value) <= places <= min(2 * len(value), DENSE, left) and i != j and min(layout.size[a], layout.size[b]) > 1
                left -= places if dense else 0
                block = (DenseBlock if dense else Block)(value, r, c, layout.block(a), layout.block(b), in_order(m, a, r), in_order(m, b, c))
                (self.blocks if len(value) > LISTED else listed).append(block)
                if len(value) > max(LISTED, TOGETHER) and not dense:
                    together.setdefault(m.cats, []).append((m, block))
        grouped = {id(b) for found in together.values() for _, b in found}
        self._parts = [*(b for b in self.blocks if id(b) not in grouped), *map(Together, together.values())]
        size = sum(len(x.values) * (1 if x.diagonal else 2) for x in listed)
        rows, cols, values, low = np.empty(size, np.int32), np.empty(size, np.int32), np.empty(size), 0
        for x in listed:
            for r, into, c, of in x.halves():
                part = slice(low, low := low + len(x.values))
                rows[part], cols[part], values[part] = r, c, x.values
                rows[part] += into.start
                cols[part] += of.start
        values /= n
        order = np.argsort(rows, kind="stable")
        self._rows, self._cols, self._values = rows[order], cols[order], values[order]
        del rows, cols, values, order
        self._starts = np.flatnonzero(np.r_[True, self._rows[1:] != self._rows[:-1]]) if size else np.zeros(0, np.int64)
        self._used = self._rows[self._starts]
        y = variable(mom.query.response, False) if mom.query.response else None
        self.c = np.zeros(layout.width)
        self.s_y = 0.0
        if y is not None:
            for a in layout.h:
                v = mom.column(a * y) / n if a.cats else np.array([mom.scalar(a * y) / n])
                at = layout.positions(a.cats, a.cats) if a.cats else np.zeros(1, np.int64)
                self.c[layout.block(a)][at] = v
            self.s_y = mom.scalar(y * y) / n

    def listing(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All entries, both halves, in order of row: for direct solves and tables."""
        rows, cols, values = [self._rows], [self._cols], [self._values]
        for x in self.blocks:
            for r, into, c, of in x.halves():
                rows.append(r.astype(np.int64) + into.start)
                cols.append(c.astype(np.int64) + of.start)
                values.append(x.values / self.n)
        rows, cols, values = (np.concatenate(x) for x in (rows, cols, values))
        order = np.argsort(rows, kind="stable") if self.blocks else slice(None)
        return rows[order], cols[order], values[order]

    @property
    def all_rows(self) -> np.ndarray:
        return self.listing()[0]

    @property
    def all_cols(self) -> np.ndarray:
        return self.listing()[1]

    @property
    def all_values(self) -> np.ndarray:
        return self.listing()[2]

    @property
    def stored(self) -> int:
        return int((self._rows <= self._cols).sum()) + sum(len(x.values) for x in self.blocks)

    def matvec(self, g: np.ndarray, out: np.ndarray | None = None) -> np.ndarray:
        """out: a vector whose place the result takes."""
        if out is None:
            out = np.zeros(self.layout.width)
        else:
            out.fill(0)
        if len(self._rows):
            out[self._used] = np.add.reduceat(self._values * g[self._cols], self._starts)
        for x in self._parts:
            x.multiply(g, out, self.n)
        return out

    def diagonal(self) -> np.ndarray:
        out = np.zeros(self.layout.width)
        on = self._rows == self._cols
        out[self._rows[on]] = self._values[on]
        for x in self.blocks:
            if x.diagonal:
                out[x.at][x.rows] = x.values / self.n
        return out

    def dense(self) -> np.ndarray:
        out = np.zeros((self.layout.width, self.layout.width))
        rows, cols, values = self.listing()
        out[rows, cols] = values
        return out


def features(layout: FeatureLayout) -> tuple[int, int]:
    """Parameters of continuous and of categorical blocks (the intercept counts as continuous)."""
    cat = sum(layout.size[m] for m in layout.h if m.cats)
    return layout.width - cat, cat


def names(layout: FeatureLayout) -> list[tuple[str, str]]:
    return list(chain.from_iterable([(str(m), "|".join(map(str, k))) for k in layout.keys_of(m)] if m.cats else [(str(m), "")] for m in layout.h))
