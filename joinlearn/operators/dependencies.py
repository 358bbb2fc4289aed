"""Functional dependencies: checks, maps, reduced queries, reparameterised penalties and recovery of the parameters."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import layout
from ..functions.layout import FeatureLayout
from ..functions.models import FactorizationMachine, Linear
from ..functions.penalties import DenseD, Merged, Woodbury
from ..plans.monomials import Monomial, variable
from ..plans.query import FeatureQuery
from . import dealt
from .moments import packed_parts


@dataclass(frozen=True)
class Dependency:
    determinant: str
    determined: tuple[str, ...]


def violations(df: DataFrame, determinant: str, determined: str) -> DataFrame:
    """Determinant values with more than one determined value; a null counts as a value."""
    seen = F.count_distinct(determined) + F.max(F.when(F.col(determined).isNull(), 1).otherwise(0))
    return df.groupBy(determinant).agg(seen.alias("n_values")).where("n_values > 1")


def holds(df: DataFrame, determinant: str, determined: str) -> bool:
    return violations(df, determinant, determined).isEmpty()


def closure(dependencies: list[Dependency]) -> list[Dependency]:
    """Chains resolved: a determinant takes over all that its determined attributes determine; those fall away as determinants."""
    direct: dict[str, set[str]] = {}
    for d in dependencies:
        direct.setdefault(d.determinant, set()).update(d.determined)

    def reach(v: str, seen: frozenset) -> set[str]:
        out: set[str] = set()
        for a in direct.get(v, ()):
            if a not in seen:
                out |= {a} | reach(a, seen | {a})
        return out - {v}

    full = {v: reach(v, frozenset({v})) for v in direct}
    inner = {a for v, attrs in full.items() for a in attrs if a in full and v not in full[a]}
    return [Dependency(v, tuple(sorted(a))) for v, a in sorted(full.items()) if v not in inner]


def reduce_query(query: FeatureQuery, dependencies: list[Dependency]) -> FeatureQuery:
    """The query without the determined categorical features; their determinants must be features."""
    gone = {a for d in dependencies if d.determinant in query.categorical for a in d.determined}
    return replace(query, categorical=tuple(c for c in query.categorical if c not in gone))


def dependency_map(query: FeatureQuery, determinant: str, determined: str) -> DataFrame:
    """(determined, members): determinant values that occur in the join, for each determined value.

    Dangling rows are kept out by semi-joins with the relations that share the determinant."""
    owner = next(r for r in query.relations if {determinant, determined} <= set(query.relations[r].columns))
    rows = query.relations[owner].where(query.where[owner]) if owner in query.where else query.relations[owner]
    rows = rows.select(determinant, determined).distinct()
    for r, df in query.relations.items():
        if r != owner and determinant in df.columns:
            rows = rows.join(query.bound(r).select(determinant), determinant, "left_semi")
    return rows.groupBy(determined).agg(F.sort_array(F.collect_list(determinant)).alias("members"))


def groupings(query: FeatureQuery, dependency: Dependency, layout: FeatureLayout) -> dict[str, np.ndarray]:
    """For each determined attribute, the group number of every determinant level in the layout's order."""
    levels = pd.Index(layout.levels[dependency.determinant])
    owner_of = {a: next(r for r in query.relations if {dependency.determinant, a} <= set(query.relations[r].columns)) for a in dependency.determined if any({dependency.determinant, a} <= set(df.columns) for df in query.relations.values())}
    out: dict[str, np.ndarray] = {}
    value_of: dict[str, pd.Categorical] = {}
    for a in sorted(dependency.determined, key=lambda a: a not in owner_of):
        if a in owner_of:
            mine = _values(query.relations[owner_of[a]], dependency.determinant, a, levels)
        else:  # reached through other attributes of the closure
            steps = next((b for b in dependency.determined if b in out and any({b, a} <= set(df.columns) for df in query.relations.values())), None)
            if steps is None:
                raise ValueError(f"no relation holds {a} beside {dependency.determinant} or what it determines")
            link = {r[0]: r[1] for df in query.relations.values() if {steps, a} <= set(df.columns) for r in df.select(steps, a).distinct().collect()}
            known = value_of[steps]
            kind = pd.Index(dict.fromkeys(link.values()), dtype=object)
            through = kind.get_indexer([link[v] for v in known.categories] + [link.get(None)])
            mine = pd.Categorical.from_codes(through[known.codes], kind)
        value_of[a] = mine
        codes = mine.codes.astype(np.int64)
        _, first, number = np.unique(codes, return_index=True, return_inverse=True)
        rank = np.empty(len(first), np.int64)
        rank[np.argsort(first)] = np.arange(len(first))  # numbered as they come
        out[a] = rank[number].astype(np.min_scalar_type(len(first)))
    del levels, value_of
    dealt.trimmed(next(iter(query.relations.values())).sparkSession)  # before a descent: it needs the room, and no jobs
    return out


def _values(rows: DataFrame, determinant: str, determined: str, levels: pd.Index) -> pd.Categorical:
    """The determined value of each level, from packed columns: nothing is a Python object by row."""
    kinds: dict = {}
    code = np.full(len(levels), -2, np.int32)
    for part in packed_parts(rows.select(determinant, determined).distinct()):
        d = part[determined].combine_chunks().dictionary_encode()
        mapped = np.array([-1 if v is None else kinds.setdefault(v, len(kinds)) for v in d.dictionary.to_pylist()] + [-1], np.int32)
        at = levels.get_indexer(part[determinant].to_pandas())
        found = mapped[d.indices.fill_null(-1).to_numpy()]
        code[at[at >= 0]] = found[at >= 0]
    if (code == -2).any():
        raise KeyError(f"{determined} of {determinant} {levels[code == -2][0]!r}")
    return pd.Categorical.from_codes(code, pd.Index(list(kinds), dtype=object))


def _joined(groups: list[np.ndarray]) -> np.ndarray:
    code = np.zeros(len(groups[0]), np.int64)
    for g in groups:
        code = code * (int(g.max(initial=0)) + 1) + g
    return np.unique(code, return_inverse=True)[1]


def merged_penalty(model: Linear, dependency: Dependency, groups: dict[str, np.ndarray], intercept: bool = True) -> Merged:
    """The penalty of LR or degree-2 PR after one dependency.

    D counts, for two determinant levels, the products of attributes on which they agree: in the block of the determinant
    alone those are N single attributes and, for degree two, N(N-1)/2 products within the group; in the block of its
    products with an outside feature, N attributes, among the levels that occur with that feature's value."""
    lay, det = model.layout, dependency.determinant
    own = variable(det, True)
    gs = list(groups.values())
    parts = []
    for m in model.h:
        if det not in m.cats:
            continue
        rest = tuple(c for c in m.cats if c != det)
        places = np.arange(lay.size[m]) + lay.offset[m]
        if not rest:
            if m.cont or model.degree == 1:
                parts.append((places, Woodbury(gs)))
            else:
                pairs = [_joined([gs[a], gs[b]]) for a in range(len(gs)) for b in range(a + 1, len(gs))]
                parts.append((places, Woodbury([*gs, *pairs], 1.0 + len(gs))))
            continue
        at = lay.positions(m.cats, m.cats)
        level, other = np.empty(len(at), np.int64), np.empty(len(at), np.int64)
        level[at] = lay.positions(m.cats, own.cats)
        other[at] = lay.positions(m.cats, rest)
        # all contexts at once: groups of different contexts are different groups
        parts.append((places, _ByContext(level, other, gs)))
    return Merged(model.width, parts, intercept)


def merged_penalty_of_all(model: Linear, dependencies: list[tuple[Dependency, dict[str, np.ndarray]]], intercept: bool = True) -> Merged:
    """The penalty after several dependencies with different determinants. Each rules its own blocks; in the product block of
    two determinants u and v, D is the element-wise product of the two agreement counts over the pairs that occur."""
    parts: list[tuple[np.ndarray, object]] = []
    dets = {d.determinant: g for d, g in dependencies}
    crossed = [m for m in model.h if sum(c in dets for c in m.cats) == 2]
    taken = {i for m in crossed for i in range(model.layout.offset[m], model.layout.offset[m] + model.layout.size[m])}
    for d, groups in dependencies:
        parts += [(p, s) for p, s in merged_penalty(model, d, groups, intercept).parts if not len(p) or int(p[0]) not in taken]
    lay = model.layout
    for m in crossed:
        at = lay.positions(m.cats, m.cats)
        agree = np.ones((lay.size[m], lay.size[m]))
        for c in m.cats:
            level = np.empty(len(at), np.int64)
            level[at] = lay.positions(m.cats, (c,))
            same = (level[:, None] == level[None, :]).astype(float)
            for g in dets[c].values():
                same += g[level][:, None] == g[level][None, :]
            agree *= same
        solver = DenseD([np.arange(lay.size[m])], 0.0)
        solver.d = agree
        parts.append((np.arange(lay.size[m]) + lay.offset[m], solver))
    return Merged(model.width, parts, intercept)


class _ByContext:
    """Woodbury systems of the contexts of one product block, each over the determinant levels that occur in it."""

    def __init__(self, level: np.ndarray, context: np.ndarray, groups: list[np.ndarray]) -> None:
        self.members = [np.flatnonzero(context == c) for c in np.unique(context)]
        self.solvers = [Woodbury([g[level[m]] for g in groups]) for m in self.members]

    def solve(self, gamma: np.ndarray) -> np.ndarray:
        out = np.empty_like(gamma)
        for m, s in zip(self.members, self.solvers, strict=True):
            out[m] = s.solve(gamma[m])
        return out


def recover(model: Linear, theta: np.ndarray, dependency: Dependency, groups: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
    """Parameters of the determinant and of each determined attribute (by group number) from a merged linear fit."""
    block = model.layout.block(variable(dependency.determinant, True))
    own = Woodbury(list(groups.values())).solve(theta[block])
    return {dependency.determinant: own} | {a: np.bincount(g, weights=own) for a, g in groups.items()}


def _norms(x: np.ndarray) -> np.ndarray:
    """Squared norm of each row."""
    return np.einsum("ij,ij->i", x, x)


class DependentFM(FactorizationMachine):
    """Factorization machine over the reduced features; the dropped attributes' factors stay as parameters of the penalty.

    theta = [intercept and linear, factors, then rank factors of every group of each determined attribute]."""

    def __init__(self, query: FeatureQuery, dependency: Dependency, rank: int = 8) -> None:
        super().__init__(query, rank)
        self.dependency = dependency

    def with_groups(self, groups: dict[str, np.ndarray]) -> DependentFM:
        self.groups = list(groups.values())
        self.sizes = [int(g.max()) + 1 for g in self.groups]
        self.base = self.width
        self.width += sum(self.sizes) * self.rank
        self.places = self.layout.block(variable(self.dependency.determinant, True))
        self.d = Woodbury(self.groups)
        return self

    def start(self, seed: int | None = 0, scale: float = 0.1) -> np.ndarray:
        theta = np.random.default_rng(seed).normal(0, scale, self.width)
        theta[: self.linear] = 0.0
        return theta

    def parts(self, theta: np.ndarray, low: int = 0, high: int | None = None) -> tuple[np.ndarray, np.ndarray, list[np.ndarray], np.ndarray, list[np.ndarray]]:
        """Of the determinant's levels low to high: merged linear part, merged factors, group factors (of all groups), own
        factors, group factors by level."""
        w, v = self.split(theta)
        high = self.places.stop - self.places.start if high is None else high
        merged, factors = v[self.places.start - 1 : self.places.stop - 1][low:high], self.group_factors(theta)
        spread = [f.take(g[low:high], axis=0) for f, g in zip(factors, self.groups, strict=True)]
        return w[self.places][low:high], merged, factors, merged - sum(spread), spread

    def group_factors(self, theta: np.ndarray) -> list[np.ndarray]:
        ends = self.base + np.cumsum([0, *self.sizes]) * self.rank
        return [theta[a:b].reshape(-1, self.rank) for a, b in zip(ends[:-1], ends[1:], strict=True)]

    def _chunks(self) -> Iterator[tuple[int, int]]:
        n = self.places.stop - self.places.start
        step = max(1, layout.CHUNK // self.rank)
        return ((low, min(low + step, n)) for low in range(0, n, step))

    def _left(self, theta: np.ndarray) -> tuple[np.ndarray, float]:
        """By level the linear part without the inner products of its factors, and the own factors' squared norm."""
        left, norm = np.empty(self.places.stop - self.places.start), 0.0
        for low, high in self._chunks():
            gamma, merged, _, own, spread = self.parts(theta, low, high)
            norms = _norms(own)
            left[low:high] = gamma - 0.5 * (_norms(merged) - norms - sum(_norms(s) for s in spread))
            norm += float(norms.sum())
        return left, norm

    def value(self, theta: np.ndarray) -> float:
        left, norm = self._left(theta)
        w, v = self.split(theta)
        a, b = self.places.start, self.places.stop
        rest = sum(float(x @ x) for x in (w[:a], w[b:], v[: a - 1].ravel(), v[b - 1 :].ravel()))
        return rest + float(left @ self.d.solve(left)) + norm + sum(float((f**2).sum()) for f in self.group_factors(theta))

    def apply(self, theta: np.ndarray) -> np.ndarray:
        """Half the gradient of value(). Levels are taken in parts: no more than that is held beside the result."""
        q = self.d.solve(self._left(theta)[0])
        out = theta.copy()
        out[self.places] = q
        v = self.split(out)[1][self.places.start - 1 : self.places.stop - 1]
        pushed = self.group_factors(out)
        for low, high in self._chunks():
            _, merged, _, own, spread = self.parts(theta, low, high)
            by = q[low:high, None]
            v[low:high] = own - by * (merged - own)
            for f, s, g in zip(pushed, spread, self.groups, strict=True):
                push = -own - by * (own - s)
                for r in range(self.rank):
                    f[:, r] += np.bincount(g[low:high], weights=push[:, r], minlength=len(f))
        return out


def penalty_table(gamma: DataFrame, members: DataFrame) -> DataFrame:
    """Group sums as a query, for gamma beyond the driver: (determined, n, total, share) from gamma(level, value) and
    members(level, determined). D^-1 gamma of a level is its value minus its group's share."""
    sums = gamma.join(members, "level").groupBy("determined").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("total"))
    return sums.withColumn("share", F.col("total") / (1 + F.col("n")))


def outside(m: Monomial, dependency: Dependency) -> Monomial:
    return Monomial(m.cont, tuple(c for c in m.cats if c != dependency.determinant and c not in dependency.determined))
