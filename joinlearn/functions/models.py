"""Models over moments: each maps parameters theta to coefficients g of the feature map, with the matching Jacobian."""

from __future__ import annotations

import numpy as np

from ..plans.monomials import ONE, Monomial, variable
from ..plans.query import FeatureQuery
from .layout import CHUNK, FeatureLayout, SigmaIndex
from .penalties import Ridge


class Linear:
    """Ridge regression on h; with degree 2 or more, polynomial regression. One parameter for each coordinate of h."""

    degree, squares = 1, True

    def __init__(self, query: FeatureQuery, degree: int = 1) -> None:
        self.query, self.degree = query, degree
        self.h = query.feature_map(degree)

    def attach(self, sigma: SigmaIndex) -> Linear:
        self.sigma, self.layout = sigma, sigma.layout
        self.width = sigma.layout.width
        return self

    def start(self, seed: int | None = None, scale: float = 0.01) -> np.ndarray:
        return np.zeros(self.width) if seed is None else np.random.default_rng(seed).normal(0, scale, self.width)

    def g(self, theta: np.ndarray) -> np.ndarray:
        return theta

    def pull(self, theta: np.ndarray, v: np.ndarray) -> np.ndarray:
        """The Jacobian of g, transposed, times v."""
        return v


class FactorizationMachine(Linear):
    """Degree two; the coefficient of a product of two different attributes is the inner product of their rank-r factors.

    theta = intercept and linear parameters, then factors, attribute level by attribute level."""

    def __init__(self, query: FeatureQuery, rank: int = 8) -> None:
        self.query, self.rank, self.degree = query, rank, 2
        self.h = query.feature_map(2, squares=False)

    def attach(self, sigma: SigmaIndex) -> FactorizationMachine:
        self.sigma, self.layout = sigma, sigma.layout
        lay = sigma.layout
        singles = [m for m in self.h if m.degree == 1]
        self.linear = 1 + sum(lay.size[m] for m in singles)
        if [*self.h[: len(singles) + 1]] != [ONE, *singles]:
            raise ValueError("linear blocks must come first")
        self.factors = self.linear - 1
        self.width = self.linear + self.factors * self.rank
        #: Each product's block of h and, for both its attributes, their factors and each entry's place among them (None: one
        #: after the other, or the only one).
        self.products: list[tuple[slice, list[tuple[slice, np.ndarray | None]]]] = []
        for m in self.h:
            if m.degree != 2:
                continue
            names = [*(v for v, _ in m.cont), *m.cats]
            sides: list[tuple[slice, np.ndarray | None]] = []
            for s in (variable(n, n in m.cats) for n in names):
                order = None
                if s.cats and s.cats != m.cats:
                    at = lay.positions(m.cats, s.cats)
                    order = np.empty(lay.size[m], at.dtype)
                    order[lay.positions(m.cats, m.cats)] = at
                sides.append((slice(lay.offset[s] - 1, lay.offset[s] - 1 + lay.size[s]), order))
            self.products.append((lay.block(m), sides))
        return self

    @staticmethod
    def _part(v: np.ndarray, side: tuple[slice, np.ndarray | None], low: int, high: int) -> np.ndarray:
        """Factors of one side of entries low to high of a product."""
        own, order = v[side[0]], side[1]
        if order is not None:
            return own.take(order[low:high], axis=0)
        return np.broadcast_to(own, (high - low, own.shape[1])) if len(own) == 1 else own[low:high]

    @staticmethod
    def _add(d: np.ndarray, side: tuple[slice, np.ndarray | None], low: int, high: int, e: np.ndarray, other: np.ndarray) -> None:
        """Add to one side's factors what entries low to high, weighted with e, have as the other side's."""
        own, order = d[side[0]], side[1]
        if order is not None:
            at = order[low:high]
            first = at.min()
            at = (at - first).astype(np.intp)
            near = own[first : first + int(at.max()) + 1]
            for r in range(d.shape[1]):
                near[:, r] += np.bincount(at, weights=e * other[:, r])
        elif len(own) == 1:
            own[0] += e @ other
        else:
            own[low:high] += e[:, None] * other

    def start(self, seed: int | None = 0, scale: float = 0.1) -> np.ndarray:
        theta = np.zeros(self.width)
        theta[self.linear :] = np.random.default_rng(seed).normal(0, scale, self.factors * self.rank)
        return theta

    def split(self, theta: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return theta[: self.linear], theta[self.linear : self.linear + self.factors * self.rank].reshape(self.factors, self.rank)

    def g(self, theta: np.ndarray) -> np.ndarray:
        w, v = self.split(theta)
        out = np.zeros(self.layout.width)
        out[: self.linear] = w
        for block, (a, b) in self.products:
            into = out[block]
            for low in range(0, len(into), CHUNK):
                high = min(low + CHUNK, len(into))
                into[low:high] = np.einsum("ij,ij->i", self._part(v, a, low, high), self._part(v, b, low, high))
        return out

    def pull(self, theta: np.ndarray, x: np.ndarray) -> np.ndarray:
        w, v = self.split(theta)
        out = np.zeros_like(theta)
        out[: self.linear] = x[: self.linear]
        d = out[self.linear : self.linear + v.size].reshape(v.shape)
        for block, (a, b) in self.products:
            mine = x[block]
            for low in range(0, len(mine), CHUNK):
                high = min(low + CHUNK, len(mine))
                self._add(d, a, low, high, mine[low:high], self._part(v, b, low, high))
                self._add(d, b, low, high, mine[low:high], self._part(v, a, low, high))
        return out


def loss(model: Linear, theta: np.ndarray) -> tuple[float, np.ndarray]:
    """Mean squared error, and Sigma times the coefficients, from which `gradient` goes on."""
    g, s = model.g(theta), model.sigma
    product = s.matvec(g)
    return float(g @ product - 2 * (g @ s.c) + s.s_y), product


def valued(model: Linear, theta: np.ndarray, lam: float, penalty) -> tuple[float, np.ndarray]:
    """The objective, and what `loss` gives beside its value."""
    error, product = loss(model, theta)
    return 0.5 * error + 0.5 * lam * penalty.value(theta), product


def objective(model: Linear, theta: np.ndarray, lam: float, penalty) -> float:
    return valued(model, theta, lam, penalty)[0]


def gradient(model: Linear, theta: np.ndarray, lam: float, penalty, product: np.ndarray | None = None) -> np.ndarray:
    """product: what `loss` gave at theta; its place is used, and is free before the penalty if the caller holds no name of it."""
    if product is None:
        product = model.sigma.matvec(model.g(theta))
    product -= model.sigma.c
    out = model.pull(theta, product)
    del product
    if isinstance(penalty, Ridge):
        penalty.add(theta, lam, out)
        return out
    shrink = penalty.apply(theta)
    shrink *= lam
    out += shrink
    return out


def rmse(model: Linear, theta: np.ndarray) -> float:
    """Root mean squared error over the join, from moments alone."""
    return float(np.sqrt(max(0.0, loss(model, theta)[0])))


def coefficients(model: Linear, theta: np.ndarray) -> dict[Monomial, dict[tuple, float] | float]:
    g, lay = model.g(theta), model.layout
    return {m: dict(zip(lay.keys_of(m), g[lay.block(m)].tolist(), strict=True)) if m.cats else float(g[lay.offset[m]]) for m in model.h}


def layout_and_sigma(moments, h: list[Monomial]) -> SigmaIndex:
    return SigmaIndex(FeatureLayout(moments, h))
