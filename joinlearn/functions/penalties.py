"""Squared-norm penalties, plain and after functional dependencies merged parameters.

With merged gamma = theta_det + sum_k R_k^T theta_k the least squared norm of all thetas is gamma^T D^-1 gamma, where
D = a*I + sum of R^T R over the groupings (R has a row for each group). Four ways to apply D^-1 must agree."""

from __future__ import annotations

import numpy as np

#: Parameters that are penalised at once.
PART = 1 << 13


class Ridge:
    """The squared norm of all parameters; the intercept can be left out."""

    def __init__(self, width: int, intercept: bool = True) -> None:
        self.weights = np.broadcast_to(1.0, (width,))  # one number until some of them differ
        if not intercept:
            self.weights = self.weights.copy()
            self.weights[0] = 0.0

    def value(self, theta: np.ndarray) -> float:
        return float(theta @ (self.weights * theta))

    def apply(self, theta: np.ndarray) -> np.ndarray:
        return self.weights * theta

    def add(self, theta: np.ndarray, lam: float, out: np.ndarray) -> None:
        """Add lam times what `apply` gives."""
        for low in range(0, len(theta), PART):
            part = slice(low, low + PART)
            out[part] += lam * (self.weights[part] * theta[part])


class DenseD:
    """D built by counting, pair by pair, on how many groupings two levels agree; solved as a dense matrix."""

    def __init__(self, groups: list[np.ndarray], identity: float = 1.0) -> None:
        self.groups = groups
        self.d = identity * np.eye(len(groups[0]))
        for g in groups:
            self.d += g[:, None] == g[None, :]

    def solve(self, gamma: np.ndarray) -> np.ndarray:
        return np.linalg.solve(self.d, gamma)


class BlockCholesky:
    """One grouping: D falls into a block for each group, factorised once."""

    def __init__(self, groups: list[np.ndarray], identity: float = 1.0) -> None:
        if len(groups) != 1:
            raise ValueError("blocks exist for a single grouping only")
        self.members = [np.flatnonzero(groups[0] == k) for k in np.unique(groups[0])]
        self.factors = [np.linalg.cholesky(identity * np.eye(len(m)) + 1.0) for m in self.members]

    def solve(self, gamma: np.ndarray) -> np.ndarray:
        out = np.empty_like(gamma)
        for m, f in zip(self.members, self.factors, strict=True):
            out[m] = np.linalg.solve(f.T, np.linalg.solve(f, gamma[m]))
        return out


class ClosedForm:
    """One grouping: D^-1 gamma = (gamma - group sum / (a + group size)) / a."""

    def __init__(self, groups: list[np.ndarray], identity: float = 1.0) -> None:
        if len(groups) != 1:
            raise ValueError("the closed form exists for a single grouping only")
        self.a = identity
        _, self.at = np.unique(groups[0], return_inverse=True)
        self.n = np.bincount(self.at)

    def solve(self, gamma: np.ndarray) -> np.ndarray:
        return (gamma - (np.bincount(self.at, weights=gamma) / (self.a + self.n))[self.at]) / self.a


class Woodbury:
    """Any number of groupings: a system as large as all groups together, factorised once."""

    def __init__(self, groups: list[np.ndarray], identity: float = 1.0) -> None:
        self.a = identity
        self.at, first = [], 0
        for g in groups:
            _, inverse = np.unique(g, return_inverse=True)
            self.at.append((inverse + first).astype(np.min_scalar_type(first + len(g))))
            first += int(inverse.max()) + 1 if len(inverse) else 0
        self.k = first
        small = identity * np.eye(first)
        for x in self.at:
            for y in self.at:
                np.add.at(small, (x, y), 1.0)
        self.inverse = np.linalg.inv(small) if first else small

    def solve(self, gamma: np.ndarray) -> np.ndarray:
        if not self.k:
            return gamma / self.a
        r = sum(np.bincount(x, weights=gamma, minlength=self.k) for x in self.at)
        z = self.inverse @ r
        return (gamma - sum(z[x] for x in self.at)) / self.a

    def solve_many(self, gamma: np.ndarray) -> np.ndarray:
        return np.column_stack([self.solve(gamma[:, i]) for i in range(gamma.shape[1])])


class Merged:
    """A ridge whose blocks `parts` (places, solver) carry merged parameters."""

    def __init__(self, width: int, parts: list[tuple[np.ndarray, object]], intercept: bool = True) -> None:
        self.plain = Ridge(width, intercept)
        self.parts = parts
        self.plain.weights = self.plain.weights.copy()
        for places, _ in parts:
            self.plain.weights[places] = 0.0

    def apply(self, theta: np.ndarray) -> np.ndarray:
        out = self.plain.apply(theta)
        for places, solver in self.parts:
            out[places] = solver.solve(theta[places])
        return out

    def value(self, theta: np.ndarray) -> float:
        return float(theta @ self.apply(theta))
