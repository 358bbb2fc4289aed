"""Batch gradient descent over moments: Barzilai-Borwein trial steps, backtracking by halving. No data is read here."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

from .layout import CHUNK
from .models import Linear, gradient, objective, valued
from .penalties import Ridge

MAX_HALVINGS = 60
STEP_RANGE = (1e-20, 1e20)
#: Levels of a category up to which its parameters are solved densely, and levels that are eliminated at once.
DENSE_WIDTH = 500


@dataclass
class FitResult:
    theta: np.ndarray
    runs: int
    status: str
    objective: float
    gradient_norm: float
    seconds: float
    trace: list[tuple[int, float, float, float, int]] = field(default_factory=list)


def bb_step(s: np.ndarray, y: np.ndarray, kind: str, previous: float) -> float:
    """Barzilai-Borwein step from the last change of parameters s and of gradients y; the previous one where it has no sense."""
    return _bb_step(float(s @ s), float(s @ y), float(y @ y), kind, previous)


def _bb_step(ss: float, sy: float, yy: float, kind: str, previous: float) -> float:
    top, low = (ss, sy) if kind == "bb1" else (sy, yy)
    step = top / low if low > 0 else np.nan
    return step if np.isfinite(step) and step > 0 else previous


def _changes(theta: np.ndarray, new: np.ndarray, grad: np.ndarray, new_grad: np.ndarray, scale: np.ndarray | None) -> tuple[float, float, float]:
    """The inner products of the changes s of parameters and y of gradients, part by part: neither is held as a whole."""
    ss = sy = yy = 0.0
    for low in range(0, len(theta), CHUNK):
        part = slice(low, low + CHUNK)
        s, y = new[part] - theta[part], new_grad[part] - grad[part]
        if scale is not None:
            s /= scale[part]
            y *= scale[part]
        ss, sy, yy = ss + float(s @ s), sy + float(s @ y), yy + float(y @ y)
    return ss, sy, yy


def _moved(theta: np.ndarray, grad: np.ndarray, x: np.ndarray, hx: np.ndarray, alpha: float, scale: np.ndarray | None) -> tuple[float, float, float]:
    """Go alpha along -x, in place, part by part (the gradient, of a parabola, along -hx; x becomes the gradient times scale).

    Returns what `_changes` does."""
    ss = sy = yy = 0.0
    step = CHUNK // 8  # few enough to stay near the processor
    for low in range(0, len(theta), step):
        part = slice(low, low + step)
        new, new_grad = theta[part] - alpha * x[part], grad[part] - alpha * hx[part]
        s, y = new - theta[part], new_grad - grad[part]
        theta[part], grad[part] = new, new_grad
        if scale is not None:
            s /= scale[part]
            y *= scale[part]
            np.multiply(scale[part], new_grad, out=x[part])
        ss, sy, yy = ss + float(s @ s), sy + float(s @ y), yy + float(y @ y)
    return ss, sy, yy


def first_step(model: Linear, lam: float, rounds: int = 20, scale: np.ndarray | None = None) -> float:
    """Inverse of (largest eigenvalue of Sigma, by power iteration, plus lambda)."""
    n = model.sigma.layout.width
    v, w = np.full(n, 1.0 / np.sqrt(n)), np.empty(n)
    top = 1.0
    for _ in range(rounds):
        if scale is not None:
            v *= scale
        w = model.sigma.matvec(v, w)
        if scale is not None:
            w *= scale
        top = float(np.linalg.norm(w))
        if top == 0:
            return 1.0
        w /= top
        v, w = w, v
    return 1.0 / (top + lam)


def bgd(model: Linear, lam: float = 1e-3, tol: float | None = 1e-9, max_iter: int = 1000, seed: int | None = None, step: str = "bb1", theta0: np.ndarray | None = None, penalty=None, armijo: float = 0.5, precondition: str | None = None, fixed_step: float | None = None) -> FitResult:
    """step: bb1, bb2 or fixed. armijo: the share of step times squared gradient that a step must gain.

    precondition='diag' changes variables by the diagonal of Sigma; the objective stays the same."""
    began = time.time()
    penalty = penalty or Ridge(model.width)
    theta = model.start(seed) if theta0 is None else theta0.astype(float)
    scale = None
    plain = type(model) is Linear
    if precondition == "diag":
        d = model.sigma.diagonal()
        scale = np.ones(model.width)
        n = min(len(d), model.width)
        scale[:n] = 1 / np.sqrt(np.maximum(d[:n], 0) + lam + 1e-12)
        if not plain:  # factors of an attribute level move like its linear parameter
            scale[model.linear :] = 1.0
            scale[model.linear : model.linear + model.factors * model.rank] = np.repeat(scale[1 : model.linear], model.rank)
    j, *held = valued(model, theta, lam, penalty)
    grad = gradient(model, theta, lam, penalty, held.pop())
    d = grad if scale is None else scale * grad
    alpha = fixed_step or (first_step(model, lam, scale=scale) if plain else 1e-2 / max(1.0, float(np.linalg.norm(d))))
    goal = None if tol is None else tol * max(1.0, float(np.linalg.norm(model.sigma.c)))
    trace, status, previous = [], "max_iter", None
    hx = np.empty_like(theta) if plain else None
    for run in range(1, max_iter + 1):
        norm2 = float(d @ d)
        if goal is not None and float(np.linalg.norm(grad)) <= goal:
            status, run = "converged", run - 1
            break
        if step != "fixed" and previous is not None:
            alpha = _bb_step(*previous, step, alpha)
        alpha = float(np.clip(alpha, *STEP_RANGE))
        halvings = 0
        if plain:  # along a line the objective is a parabola: one product serves every halving and the new gradient
            x = d if scale is None else np.multiply(scale, d, out=d)
            hx = model.sigma.matvec(x, hx)
            if isinstance(penalty, Ridge):
                penalty.add(x, lam, hx)
            else:
                hx += lam * penalty.apply(x)
            bend = float(x @ hx)
        else:
            new = np.empty_like(theta)
        while True:
            if plain:
                gain = alpha * norm2 - 0.5 * alpha * alpha * bend
                new_j = j - gain
            else:
                np.multiply(d, -alpha, out=new)
                if scale is not None:
                    new *= scale
                new += theta
                held.clear()
                new_j, *held = valued(model, new, lam, penalty)
                gain = j - new_j
            if step == "fixed" or gain > armijo * alpha * norm2 or not np.isfinite(alpha):
                break
            if halvings >= MAX_HALVINGS or alpha * norm2 < 1e-17 * max(abs(j), 1e-300):
                halvings = MAX_HALVINGS
                break
            alpha /= 2
            halvings += 1
        if halvings >= MAX_HALVINGS:
            status, run = "stalled", run - 1
            break
        j = new_j
        if plain and run % 50:
            previous = _moved(theta, grad, x, hx, alpha, scale)
        else:
            if plain:
                new = np.multiply(x, -alpha, out=hx)
                new += theta
                new_grad = gradient(model, new, lam, penalty)
                hx = theta
            else:
                new_grad = gradient(model, new, lam, penalty, held.pop())
            previous = _changes(theta, new, grad, new_grad, scale)
            theta, grad = new, new_grad
            del new, new_grad
            d = grad if scale is None else np.multiply(scale, grad, out=d)
        trace.append((run, float(j), float(np.linalg.norm(grad)), alpha, halvings))
        if not np.isfinite(j):
            status = "diverged"
            break
    return FitResult(theta, run, status, objective(model, theta, lam, penalty), float(np.linalg.norm(gradient(model, theta, lam, penalty))), time.time() - began, trace)


def solve_exact(model: Linear, lam: float, penalty=None) -> np.ndarray:
    """The stationary point of a model linear in its parameters, by a direct solve: the oracle of tests.

    Under a ridge, levels of the widest category are eliminated first if their block is diagonal, as it is in degree one; the
    dense system is then as wide as all other parameters."""
    if penalty is None or isinstance(penalty, Ridge):
        weights = (penalty or Ridge(model.width)).weights
        widest = max((m for m in model.h if m.cats), key=lambda m: model.layout.size[m], default=None)
        if widest is not None and model.layout.size[widest] > DENSE_WIDTH:
            found = _eliminated(model, lam * weights, model.layout.block(widest))
            if found is not None:
                return found
        sigma = model.sigma.dense()
        return np.linalg.solve(sigma + lam * np.diag(weights), model.sigma.c)
    sigma = model.sigma.dense()
    p = np.column_stack([penalty.apply(e) for e in np.eye(model.width)])
    return np.linalg.solve(sigma + lam * p, model.sigma.c)


def _eliminated(model: Linear, ridge: np.ndarray, block: slice) -> np.ndarray | None:
    """The ridge solution by the Schur complement of a diagonal block; None if the block is not diagonal.

    Entries of the block beside the other parameters stay sparse: they are multiplied level by level."""
    s, n = model.sigma, model.width
    inside = np.zeros(n, bool)
    inside[block] = True
    r, c, v = s.listing()
    if (inside[r] & inside[c] & (r != c)).any():
        return None
    rest = np.flatnonzero(~inside)
    at = np.cumsum(~inside) - 1
    pivot = 1.0 / (s.diagonal()[block] + ridge[block])
    outer = ~inside[r] & ~inside[c]
    small = np.zeros((len(rest), len(rest)))
    small[at[r[outer]], at[c[outer]]] = v[outer]
    small += np.diag(ridge[rest])
    cross = inside[r] & ~inside[c]
    level, column, value = r[cross] - block.start, at[c[cross]], v[cross]
    order = np.argsort(level, kind="stable")
    level, column, value = level[order], column[order], value[order]
    right, own = s.c[rest].copy(), s.c[block]
    for low in range(0, len(pivot), DENSE_WIDTH):
        high = min(low + DENSE_WIDTH, len(pivot))
        a, b = np.searchsorted(level, (low, high))
        part = np.zeros((high - low, len(rest)))
        part[level[a:b] - low, column[a:b]] = value[a:b]
        scaled = part * pivot[low:high, None]
        small -= part.T @ scaled
        right -= scaled.T @ own[low:high]
    theta = np.empty(n)
    theta[rest] = np.linalg.solve(small, right)
    theta[block] = pivot * (own - np.bincount(level, weights=value * theta[rest][column], minlength=len(pivot)))
    return theta
