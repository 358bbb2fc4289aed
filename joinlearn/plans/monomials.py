"""Monomials over features: exponents of continuous variables and a set of categorical ones.

A categorical variable stands for its indicator block, whose powers are itself, so its exponent never exceeds one."""

from __future__ import annotations

from collections.abc import Iterable
from itertools import combinations_with_replacement
from typing import NamedTuple


class Monomial(NamedTuple):
    cont: tuple[tuple[str, int], ...] = ()
    cats: tuple[str, ...] = ()

    def __mul__(self, other: Monomial) -> Monomial:  # type: ignore[override]
        powers = dict(self.cont)
        for v, e in other.cont:
            powers[v] = powers.get(v, 0) + e
        return Monomial(tuple(sorted(powers.items())), tuple(sorted({*self.cats, *other.cats})))

    def on(self, variables: Iterable[str]) -> Monomial:
        """The part over the given variables."""
        keep = set(variables)
        return Monomial(tuple(x for x in self.cont if x[0] in keep), tuple(c for c in self.cats if c in keep))

    @property
    def degree(self) -> int:
        return sum(e for _, e in self.cont) + len(self.cats)

    def __str__(self) -> str:
        return "*".join([*(v if e == 1 else f"{v}^{e}" for v, e in self.cont), *(f"[{c}]" for c in self.cats)]) or "1"


ONE = Monomial()


def variable(name: str, categorical: bool) -> Monomial:
    return Monomial((), (name,)) if categorical else Monomial(((name, 1),), ())


def feature_monomials(continuous: Iterable[str], categorical: Iterable[str], degree: int = 1, squares: bool = True) -> list[Monomial]:
    """The feature map: all products of at most `degree` features, in order of degree.

    A categorical variable is never multiplied with itself; without `squares` neither is a continuous one."""
    cats = set(categorical)
    names = [*continuous, *categorical]
    found = [ONE]
    for d in range(1, degree + 1):
        for pick in combinations_with_replacement(names, d):
            twice = {v for v in pick if pick.count(v) > 1}
            if twice & cats or (twice and not squares):
                continue
            m = ONE
            for v in pick:
                m = m * variable(v, v in cats)
            found.append(m)
    return found


def aggregate_monomials(h: list[Monomial], response: str | None = None) -> list[Monomial]:
    """Distinct products of pairs of h, of h with the response, and the squared response; the count comes first."""
    found = dict.fromkeys([ONE])
    for i, a in enumerate(h):
        for b in h[i:]:
            found[a * b] = None
    if response:
        y = variable(response, False)
        for a in h:
            found[a * y] = None
        found[y * y] = None
    return list(found)


def by_keys(monomials: Iterable[Monomial]) -> dict[tuple[str, ...], list[Monomial]]:
    """Monomials by their categorical part, smaller parts first."""
    out: dict[tuple[str, ...], list[Monomial]] = {}
    for m in monomials:
        out.setdefault(m.cats, []).append(m)
    return dict(sorted(out.items(), key=lambda x: (len(x[0]), x[0])))
