"""Feature queries: a natural join of relations by variable name, with features and a response."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .monomials import Monomial, aggregate_monomials, feature_monomials

NULL_LEVEL = "∅"


@dataclass
class FeatureQuery:
    """relations: DataFrames whose columns carry variable names; equal names join.

    where: a condition for a relation, pushed to its scan. null_policy: 'error' leaves nulls to fail in sums of the solver,
    'drop_row' drops rows with a null in a used column, 'own_level' gives null categories a level of their own.
    scale: in exact mode, factors that make a continuous column whole; sums are then decimals without rounding error."""

    relations: dict[str, DataFrame]
    continuous: tuple[str, ...] = ()
    categorical: tuple[str, ...] = ()
    response: str | None = None
    where: dict[str, Column | str] = field(default_factory=dict)
    set_semantics: bool = False
    null_policy: str = "error"
    scale: dict[str, int] | None = None
    extra: tuple[str, ...] = ()

    def __post_init__(self) -> None:
        owned = {c for r in self.relations.values() for c in r.columns}
        if missing := {*self.continuous, *self.categorical, *self.extra, *([self.response] if self.response else [])} - owned:
            raise ValueError(f"no relation has {sorted(missing)}")
        if both := set(self.continuous) & set(self.categorical):
            raise ValueError(f"continuous and categorical at once: {sorted(both)}")

    @property
    def features(self) -> tuple[str, ...]:
        return (*self.continuous, *self.categorical)

    def joins(self) -> set[str]:
        seen: dict[str, int] = {}
        for r in self.relations.values():
            for c in r.columns:
                seen[c] = seen.get(c, 0) + 1
        return {c for c, n in seen.items() if n > 1}

    def variables(self) -> list[str]:
        used = {*self.features, *self.extra, *self.joins(), *([self.response] if self.response else [])}
        return [c for c in dict.fromkeys(c for r in self.relations.values() for c in r.columns) if c in used]

    def attributes(self, relation: str) -> list[str]:
        used = set(self.variables())
        return [c for c in self.relations[relation].columns if c in used]

    def numeric(self, name: str) -> bool:
        return name in self.continuous or name == self.response

    def bound(self, relation: str) -> DataFrame:
        """The relation's rows as the plans read them: pruned to used columns, filtered, typed."""
        df = self.relations[relation]
        if relation in self.where:
            df = df.where(self.where[relation])
        cols = self.attributes(relation)
        df = df.select(*cols)
        if self.null_policy == "drop_row":
            df = df.dropna(subset=cols)
        typed = []
        for c in cols:
            if self.numeric(c) and self.scale is not None:
                typed.append(F.round(F.col(c) * F.lit(self.scale.get(c, 1))).cast("decimal(38,0)").alias(c))
            elif self.numeric(c):
                typed.append(F.col(c).cast("double").alias(c))
            elif c in self.categorical and self.null_policy == "own_level":
                typed.append(F.coalesce(F.col(c).cast("string"), F.lit(NULL_LEVEL)).alias(c))
            else:
                typed.append(F.col(c))
        df = df.select(*typed)
        return df.distinct() if self.set_semantics else df

    def listing(self) -> DataFrame:
        """The natural join itself; only baselines and measures evaluate it."""
        todo = list(self.relations)
        out = self.bound(todo.pop(0))
        while todo:
            nxt = next((r for r in todo if set(self.attributes(r)) & set(out.columns)), todo[0])
            todo.remove(nxt)
            right = self.bound(nxt)
            on = [c for c in right.columns if c in out.columns]
            out = out.join(right, on) if on else out.crossJoin(right)
        return out

    def feature_map(self, degree: int = 1, squares: bool = True) -> list[Monomial]:
        return feature_monomials(self.continuous, self.categorical, degree, squares)

    def aggregates(self, degree: int = 1, squares: bool = True) -> list[Monomial]:
        return aggregate_monomials(self.feature_map(degree, squares), self.response)
