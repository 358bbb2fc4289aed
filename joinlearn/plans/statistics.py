"""Sizes that plans are chosen by: rows and distinct values of each relation, and what joins and groupings make of them.

They decide how a plan is laid out and never what it returns."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, field
from math import prod

from pyspark.sql import functions as F

from .query import FeatureQuery

#: Measured relations by application and by the plan that reads them: a relation is measured once a session.
_KNOWN: dict[tuple, tuple[float, dict[str, float], int]] = {}


@dataclass
class Size:
    """Estimated rows of a frame and distinct values of its variables."""

    rows: float
    distinct: dict[str, float]

    def joined(self, other: Size) -> Size:
        shared = self.distinct.keys() & other.distinct.keys()
        rows = self.rows * other.rows / prod(max(1.0, self.distinct[v], other.distinct[v]) for v in shared)
        both = {v: min(d.get(v, float("inf")) for d in (self.distinct, other.distinct)) for v in {**self.distinct, **other.distinct}}
        return Size(rows, {v: min(n, max(rows, 1.0)) for v, n in both.items()})


@dataclass
class Statistics:
    """rows: by relation. distinct: by relation, then variable (join variables and categories only). splits: by columns, the
    input partitions that hold rows."""

    rows: dict[str, float] = field(default_factory=dict)
    distinct: dict[str, dict[str, float]] = field(default_factory=dict)
    splits: dict[tuple[str, ...], int] = field(default_factory=dict)

    @staticmethod
    def of(query: FeatureQuery) -> Statistics:
        """One pass over each relation's join and category columns, sketched; a catalogue's figures can be given instead."""
        found = Statistics()
        joins = query.joins()
        for r in query.relations:
            df = query.bound(r)
            names = [v for v in df.columns if v in joins or v in query.categorical]
            at = (df.sparkSession.sparkContext.applicationId, df.semanticHash(), tuple(names))
            if at not in _KNOWN:
                row = df.withColumn("__split", F.spark_partition_id()).agg(F.count(F.lit(1)), F.approx_count_distinct("__split"), *[F.approx_count_distinct(v) for v in names]).first()
                _KNOWN[at] = float(row[0]), {v: float(n) for v, n in zip(names, row[2:], strict=True)}, int(row[1])
            found.rows[r], found.distinct[r], found.splits[tuple(df.columns)] = _KNOWN[at]
        return found

    def size(self, relation: str) -> Size:
        return Size(self.rows[relation], dict(self.distinct[relation]))

    def groups(self, size: Size, columns: Iterable[str]) -> float:
        """Estimated key combinations in a frame: columns of one relation never combine in more ways than it has rows."""
        left, n = set(columns), 1.0
        while left:
            owned = {r: left & d.keys() for r, d in self.distinct.items()}
            best = max(owned, key=lambda r: (len(owned[r]), -self.rows[r]))
            mine = owned[best] or left
            n *= min(prod(max(1.0, size.distinct.get(v, size.rows)) for v in mine), max(1.0, self.rows[best]) if owned[best] else size.rows)
            left -= mine
        return min(n, size.rows)
