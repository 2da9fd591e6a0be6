"""Constraints between a row's label set and a query's, and their Boolean mixes.

Empty query sets: containment passes every row, overlap none, equality the rows without labels.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


class Constraint:
    name = ""

    def column(self, labels: Column, asked: Column) -> Column:
        raise NotImplementedError

    def __and__(self, other: Constraint) -> All:
        return All((self, other))

    def __or__(self, other: Constraint) -> Any_:
        return Any_((self, other))

    def __invert__(self) -> Not:
        return Not(self)


@dataclass(frozen=True)
class NoFilter(Constraint):
    name = "nofilter"

    def column(self, labels: Column, asked: Column) -> Column:
        return F.lit(True)


@dataclass(frozen=True)
class Containment(Constraint):
    name = "containment"

    def column(self, labels: Column, asked: Column) -> Column:
        return F.size(F.array_except(asked, labels)) == 0


@dataclass(frozen=True)
class Overlap(Constraint):
    name = "overlap"

    def column(self, labels: Column, asked: Column) -> Column:
        return F.arrays_overlap(labels, asked)


@dataclass(frozen=True)
class Equality(Constraint):
    name = "equality"

    def column(self, labels: Column, asked: Column) -> Column:
        return labels == asked


@dataclass(frozen=True)
class FixedEquality(Constraint):
    """Equality where all rows have the same number of labels; assert_fixed_length checks it."""

    name = "fixed"

    def column(self, labels: Column, asked: Column) -> Column:
        return labels == asked


@dataclass(frozen=True)
class All(Constraint):
    parts: tuple[Constraint, ...]
    name = "combined"

    def column(self, labels: Column, asked: Column) -> Column:
        out = F.lit(True)
        for p in self.parts:
            out = out & p.column(labels, asked)
        return out


@dataclass(frozen=True)
class Any_(Constraint):
    parts: tuple[Constraint, ...]
    name = "combined"

    def column(self, labels: Column, asked: Column) -> Column:
        out = F.lit(False)
        for p in self.parts:
            out = out | p.column(labels, asked)
        return out


@dataclass(frozen=True)
class Not(Constraint):
    part: Constraint
    name = "combined"

    def column(self, labels: Column, asked: Column) -> Column:
        return ~self.part.column(labels, asked)


@dataclass(frozen=True)
class HasAny(Constraint):
    """The row has one of these fixed labels, whatever the query asks."""

    wanted: tuple[int, ...]
    name = "combined"

    def column(self, labels: Column, asked: Column) -> Column:
        return F.arrays_overlap(labels, F.array(*map(F.lit, self.wanted)).cast("array<int>"))


@dataclass(frozen=True)
class Matches(Constraint):
    """A column of the base matches a regular expression."""

    on: str
    pattern: str
    name = "combined"

    def column(self, labels: Column, asked: Column) -> Column:
        return F.col(self.on).rlike(self.pattern)


@dataclass(frozen=True)
class InRange(Constraint):
    """A scalar attribute lies in [low, high]; pushed down to the scan for plain columns."""

    on: str
    low: Any
    high: Any
    name = "combined"

    def column(self, labels: Column, asked: Column) -> Column:
        return F.col(self.on).between(self.low, self.high)


SCENARIOS: dict[str, Constraint] = {c.name: c for c in (NoFilter(), Containment(), Overlap(), Equality(), FixedEquality())}


def constraint(of: str | Constraint) -> Constraint:
    return SCENARIOS[of] if isinstance(of, str) else of


def assert_fixed_length(base: DataFrame) -> int:
    """The common number of labels; raises if rows differ."""
    low, high = base.agg(F.min(F.size("labels")), F.max(F.size("labels"))).first()
    if low != high:
        raise ValueError(f"label vectors have {low} to {high} positions")
    return low or 0


def predicate_sql(scenario: str) -> str:
    return {"nofilter": "true", "containment": "list_has_all(labels, qlabels)", "overlap": "list_has_any(labels, qlabels)", "equality": "labels = qlabels", "fixed": "labels = qlabels"}[scenario]
