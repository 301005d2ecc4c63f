"""Interval relations of two closed endpoint comparisons, and their normal form: X >= x and Y <= y."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

_TERM = re.compile(r"\s*([st])\s*(>=|<=)\s*(sq|tq)\s*")


class UnsupportedRelation(ValueError):
    """The predicate is not a conjunction of two closed comparisons of an endpoint with a query endpoint; filter exactly instead."""


@dataclass(frozen=True)
class Term:
    end: str
    op: str
    query: str

    def holds(self) -> Column:
        a, b = F.col(self.end), F.col(self.query)
        return a >= b if self.op == ">=" else a <= b


@dataclass(frozen=True)
class AxisPlan:
    """X = x_sign * endpoint, and so on; the same signs apply to the query's endpoints."""

    x: Term
    y: Term

    @property
    def signs(self) -> tuple[int, int]:
        return (1 if self.x.op == ">=" else -1), (1 if self.y.op == "<=" else -1)

    def object_axes(self) -> tuple[Column, Column]:
        a, b = self.signs
        return F.col(self.x.end) * a, F.col(self.y.end) * b

    def query_axes(self) -> tuple[Column, Column]:
        a, b = self.signs
        return F.col(self.x.query) * a, F.col(self.y.query) * b


@dataclass(frozen=True)
class Relation:
    name: str
    terms: tuple[Term, Term]

    def predicate(self) -> Column:
        """The plain predicate over s, t, sq, tq: pushable, for exact filtering."""
        return self.terms[0].holds() & self.terms[1].holds()

    def plan(self, swap: bool = False) -> AxisPlan:
        """One term for each axis. A >= term takes X and a <= term Y where there are both; swap assigns them the other way, with signs."""
        a, b = self.terms
        if a.op == "<=" and b.op == ">=":
            a, b = b, a
        return AxisPlan(b, a) if swap else AxisPlan(a, b)


def custom(*terms: str, name: str = "custom") -> Relation:
    if len(terms) != 2:
        raise UnsupportedRelation(f"two comparisons are needed, not {len(terms)}")
    found = [_TERM.fullmatch(t) for t in terms]
    for t, m in zip(terms, found):
        if not m:
            raise UnsupportedRelation(f"{t!r} is not s or t, >= or <=, sq or tq")
    return Relation(name, tuple(Term(*m.groups()) for m in found))


CONTAINED = custom("s>=sq", "t<=tq", name="contained")
OVERLAPS = custom("t>=sq", "s<=tq", name="overlaps")
COVERS = custom("t>=tq", "s<=sq", name="covers")
AFTER = custom("s>=sq", "t>=tq", name="after")
BEFORE = custom("s<=sq", "t<=tq", name="before")
ALL = {r.name: r for r in (CONTAINED, OVERLAPS, COVERS, AFTER, BEFORE)}
