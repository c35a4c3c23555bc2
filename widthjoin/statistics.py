"""Degree statistics: bounds on how many Y-values go with one X-value, declared or measured, each with a guard relation."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .instance import Instance, columns
from .query import ConjunctiveQuery, Vars


@dataclass(frozen=True)
class DegreeConstraint:
    """At most max_degree Y-values for one X-value in the guard. An empty X: a cardinality; max_degree 1: X is a key for Y."""

    y: Vars
    x: Vars
    max_degree: int
    guard: Vars

    def __post_init__(self):
        if not (self.x | self.y) <= self.guard:
            raise ValueError("the guard must have all variables of the constraint")


@dataclass(frozen=True)
class Statistics:
    terms: tuple[DegreeConstraint, ...] = ()

    @staticmethod
    def declare(*terms: tuple[str | Iterable[str], str | Iterable[str], int, Iterable[str]]) -> Statistics:
        """(y, x, max_degree, guard), the sets as iterables of names or one name."""
        own = lambda s: frozenset([s]) if isinstance(s, str) and s else frozenset(s)
        return Statistics(tuple(DegreeConstraint(own(y), own(x), n, frozenset(g)) for y, x, n, g in terms))

    def __add__(self, other: Statistics) -> Statistics:
        return Statistics(self.terms + other.terms)

    def frame(self, spark: SparkSession) -> DataFrame:
        rows = [(columns(t.y), columns(t.x), t.max_degree, columns(t.guard)) for t in self.terms]
        return spark.createDataFrame(rows, "y array<string>, x array<string>, max_degree bigint, guard array<string>")


def degrees(rel: DataFrame, y: Iterable[str], x: Iterable[str]) -> DataFrame:
    """(x..., degree): distinct Y-values of each X-value."""
    x, rest = columns(x), columns(set(y) - set(x))
    own = rel.select(*x, *rest) if set(rel.columns) == {*x, *rest} else rel.select(*x, *rest).distinct()
    return own.groupBy(*x).agg(F.count(F.lit(1)).alias("degree"))


def max_degree(rel: DataFrame, y: Iterable[str], x: Iterable[str]) -> int:
    return degrees(rel, y, x).agg(F.coalesce(F.max("degree"), F.lit(0)).alias("d")).first()["d"]


def degree_at(rel: DataFrame, y: Iterable[str], x: dict[str, object]) -> int:
    for v, value in x.items():
        rel = rel.filter(F.col(v) == F.lit(value))
    return rel.select(columns(y)).distinct().count()


def collect_statistics(inst: Instance, terms: Iterable[tuple[Vars, Vars, Vars]]) -> Statistics:
    """Measure (y, x, guard) terms, all in one job."""
    terms = list(terms)
    parts = [degrees(inst.relations[g], y, x).agg(F.coalesce(F.max("degree"), F.lit(0)).alias("d")).select(F.lit(i).alias("i"), "d") for i, (y, x, g) in enumerate(terms)]
    if not parts:
        return Statistics()
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.union(p)
    found = {r["i"]: r["d"] for r in whole.collect()}
    return Statistics(tuple(DegreeConstraint(y, x, max(1, found[i]), g) for i, (y, x, g) in enumerate(terms)))


def check_statistics(inst: Instance, stats: Statistics) -> list[tuple[DegreeConstraint, int]]:
    """Constraints whose guard violates them, with the measured degree."""
    own = [t for t in stats.terms if t.guard in inst.relations]
    missing = [(t, -1) for t in stats.terms if t.guard not in inst.relations]
    got = collect_statistics(inst, [(t.y, t.x, t.guard) for t in own]).terms
    return missing + [(t, m.max_degree) for t, m in zip(own, got, strict=True) if m.max_degree > t.max_degree]


def cardinalities(inst: Instance) -> Statistics:
    return Statistics(tuple(DegreeConstraint(k, frozenset(), max(1, n), k) for k, n in inst.measure().items()))


def edge_domination(query: ConjunctiveQuery, n: int) -> Statistics:
    """Every atom has at most n rows."""
    return Statistics(tuple(DegreeConstraint(e, frozenset(), n, e) for e in query.edges))
