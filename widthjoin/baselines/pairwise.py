"""Plain binary joins: one plan for all rows, joined along common variables, in the order whose joins are expected to be smallest."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..guided import join_profile
from ..instance import Instance, columns, met, natural_join, project
from ..materialize import sendable
from ..query import ConjunctiveQuery, Vars


@dataclass
class Estimate:
    """Rows of a relation, and about how many values each of its variables has."""

    rows: float
    values: dict[str, float]

    def fan_out(self, on: Vars) -> float:
        """Rows that go with one value of the given variables, on average."""
        n = 1.0
        for v in on:
            n *= max(self.values[v], 1.0)
        return self.rows / min(n, max(self.rows, 1.0))


def estimates(inst: Instance, edges: Iterable[Vars]) -> dict[Vars, Estimate]:
    """One aggregate a relation; the values only choose the order, never the answers."""
    out = {}
    for e in edges:
        own = columns(e)
        r = inst.relations[e].agg(F.count(F.lit(1)).alias("__n"), *[F.approx_count_distinct(v).alias(v) for v in own]).first()
        out[e] = Estimate(float(r["__n"]), {v: float(r[v]) for v in own})
    return out


def greedy(first: Vars, left: Iterable[Vars], of: dict[Vars, Estimate]) -> tuple[float, list[Vars]]:
    """(largest expected join, order) from a first relation on: those that share variables before the others, the least fan-out first."""
    out, left, seen, rows = [first], list(left), first, of[first].rows
    most = rows
    while left:
        left.sort(key=lambda e: (not e & seen, of[e].fan_out(e & seen), -len(e & seen), sorted(e)))
        e = left.pop(0)
        rows *= of[e].fan_out(e & seen)
        most, seen = max(most, rows), seen | e
        out.append(e)
    return most, out


def connected_order(edges: Iterable[Vars], of: dict[Vars, Estimate]) -> tuple[float, list[Vars]]:
    """(largest expected join, order): the best of the greedy orders from each relation."""
    own = sorted(edges, key=sorted)
    return min((greedy(e, [o for o in own if o != e], of) for e in own), key=lambda x: x[0])


#: How many times the rows of all relations the join of two may have before what is joined to it is sent to it.
CROWDED = 10


def crowded(inst: Instance, order: list[Vars]) -> bool:
    """Whether the first join in this order, counted from degrees, is far longer than all relations, and these are short enough to be sent to it."""
    first, second = (inst.relations[e] for e in order[:2]) if len(order) > 1 else (None, None)
    if first is None or not order[0] & order[1] or not all(sendable(inst.relations[e]) for e in order):
        return False
    return join_profile(first, second, order[0] & order[1], 0, 0).joined > CROWDED * inst.size


def with_texts(inst: Instance, head: Vars, df: DataFrame) -> DataFrame:
    """The head's columns, strings for the numbers of variables that have texts."""
    return df.select(*[F.col(f"__text_{v}").alias(v) if f"__text_{v}" in df.columns else v for v in columns(head)])


def joined_in_place(inst: Instance, order: list[Vars], of: dict[Vars, Estimate]) -> DataFrame:
    """The join of all relations, of which no row is shuffled or written: those with texts meet first, by their common variables; each other one is sent to what they make.

    Rows of a dense part of the data come from few rows of the first relation, so these are dealt out evenly.
    """
    spark = inst.relations[order[0]].sparkSession
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8 * spark.sparkContext.defaultParallelism)
    wide, left = [e for e in order if e in inst.texts], list(order)
    left.remove(first := (wide or order)[0])
    shared = frozenset.intersection(*wide) if wide else frozenset()
    out = inst.texts.get(first, inst.relations[first]).repartition(tasks, *(columns(shared) if len(wide) > 1 else []))
    seen = first
    for e in wide[1:]:
        left.remove(e)
        out = out.join(inst.texts[e].repartition(tasks, *columns(shared)), columns(e & seen))
        seen |= e
    while left:
        left.sort(key=lambda e: (not e & seen, not e <= seen, of[e].fan_out(e & seen), -len(e & seen), sorted(e)))
        e = left.pop(0)
        out = met(out, inst.relations[e]) if e & seen else out.crossJoin(F.broadcast(inst.relations[e]))
        seen |= e
    return out


def pairwise_evaluate(q: ConjunctiveQuery, inst: Instance) -> DataFrame:
    _, order = connected_order(q.edges, of := estimates(inst, q.edges))
    if inst.texts or (not q.is_boolean and crowded(inst, order)):
        out = with_texts(inst, q.head, joined_in_place(inst, order, of))
        return out if q.head == q.variables else out.distinct()
    out = inst.relations[order[0]]
    for e in order[1:]:
        out = natural_join(out, inst.relations[e])
    if q.is_boolean:
        return out.sparkSession.createDataFrame([(not out.limit(1).isEmpty(),)], "answer boolean")
    return project(out, q.head)
