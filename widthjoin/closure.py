"""Bound closure: make bounds monotone and consistent with the statistics, with a relation behind every bound.

Bounds only fall along two kinds of edges: from a set to its subsets (a
projection, weight one) and from X to X + Y for a degree constraint (a join with
the guard, weight the degree). So the least bounds are shortest paths in products
of weights from the bounds at hand, found by one run of Dijkstra on the driver;
only the winning edges are replayed on DataFrames.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass
from fractions import Fraction

from .bounds import EMPTY, Bounds, subsets
from .instance import Instance, natural_join, project
from .query import Vars, show
from .statistics import DegreeConstraint, Statistics


@dataclass(frozen=True)
class Step:
    """Get the relation over `to` from the one over `source`: a projection, or a join with a constraint's guard."""

    to: Vars
    source: Vars
    term: DegreeConstraint | None = None


def settle(stats: Statistics, vars: Vars, bounds: Bounds) -> tuple[Bounds, list[Step]]:
    """The closed bounds, and the steps that give each lowered set its relation, in an order in which sources come first."""
    best: dict[Vars, Fraction] = {EMPTY: Fraction(1)}
    done: dict[Vars, Fraction] = {}
    by: dict[Vars, Step] = {}
    order: list[Vars] = []
    heap = [(Fraction(1), 0, show(EMPTY), EMPTY)]
    for s, v in bounds.items():
        if s:
            best[s] = Fraction(v)
            heapq.heappush(heap, (best[s], -len(s), show(s), s))
    while heap:
        v, _, _, s = heapq.heappop(heap)
        if s in done or v > best[s]:
            continue
        done[s] = v
        order.append(s)
        edges = [(s - {x}, v, Step(s - {x}, s)) for x in s if len(s) > 1]
        edges += [(s | t.y, v * t.max_degree, Step(s | t.y, s, t)) for t in stats.terms if t.x == s and not t.y <= s]
        for to, value, step in edges:
            if to and (to not in best or value < best[to]):
                best[to], by[to] = value, step
                heapq.heappush(heap, (value, -len(to), show(to), to))
    return done, [by[s] for s in order if s in by and done[s] < bounds.get(s, done[s] + 1)]


def settle_cardinalities(bounds: Bounds) -> tuple[Bounds, list[Step]]:
    """settle() where sizes are the only statistics: each set takes the least bound of a set above it, by one projection."""
    own, steps = dict(bounds) | {EMPTY: Fraction(1)}, []
    below = {x for s in bounds for x in subsets(s) if x}
    for x in sorted(below, key=lambda s: (-len(s), show(s))):
        least = min((s for s in bounds if x <= s and s), key=lambda s: (bounds[s], len(s), show(s)))
        if x not in bounds or bounds[least] < bounds[x]:
            own[x] = Fraction(bounds[least])
            steps.append(Step(x, least))
    return own, steps


def only_cardinalities(stats: Statistics, bounds: Bounds) -> bool:
    """No constraint has a condition, and none is below the bound of its own set."""
    return all(not t.x and t.y in bounds and bounds[t.y] <= t.max_degree for t in stats.terms)


def apply(inst: Instance, steps: list[Step]) -> Instance:
    out = inst.copy()
    for step in steps:
        source = out.relations.get(step.source)
        if step.term is None:
            df = project(source, step.to)
        else:
            guard = project(inst.relations[step.term.guard], step.term.x | step.term.y)
            df = guard if source is None or not step.source else natural_join(source, guard)
        out.augment(step.to, df)
    return out


def close_bounds(stats: Statistics, inst: Instance, bounds: Bounds, vars: Vars) -> tuple[Instance, Bounds]:
    closed, steps = settle_cardinalities(bounds) if only_cardinalities(stats, bounds) else settle(stats, vars, bounds)
    return apply(inst, steps), closed


def close_bounds_naive(stats: Statistics, vars: Vars, bounds: Bounds) -> Bounds:
    """Reference for tests: repair one violation after the other until none is left (bounds alone)."""
    own = dict(bounds) | {EMPTY: Fraction(1)}
    while True:
        for x in subsets(vars):
            above = [own[y] for y in own if x < y]
            if x and above and own.get(x, max(above) + 1) > min(above):
                own[x] = min(above)
                break
        else:
            for t in stats.terms:
                if t.x in own and own.get(t.x | t.y, own[t.x] * t.max_degree + 1) > own[t.x] * t.max_degree:
                    own[t.x | t.y] = own[t.x] * t.max_degree
                    break
            else:
                return own


def check_closure(before: Bounds, after: Bounds, c: Fraction | None = None) -> list[str]:
    """Bounds never rise; and after lowering one entry to c, none that changed falls below c."""
    out = [f"{show(s)} rose" for s in before if after[s] > before[s]]
    if c is not None:
        out += [f"{show(s)} fell below" for s in after if after[s] < before.get(s, after[s] + 1) and after[s] < c and s in before]
    return out
