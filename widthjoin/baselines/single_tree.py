"""Evaluation over one fixed decomposition: every bag is the join of the atoms inside it and of projections that bind its other variables.

A bag that is expected to be larger than what a neighbour leaves of it is made from the neighbour's values of the variables they share.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..acyclic import acyclic_boolean, acyclic_evaluate
from ..decomposition import TreeDecomposition, enumerate_decompositions, trivial_decomposition
from ..guided import join_profile
from ..instance import Instance, natural_join, project
from ..query import ConjunctiveQuery, Vars
from .pairwise import Estimate, connected_order, estimates, greedy, joined_in_place, with_texts


def atoms_of(q: ConjunctiveQuery, bag: Vars) -> list[Vars]:
    """Variable sets of the atoms inside a bag, and of the projections that bind its other variables."""
    own = sorted((e for e in q.edges if e <= bag), key=lambda e: (-len(e), sorted(e)))
    while frozenset().union(*own) != bag:  # variables that only wider atoms bind
        missing = bag - frozenset().union(*own)
        own.append(max((e for e in q.edges), key=lambda e: (len(e & missing), sorted(e))) & bag)
    return own


def bag_relation(q: ConjunctiveQuery, inst: Instance, bag: Vars, near: DataFrame | None = None) -> DataFrame:
    """near: distinct values of some of its variables, outside which no row of the bag is needed."""
    parts = [inst.relations[e] if e in inst.relations else project(inst.relations[next(o for o in sorted(q.edges, key=sorted) if e <= o)], e) for e in atoms_of(q, bag)]
    out, left = (parts[0], parts[1:]) if near is None else (near, parts)
    while left:
        left.sort(key=lambda p: -len(set(p.columns) & set(out.columns)))
        out = natural_join(out, left.pop(0))
    return out


def bag_size(q: ConjunctiveQuery, inst: Instance, bag: Vars) -> int:
    """Rows of a bag. The join of two atoms is counted from their degrees, not made."""
    own = atoms_of(q, bag)
    if len(own) == 2 and all(e in inst.relations for e in own) and own[0] & own[1]:
        return join_profile(inst.relations[own[0]], inst.relations[own[1]], own[0] & own[1], 0, 0).joined
    return bag_relation(q, inst, bag).count()


def bag_relations(q: ConjunctiveQuery, inst: Instance, t: TreeDecomposition) -> dict[Vars, DataFrame]:
    """The bags, from the one that is expected to be smallest outwards."""
    if len(t.bags) == 1 or not all(set(atoms_of(q, b)) <= set(inst.relations) for b in t.bags):
        return {b: bag_relation(q, inst, b) for b in t.bags}
    of = estimates(inst, q.edges)
    cost = {i: connected_order(atoms_of(q, b), of)[0] for i, b in enumerate(t.bags)}
    first = min(cost, key=cost.get)
    made, rows, wave = {first: bag_relation(q, inst, t.bags[first])}, {first: cost[first]}, [first]
    while wave:
        i = wave.pop(0)
        for j in range(len(t.bags)):
            if j in made or (t.parent[i] != j and t.parent[j] != i):
                continue
            shared, own = t.bags[i] & t.bags[j], atoms_of(q, t.bags[j])
            if shared:
                values = {v: max((of[e].values[v] for e in q.edges if v in e), default=1.0) for v in shared}
                through = greedy(shared, [e for e in own if e != shared], of | {shared: Estimate(rows[i], values)})[0]
            near = project(made[i], shared) if shared and through < cost[j] else None
            made[j], rows[j] = bag_relation(q, inst, t.bags[j], near), cost[j] if near is None else through
            wave.append(j)
    return {t.bags[i]: df for i, df in made.items()}


def single_tree_evaluate(q: ConjunctiveQuery, inst: Instance, tree: TreeDecomposition | int = 0, sizes: dict | None = None) -> DataFrame:
    """tree: a decomposition, or its place among the undominated ones. sizes: gets the rows of each whole bag."""
    t = enumerate_decompositions(q)[tree] if isinstance(tree, int) else tree
    if inst.texts and len(t.bags) == 1:  # the bag is the answers
        _, order = connected_order(q.edges, of := estimates(inst, q.edges))
        out = with_texts(inst, q.head, joined_in_place(inst, order, of))
        return out if q.head == q.variables else out.distinct()
    bags = bag_relations(q, inst, t)
    if sizes is not None:
        sizes |= {b: bag_size(q, inst, b) for b in t.bags}
    if q.is_boolean:
        spark = next(iter(bags.values())).sparkSession
        return spark.createDataFrame([(acyclic_boolean(t, bags),)], "answer boolean")
    return acyclic_evaluate(t, bags, q.head)


def trivial(q: ConjunctiveQuery) -> TreeDecomposition:
    return trivial_decomposition(q)
