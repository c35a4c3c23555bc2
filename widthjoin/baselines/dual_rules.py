"""The dual baseline: one disjunctive rule for each minimal bag selector, then all decompositions over the tables the rules fill.

A disjunctive rule gives each row of the body's join to at least one of its head
tables. It is solved by the same splitting as the guided evaluator, which stops
as soon as one bag of the selector has a relation. If, for an answer, each tree
lacked it in some bag, these bags would hold a selector whose rule has no place
for it; so some tree has it in all of its bags.
"""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..acyclic import acyclic_boolean, acyclic_evaluate, reduced
from ..decomposition import bag_selectors, enumerate_decompositions
from ..guided import Options, explore
from ..instance import Instance, columns
from ..materialize import keep_union
from ..query import ConjunctiveQuery, Vars
from ..statistics import Statistics


def rule_parts(q: ConjunctiveQuery, inst: Instance, heads: frozenset[Vars], stats: Statistics | None, options: Options | None) -> dict[Vars, list[DataFrame]]:
    """The leaves' rows of some of the heads."""
    order = sorted(heads, key=sorted)
    run = explore(q, inst, stats, options or Options(), lambda s: next((h for h in order if h in s), None), order)
    out: dict[Vars, list[DataFrame]] = {}
    for head, leaf in run.leaves:
        out.setdefault(head, []).append(reduced(leaf.relations, head, leaf.relations[head]))
    return out


def disjunctive_rule(q: ConjunctiveQuery, inst: Instance, heads: frozenset[Vars], stats: Statistics | None = None, options: Options | None = None) -> dict[Vars, DataFrame]:
    """Tables over some of the heads that together cover every row of the body's join."""
    return {k: keep_union(parts).distinct() for k, parts in rule_parts(q, inst, heads, stats, options).items()}


def dual_rules_evaluate(q: ConjunctiveQuery, inst: Instance, stats: Statistics | None = None, options: Options | None = None) -> DataFrame:
    trees = enumerate_decompositions(q)
    base = {e: inst.relations[e] for e in q.edges}
    parts: dict[Vars, list[DataFrame]] = {}
    for s in bag_selectors(trees):
        for k, own in rule_parts(q, inst, s, stats, options).items():
            parts.setdefault(k, []).extend(reduced(base, k, df) for df in own)
    tables = {k: keep_union(own) for k, own in parts.items()}
    own = [t for t in trees if t.bag_set <= set(tables)]
    spark = next(iter(inst.relations.values())).sparkSession
    if q.is_boolean:
        return spark.createDataFrame([(any(acyclic_boolean(t, tables) for t in own),)], "answer boolean")
    kinds = {c: k for df in inst.relations.values() for c, k in df.dtypes}
    out = spark.createDataFrame([], ", ".join(f"{c} {kinds[c]}" for c in columns(q.head)))
    for t in own:
        out = out.union(acyclic_evaluate(t, tables, q.head, repeated=True))
    return out.distinct()
