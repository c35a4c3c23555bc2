"""Leaf phase: reduce the bags of a covered decomposition, then evaluate along its tree with semijoins, joining head nodes alone."""

from __future__ import annotations

from pyspark.sql import DataFrame

from .decomposition import TreeDecomposition
from .instance import columns, natural_join, project, semijoin
from .materialize import LARGE, agreed, agreeing, at_most, collected, keep, most_rows
from .query import Vars


def reduce_bags(relations: dict[Vars, DataFrame], t: TreeDecomposition) -> dict[Vars, DataFrame]:
    """Each bag's relation, semijoin-reduced by every relation over a subset of its variables."""
    return {bag: reduced(relations, bag, relations[bag]) for bag in t.bags}


def reduced(relations: dict[Vars, DataFrame], bag: Vars, df: DataFrame) -> DataFrame:
    """df over a bag's variables, semijoin-reduced by every relation over fewer of them with which its rows are not known to agree."""
    known, first = agreed(df), df
    left = [k for k in relations if k < bag and relations[k] not in known]
    for k in sorted(left, key=lambda k: (-len(k), sorted(k))):
        if not any(k < o for o in left):  # a smaller one is implied by a larger one that is reduced alike
            by, own = relations[k], agreed(relations[k])
            for o in sorted((o for o in left if o < k and relations[o] not in own), key=sorted):
                by = semijoin(by, relations[o])
            if df is not first and (most_rows(df) or 0) >= LARGE:  # shuffle files of one semijoin go before the next
                df = keep(df)
                collected(df.sparkSession, LARGE)
            df = semijoin(df, by)
    return df if df.columns == columns(bag) else agreeing(at_most(df.select(columns(bag)), most_rows(df)), df)


def up_pass(t: TreeDecomposition, rel: dict[int, DataFrame]) -> dict[int, DataFrame]:
    out = dict(rel)
    for i in t.bottom_up():
        if t.parent[i] >= 0:
            out[t.parent[i]] = semijoin(out[t.parent[i]], out[i])
    return out


def down_pass(t: TreeDecomposition, rel: dict[int, DataFrame]) -> dict[int, DataFrame]:
    out = dict(rel)
    for i in reversed(t.bottom_up()):
        if t.parent[i] >= 0:
            out[i] = semijoin(out[i], out[t.parent[i]])
    return out


def full_reduction(t: TreeDecomposition, bags: dict[Vars, DataFrame]) -> dict[int, DataFrame]:
    return down_pass(t, up_pass(t, {i: bags[b] for i, b in enumerate(t.bags)}))


def acyclic_evaluate(t: TreeDecomposition, bags: dict[Vars, DataFrame], head: Vars, repeated: bool = False) -> DataFrame:
    """Distinct answers over the head. After the reductions each join of head nodes only adds answers, never dangling rows.
    repeated: bags may have rows several times; semijoins do not mind, so only the reduced head nodes are made distinct."""
    if not head:
        raise ValueError("use acyclic_boolean for an empty head")
    rel = full_reduction(t, bags)
    own = [i for i in reversed(t.bottom_up()) if i in t.head_nodes]
    nodes = [at_most(rel[i].distinct(), most_rows(rel[i])) if repeated else rel[i] for i in own]
    out = nodes[0]
    for df in nodes[1:]:
        out = natural_join(out, df)
    return project(out, head)


def acyclic_boolean(t: TreeDecomposition, bags: dict[Vars, DataFrame]) -> bool:
    rel = up_pass(t, {i: bags[b] for i, b in enumerate(t.bags)})
    return not rel[t.bottom_up()[-1]].limit(1).isEmpty()
