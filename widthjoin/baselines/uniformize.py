"""The uniformizing baseline, reconstructed from its outline: keep relations consistent, split a pair A < B whose largest degree is far
above its average, until none is left; then join where the estimate fits the current cap, and raise the cap when nothing fits.

Splits cover all rows, so the answers are exact. Only cost is compared, not proved here. It knows no degree statistics.
most: an experiment's limit of branches, beyond which it raises; none by default.
"""

from __future__ import annotations

import math
from collections import deque
from itertools import combinations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..decomposition import covered_by, enumerate_decompositions
from ..guided import Run, evaluate_leaves
from ..instance import Instance, columns, natural_join, project, semijoin
from ..materialize import keep
from ..query import ConjunctiveQuery, Vars
from ..statistics import degrees


def uniformity_gap(rel: DataFrame, a) -> DataFrame:
    """One row: rows, keys over a, the largest degree, and how far it is above the average."""
    return degrees(rel, rel.columns, a).agg(F.coalesce(F.sum("degree"), F.lit(0)).alias("n_rows"), F.count(F.lit(1)).alias("n_keys"), F.coalesce(F.max("degree"), F.lit(0)).alias("max_degree")).withColumn("gap", F.round(F.col("max_degree") * F.col("n_keys") / F.greatest("n_rows", F.lit(1)), 6))


def consistent(inst: Instance) -> Instance:
    """Nested relations agree: each is reduced by its subsets, and subsets by it; one sweep each way."""
    out = inst.copy()
    keys = sorted(out.relations, key=lambda k: (len(k), sorted(k)))
    for b in keys:  # written one by one, so that no plan holds another one's plan
        below = [a for a in keys if a < b]
        if below:
            df = out.relations[b]
            for a in below:
                df = semijoin(df, out.relations[a])
            out.relations[b] = keep(df)
    for b in reversed(keys):
        above = [a for a in keys if b < a]
        if above:
            df = out.relations[b]
            for a in above:
                df = semijoin(df, project(out.relations[a], b))
            out.relations[b] = keep(df)
    out.sizes = {}
    out.measure()
    return out


def uniformize_evaluate(q: ConjunctiveQuery, inst: Instance, eps: float = 0.5, most: int | None = None, with_run: bool = False):
    if q.is_boolean:
        full = uniformize_evaluate(q.with_head(q.variables), inst, eps, most)
        return full.sparkSession.createDataFrame([(not full.limit(1).isEmpty(),)], "answer boolean")
    trees = enumerate_decompositions(q)
    n = max(inst.size, 2)
    slack = n**eps
    start = inst.copy()
    for e in q.edges:
        for v in e:
            start.augment(frozenset([v]), project(inst.relations[e], [v]))
    run, queue = Run(n, 0), deque([(consistent(start), float(n))])
    while queue:
        own, cap = queue.popleft()
        sizes = own.measure()
        row = {"branch": len(run.trace), "parent": -1, "kind": "uniform", "largest": max(sizes.values()), "n_relations": len(sizes)}
        run.trace.append(row)
        if most is not None and len(run.trace) > most:
            raise RuntimeError(f"more than {most} branches")
        if not all(sizes.values()):
            row["outcome"] = "empty"
            continue
        tree = min((t for t in trees if covered_by(t, set(own.relations))), key=lambda t: max(sizes[b] for b in t.bags), default=None)
        if tree is not None:
            row["outcome"] = "leaf"
            run.leaves.append((tree, own))
            continue
        split = widest_gap(own, slack)
        if split is not None:
            a, b, average = split
            keys = degrees(own.relations[b], b, a)
            high = keys.filter(F.col("degree") > average * slack**0.5).select(columns(a))
            low = keys.filter(F.col("degree") <= average * slack**0.5).select(columns(a))
            row["outcome"] = "split"
            for part in (high, low):
                child = own.copy()
                child.relations[a] = semijoin(child.relations[a], keep(part)) if a in child.relations else keep(part)
                child.sizes.pop(a, None)
                child.relations[b] = semijoin(child.relations[b], child.relations[a])
                queue.append((consistent(child), cap))
            continue
        best = cheapest_join(own, q.variables)
        while best[0] > cap:
            cap *= slack
        child = own.copy()
        x, y = best[1:]
        child.relations[x | y] = keep(natural_join(own.relations[x], own.relations[y]))
        child.sizes.pop(x | y, None)
        row |= {"outcome": "join", "n_rows": child.measure()[x | y]}
        queue.append((consistent(child) if child.sizes[x | y] else child, cap))
    spark = next(iter(inst.relations.values())).sparkSession
    kinds = {c: t for df in inst.relations.values() for c, t in df.dtypes}
    out = evaluate_leaves(q, run, True, spark, ", ".join(f"{c} {kinds[c]}" for c in columns(q.head)))
    return (out, run) if with_run else out


def widest_gap(inst: Instance, slack: float) -> tuple[Vars, Vars, float] | None:
    pairs = [(a, b) for b in inst.relations for a in inst.relations if a < b]
    parts = [uniformity_gap(inst.relations[b], a).select(F.lit(i).alias("i"), "n_rows", "n_keys", "gap") for i, (a, b) in enumerate(pairs)]
    if not parts:
        return None
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.union(p)
    worst = max(whole.collect(), key=lambda r: (r["gap"], -r["i"]))
    if worst["gap"] <= slack:
        return None
    return *pairs[worst["i"]], worst["n_rows"] / max(worst["n_keys"], 1)


def cheapest_join(inst: Instance, vars_: Vars) -> tuple[float, Vars, Vars]:
    """The pair with the least estimate of rows: sizes multiplied, divided by the common part's."""
    s, out = inst.sizes, []
    for x, y in combinations(sorted(inst.relations, key=lambda k: (len(k), sorted(k))), 2):
        if not (x <= y or y <= x) and x | y not in inst.relations and (x & y in s or not x & y):
            out.append((s[x] * s[y] / (s[x & y] if x & y else 1), sorted(x | y), sorted(x), x, y))
    if not out:
        raise RuntimeError("nothing is left to join")
    best = min(out)
    return best[0], best[3], best[4]


def exponent(rows: int, n: int) -> float:
    return math.log(max(rows, 1)) / math.log(max(n, 2))
