"""Table functions for SQL, an aggregate of degrees, and an entry that takes SQL text or a rule."""

from __future__ import annotations

import sys

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import bounds, decomposition, query, simplex, statistics, width
from ..guided import Options, guided_evaluate
from ..instance import Instance
from ..query import parse_rule, parse_sql, show
from ..statistics import Statistics

PROFILE = "n bigint, largest bigint, p99 double, mean double"


def sql(spark: SparkSession, text: str, tables: dict[str, DataFrame] | None = None, stats: Statistics | None = None, options: Options | None = None) -> DataFrame:
    """Answers of `SELECT DISTINCT ... FROM ... WHERE equalities`, or of a rule, by the guided evaluator.

    Relations are tables of the session, or those passed in. A rule takes columns by position, SQL by name.
    """
    have = tables or {}
    of = lambda name: have[name] if name in have else spark.table(name)
    if ":-" in text:
        q = parse_rule(text)
        inst = Instance.load(q, {a.relation: of(a.relation) for a in q.atoms})
    else:
        q, columns_of = parse_sql(text)
        inst = Instance.of_atoms((a, of(a.relation).select(*own)) for a, own in zip(q.atoms, columns_of.values(), strict=True))
    return guided_evaluate(q, inst, stats, options)


class Decompositions:
    """(tree, bags): the undominated decompositions of a rule."""

    def eval(self, rule: str):
        for i, t in enumerate(decomposition.enumerate_decompositions(parse_rule(rule))):
            yield i, "|".join(sorted(map(show, t.bags)))


class Widths:
    """(measure, value) of a rule whose atoms have at most n rows."""

    def eval(self, rule: str, n: int):
        q = parse_rule(rule)
        own = statistics.edge_domination(q, n)
        yield "width", round(width.submodular_width(q, own, n), 6)
        yield "single tree", round(width.single_width(q, own, n), 6)


def register(spark: SparkSession) -> None:
    """decompositions(rule), widths(rule, n) and degree_profile(degree) in SQL. What they use is pickled with them, so workers need no copy."""
    for module in (query, bounds, decomposition, simplex, statistics, width, sys.modules[__name__]):
        cloudpickle.register_pickle_by_value(module)
    spark.udtf.register("decompositions", F.udtf(Decompositions, returnType="tree int, bags string"))
    spark.udtf.register("widths", F.udtf(Widths, returnType="measure string, value double"))
    spark.udf.register("degree_profile", degree_profile())


def degree_profile():
    """A grouped aggregate of degrees: how many, largest, 99th percentile, mean."""

    def profile(degree: pd.Series) -> str:
        return f"{len(degree)} {int(degree.max())} {float(degree.quantile(0.99)):.3f} {float(degree.mean()):.3f}"

    return F.pandas_udf(profile, "string")
