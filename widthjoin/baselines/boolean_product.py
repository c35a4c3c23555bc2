"""Join-project over a semiring: which (x, z) have a common y, with no list of the y; and least sums over cycles."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def boolean_product(r: DataFrame, s: DataFrame, y: str) -> DataFrame:
    """(x..., z...) with a common y, and the number of such y."""
    own = [c for c in r.columns if c != y] + [c for c in s.columns if c != y]
    return r.join(s, y).groupBy(*own).agg(F.count(F.lit(1)).alias("n_common"))


def min_plus_cycle(answers: DataFrame, weights: dict[str, DataFrame], by: list[str]) -> DataFrame:
    """Least sum of weights of the answers of a query, for each value of `by`.

    weights: column name -> (variables..., weight) of one relation. As the least
    value is idempotent, answers that several leaves give do no harm.
    """
    out, names = answers, []
    for name, w in weights.items():
        on = [c for c in w.columns if c != "weight"]
        out = out.join(w.groupBy(*on).agg(F.min("weight").alias(name)), on)
        names.append(name)
    total = sum((F.col(n) for n in names), F.lit(0).cast("bigint"))
    return out.groupBy(*by).agg(F.min(total).alias("least"))
