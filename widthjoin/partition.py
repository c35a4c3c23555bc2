"""Splitting a relation by degree: few heavy keys, and light rows in parts of even degree."""

from __future__ import annotations

from collections.abc import Iterable
from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .instance import columns
from .statistics import degrees


def heavy_light(rel: DataFrame, w: Iterable[str], threshold: Fraction | int) -> tuple[DataFrame, DataFrame]:
    """(keys over w with a degree above the threshold, rows of the other keys). Degrees are sums with map-side combine;
    at most |rel| / threshold keys are heavy, so Spark's size check usually broadcasts them."""
    w = columns(w)
    keys = degrees(rel, rel.columns, w).filter(F.col("degree") > int(threshold)).select(w)
    return keys, rel.join(keys, w, "left_anti").select(rel.columns)


def equal_degree_parts(light: DataFrame, w: Iterable[str], most: int) -> DataFrame:
    """light with __part: each key has at most `most` rows in a part. Heavy keys are gone, so no window is long."""
    w = columns(w)
    rest = [c for c in light.columns if c not in w]
    number = F.row_number().over(Window.partitionBy(*w).orderBy(*rest)) - 1
    return light.withColumn("__part", F.floor(number / max(1, most)).cast("int"))
