"""Running totals and ranks over a whole table without a window that takes it into one task.

Rows are dealt by ranges of the order and kept; each range's total is one number
for the driver; a window inside a range adds the totals of the ranges before it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..materialize import keep


def running_total(df: DataFrame, order: list[Column], value: str, name: str, parts: int | None = None) -> DataFrame:
    """df with the sum of `value` over all rows up to this one. The order must tell rows apart."""
    spark = df.sparkSession
    n = parts or int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = keep(df.repartitionByRange(n, *order).withColumn("__range", F.spark_partition_id()))
    before, at = [], 0
    for r in ranged.groupBy("__range").agg(F.sum(value).alias("s")).orderBy("__range").collect():  # at most n
        before.append((r["__range"], at))
        at += r["s"] or 0
    offsets = spark.createDataFrame(before, "__range int, __before bigint")
    own = F.sum(value).over(Window.partitionBy("__range").orderBy(*order).rowsBetween(Window.unboundedPreceding, 0))
    return ranged.join(F.broadcast(offsets), "__range").withColumn(name, own + F.col("__before")).drop("__range", "__before")


def dense_rank(df: DataFrame, by: str, name: str, descending: bool = True, parts: int | None = None) -> DataFrame:
    """df with the number of distinct values of `by` up to this row's. Only distinct values are ordered."""
    values = df.select(F.col(by).alias("__v")).distinct().withColumn("__one", F.lit(1))
    ranks = running_total(values, [F.desc("__v") if descending else F.asc("__v")], "__one", name, parts).drop("__one")
    return df.join(ranks, F.col(by) == F.col("__v")).drop("__v")
