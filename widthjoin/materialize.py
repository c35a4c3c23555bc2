"""Where branch relations live, and how they are counted.

Relations that a branch keeps are written once to the folder that all executors
share, so that plans stay short and a lost executor costs a task, not a branch.
Sizes of many relations come from one job.
"""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from weakref import WeakKeyDictionary, WeakSet

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def scratch(spark: SparkSession) -> str:
    """A new path in spark.checkpoint.dir; where that is unset and the master is local, as in tests, in a temporary folder."""
    sc = spark.sparkContext
    top = sc.getConf().get("spark.checkpoint.dir")
    if not top:
        if not sc._jsc.sc().getCheckpointDir().isDefined():
            if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
                raise ValueError("spark.checkpoint.dir is not set: a cluster needs a folder that all its machines share")
            sc.setCheckpointDir(tempfile.mkdtemp(prefix="widthjoin-"))
        top = sc._jsc.sc().getCheckpointDir().get()
    path = f"{top.rstrip('/')}/{uuid.uuid4().hex}"
    for own in _made:
        own.append(path)
    return path


#: Paths made inside each call of cleaned() that has not returned yet.
_made: list[list[str]] = []


def cleaned(spark: SparkSession, make: Callable[[], DataFrame]) -> DataFrame:
    """make()'s rows, written; every relation that was kept on the way is deleted. Without it a lazy result still reads them."""
    path, own = scratch(spark), []
    _made.append(own)
    try:
        df = make()
        df.write.parquet(path)
    finally:
        _made.remove(own)
        fs = spark._jvm.org.apache.hadoop.fs
        for x in own:
            p = fs.Path(x)
            p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
    return spark.read.schema(df.schema).parquet(path)


#: Rows that a relation has at most, where that is known. Spark takes the size of compressed files for the size of their rows.
_most: WeakKeyDictionary = WeakKeyDictionary()


def at_most(df: DataFrame, rows: int | None) -> DataFrame:
    if rows is not None:
        _most[df] = rows
    return df


def most_rows(df: DataFrame) -> int | None:
    return _most.get(df)


def too_long(df: DataFrame) -> bool:
    """Whether a relation may be above Spark's limit for broadcasts by its rows, though its files may be below it."""
    rows, limit = most_rows(df), df.sparkSession._jsparkSession.sessionState().conf().autoBroadcastJoinThreshold()
    return rows is not None and rows * sum(8 if k != "string" else 40 for _, k in df.dtypes) + 8 * rows > limit


#: Relations that each row of a relation agrees with, as far as that is known: those it was joined or filtered by, its projections.
_agrees: WeakKeyDictionary = WeakKeyDictionary()


def agreeing(df: DataFrame, *others: DataFrame) -> DataFrame:
    """df, noted as agreeing with others, so that it need not be semijoined by them again."""
    own = _agrees.setdefault(df, WeakSet())
    for o in others:
        own |= {o, *_agrees.get(o, ())}
    return df


def agreed(df: DataFrame) -> set[DataFrame]:
    out, left = {df}, [df]
    while left:
        more = set(_agrees.get(left.pop(), ())) - out
        out |= more
        left += more
    return out


#: Rows of numbers up to which a relation may be sent to every task.
SENT = 1_000_000


def sendable(df: DataFrame) -> bool:
    """Whether a relation is known to have few enough rows, all of numbers, to meet a longer one where that one is."""
    rows = most_rows(df)
    return rows is not None and rows <= SENT and all(k in ("boolean", "tinyint", "smallint", "int", "bigint", "float", "double", "date", "timestamp") for _, k in df.dtypes)


def keep(df: DataFrame) -> DataFrame:
    """Write and read back."""
    return keep_counted(df)[0]


def keep_counted(df: DataFrame) -> tuple[DataFrame, int]:
    """keep(), and the number of rows, observed by the job that writes."""
    path = scratch(df.sparkSession)
    n = written(df, path)
    out = at_most(df.sparkSession.read.schema(df.schema).parquet(path), n)
    agreeing(df, agreeing(out, df))
    return out, n


def written(df: DataFrame, path: str) -> int:
    seen = Observation()
    df.observe(seen, F.count(F.lit(1)).alias("n")).write.option("compression", "zstd").parquet(path)
    return seen.get["n"]


def keep_union(parts: list[DataFrame]) -> DataFrame:
    """The rows of all parts, each written by its own job, side by side. They are read back by one scan, so that the plan of a
    result does not grow with the number of parts, however often it uses them. Rows that several parts have come several times."""
    spark, own = parts[0].sparkSession, parts[0].columns
    top = scratch(spark)
    paths = [f"{top}/{i}" for i in range(len(parts))]
    with ThreadPoolExecutor(4) as pool:
        n = sum(pool.map(lambda df, path: written(df.select(own), path), parts, paths))
    return at_most(spark.read.schema(parts[0].schema).parquet(*paths), n)


#: Rows of an instance from which shuffle files of steps that are over are worth a collection of garbage.
LARGE = 1_000_000


def collected(spark: SparkSession, rows: int) -> None:
    """Of large instances, let Spark drop the shuffle files of steps that are over; else they stay until the driver happens to collect its garbage."""
    if rows >= LARGE:
        gc.collect()
        spark.sparkContext._jvm.System.gc()


def count_all(frames: dict) -> dict:
    """Row counts of several DataFrames, one job."""
    if not frames:
        return {}
    keys = list(frames)
    parts = [frames[k].agg(F.count(F.lit(1)).alias("n")).select(F.lit(i).alias("i"), "n") for i, k in enumerate(keys)]
    whole = parts[0]
    for p in parts[1:]:
        whole = whole.union(p)
    got = {r["i"]: r["n"] for r in whole.collect()}
    return {k: got[i] for i, k in enumerate(keys)}
