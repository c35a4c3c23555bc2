"""What the operators share: column hygiene, the shared scratch folder, words and hashes on Arrow data."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: An Arrow batch is cut into pieces of at most this many bytes of text (one row may be longer).
SLICE_BYTES = 4 << 20
#: Rows of an Arrow batch in the steps that save() runs: whole texts and sets stand in them.
BATCH_ROWS, ARROW_ROWS = 1000, "spark.sql.execution.arrow.maxRecordsPerBatch"
#: Rows of ids or of small fixed-size entries that may be broadcast, after counting them.
BROADCAST_ROWS = 1_000_000
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
SPACES = r"[\x20\x09-\x0D]+"


def pick(df: DataFrame, **kinds: str) -> DataFrame:
    """The named columns alone, cast; a missing column is null. Whatever else the table has, under any name, stays out."""
    have = set(df.columns)
    return df.select(*[(F.col(f"`{c}`") if c in have else F.lit(None)).cast(k).alias(c) for c, k in kinds.items()])


def unused(name: str, *frames: DataFrame) -> str:
    """A column name that none of the tables has."""
    taken = {c.lower() for f in frames for c in f.columns}
    while name.lower() in taken:
        name += "_"
    return name


#: Paths of tables saved since each call of finished() that has not returned yet.
_saved: list[list[str]] = []


def scratch(spark: SparkSession) -> str:
    """A new path in the folder all executors share, spark.checkpoint.dir. A temporary folder only where that is unset and the master is local."""
    sc = spark.sparkContext
    top = sc.getConf().get("spark.checkpoint.dir")
    if not top:
        if not sc._jsc.sc().getCheckpointDir().isDefined():
            if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
                raise ValueError("spark.checkpoint.dir is not set: a cluster needs a folder that all its machines share")
            sc.setCheckpointDir(tempfile.mkdtemp(prefix="widthjoin-"))
        top = sc._jsc.sc().getCheckpointDir().get()
    path = f"{top.rstrip('/')}/{uuid.uuid4().hex}"
    if _saved:
        _saved[-1].append(path)
    return path


def save(df: DataFrame, codec: str = "zstd", path: str | None = None, rows: int | None = BATCH_ROWS) -> DataFrame:
    """Write once to the shared folder and read back: cuts lineage, survives lost executors.

    rows: of an Arrow batch while this is written; None leaves the session's own. JVM and worker hold whole batches, and do not give all of that back.
    """
    spark, path = df.sparkSession, path or scratch(df.sparkSession)
    before = spark.conf.get(ARROW_ROWS, None)
    if rows is not None:
        spark.conf.set(ARROW_ROWS, str(rows))
    try:
        df.write.option("compression", codec).parquet(path)
    finally:
        if rows is not None:
            spark.conf.unset(ARROW_ROWS) if before is None else spark.conf.set(ARROW_ROWS, before)
    return spark.read.schema(df.schema).parquet(path)


def delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def finished(spark: SparkSession, make: Callable[[], DataFrame]) -> DataFrame:
    """make()'s rows, saved; the tables that were saved on the way are deleted. Without it a lazy result still reads them."""
    path, own = scratch(spark), []
    _saved.append(own)
    try:
        return save(make(), path=path)
    finally:
        _saved.pop()
        for x in own:
            delete(spark, x)


def row_key(id: Column, text: Column) -> Column:
    """A 64-bit hash of a row's id and text: rows that share an id alone have different ones."""
    return F.xxhash64(F.coalesce(id.cast("string"), F.lit("")), F.lit("|"), F.coalesce(text.cast("string"), F.lit("")))


def without(documents: DataFrame, found: Callable[[DataFrame], DataFrame], id: str = "doc_id", text: str = "text") -> DataFrame:
    """The documents, with their columns, but for the rows that found() names: it gets (doc_id, text), doc_id being the row's key, and returns some of these doc_id."""
    key = row_key(F.col(f"`{id}`"), F.col(f"`{text}`"))
    name = unused("gone", documents)
    rows = documents.select(key.alias("doc_id"), F.col(f"`{text}`").cast("string").alias("text"))
    gone = save(found(rows).select(F.col("doc_id").alias(name)).distinct())
    return documents.join(small(gone), key == F.col(name), "left_anti")


def small(df: DataFrame, rows: int | None = None, limit: int = BROADCAST_ROWS) -> DataFrame:
    """Hint a broadcast if the counted rows (ids, hashes, short arrays) stay below the limit; else leave the join to Spark."""
    return F.broadcast(df) if (df.count() if rows is None else rows) <= limit else df


def ascii_lower(c):
    return F.translate(c, UPPER, UPPER.lower())


def pieces(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Batches cut so that each has at most `most` bytes of the column, null text replaced by the empty string."""
    for b in batches:
        k = b.schema.get_field_index(column)
        size = np.cumsum(pc.fill_null(pc.binary_length(b.column(k)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
        at = 0
        while at < b.num_rows:
            to = max(at + 1, int(np.searchsorted(size, (size[at - 1] if at else 0) + most, "right")))
            own = b.take(pa.array(np.arange(at, to)))  # copied piece by piece, so that no array starts inside a buffer
            text = pc.fill_null(own.column(k).cast(pa.large_string()), "")
            yield pa.RecordBatch.from_arrays([text if i == k else own.column(i) for i in range(b.num_columns)], names=b.schema.names)
            del own, text
            at = to
        del b, size
        trim()


def trim() -> None:
    """Give freed memory back to the system: workers live on between stages, and would keep their peaks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def words(text: pa.Array, lower: bool = False) -> tuple[np.ndarray, pa.Array]:
    """Offsets (one more than rows) and the words, maximal runs without the six ASCII white-space characters; lower: A-Z only."""
    if lower:
        text = pc.ascii_lower(text)
    split = pc.ascii_split_whitespace(text)
    flat, offs = split.flatten(), split.offsets.to_numpy().astype(np.int64)
    offs = offs - offs[0] if len(offs) else np.zeros(1, np.int64)
    keep = pc.greater(pc.binary_length(flat), 0).to_numpy(zero_copy_only=False).astype(bool)
    if not keep.all():
        offs = np.concatenate([[0], np.cumsum(keep)])[offs]
        flat = flat.filter(pa.array(keep))
    return offs, flat


def coded(flat: pa.Array) -> tuple[np.ndarray, pa.Array]:
    """Index of each word among the distinct ones, and these."""
    d = flat.dictionary_encode()
    return d.indices.to_numpy(zero_copy_only=False).astype(np.int64), d.dictionary


def hashes(values: pa.Array) -> np.ndarray:
    """64-bit hashes of strings, the same on every machine."""
    if not len(values):
        return np.zeros(0, np.uint64)
    return pd.util.hash_array(values.to_numpy(zero_copy_only=False).astype(object), categorize=False).astype(np.uint64)


def mixed(x: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash."""
    x = x.astype(np.uint64, copy=True)
    with np.errstate(over="ignore"):
        x ^= x >> np.uint64(30)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(31)
    return x


def sums(values: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """Sum of each row's values."""
    total = np.concatenate([np.zeros(1, np.int64 if values.dtype.kind in "iub" else np.float64), np.cumsum(values, dtype=np.int64 if values.dtype.kind in "iub" else np.float64)])
    return total[offs[1:]] - total[offs[:-1]]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
