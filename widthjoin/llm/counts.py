"""Token counts as delta-maintained rollups.

A batch of changes (insert, delete, revise) becomes signed rows of a ledger, one
a document and tokenizer version, and signed sums by source, language and
version. Totals are sums of the committed batches' sums; nothing is recounted.
A batch is committed by its writer's success mark, last of all, under its batch
id, so a batch that comes twice, or again after a failure, counts once. compact()
replaces the ledgers of committed batches by their net rows.

Null text: empty, no tokens. Null source or language: groups of their own. An
insert of a live id, like a revision, withdraws the old counts first; a delete of
an unknown id has no effect. Several rows of one id in a batch: the greatest by
(operation, counts, source, language) holds, deletes being least. Rows without
an id are ignored for deletes and revisions, and count as documents of their own
when inserted. Unknown operations are an error. An empty batch commits nothing
but its id.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import tokens
from .common import delete, pick, pieces, save

OPERATIONS = ("delete", "insert", "revise")
LEDGER = "doc_id long, source string, lang string, version string, sign int, n_tokens long, bucket int"
#: The ledger lies in so many folders, by the hash of ids: a batch reads those of its ids alone.
BUCKETS = 64
DELTAS = "source string, lang string, version string, n_docs long, n_tokens long"


def count_tokens(batches: Iterator[pa.RecordBatch], versions: dict[str, str]) -> Iterator[pa.RecordBatch]:
    for b in pieces(batches):
        text = b.column(b.schema.get_field_index("text")).to_pylist()
        own = [pa.array([len(tokens.encode(path, t)) for t in text], pa.int64()) for path in versions.values()]
        yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index(c)) for c in ("op", "doc_id", "source", "lang")] + own, names=["op", "doc_id", "source", "lang", *(f"n{i}" for i in range(len(own)))])


class Rollup:
    """The store in a folder that all executors share. versions: tokenizer version -> path of its vocabulary."""

    def __init__(self, spark: SparkSession, path: str, versions: dict[str, str]):
        self.spark, self.path, self.versions = spark, path.rstrip("/"), versions

    def _exists(self, path: str) -> bool:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(p)

    def committed(self) -> list[str]:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/deltas")
        fs = p.getFileSystem(self.spark._jsc.hadoopConfiguration())
        names = [x.getPath().getName() for x in fs.listStatus(p)] if fs.exists(p) else []
        return sorted(n for n in names if self._exists(f"{self.path}/deltas/{n}/_SUCCESS"))

    def _read(self, kind: str, schema: str) -> DataFrame:
        paths = [f"{self.path}/{kind}/{b}" for b in self.committed()]
        return self.spark.read.schema(schema).parquet(*paths) if paths else self.spark.createDataFrame([], schema)

    def _bases(self) -> list[str]:
        p = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/base")
        fs = p.getFileSystem(self.spark._jsc.hadoopConfiguration())
        names = sorted(x.getPath().getName() for x in fs.listStatus(p)) if fs.exists(p) else []
        return [n for n in names if self._exists(f"{self.path}/base/{n}/batches/_SUCCESS")]

    def _ledger(self) -> DataFrame:
        """Rows of the last compaction and of the batches that it does not hold."""
        bases, batches, paths = self._bases(), self.committed(), []
        if bases:
            held = {r["batch"] for r in self.spark.read.schema("batch string").parquet(f"{self.path}/base/{bases[-1]}/batches").collect()}  # names of batches
            batches, paths = [b for b in batches if b not in held], [f"{self.path}/base/{bases[-1]}/ledger"]
        out = None
        for p in [*paths, *(f"{self.path}/ledger/{b}" for b in batches)]:
            own = self.spark.read.schema(LEDGER).parquet(p)
            out = own if out is None else out.unionByName(own)
        return self.spark.createDataFrame([], LEDGER) if out is None else out

    def live(self, buckets: list[int] | None = None) -> DataFrame:
        """Documents that count now, with their counts: net sums of the ledger, or of some of its buckets."""
        r = self._ledger()
        if buckets is not None:
            r = r.filter(F.col("bucket").isin(buckets))
        return r.groupBy("doc_id", "source", "lang", "version").agg(F.sum("sign").alias("net"), F.sum(F.col("sign") * F.col("n_tokens")).alias("n_tokens")).filter("net > 0")

    def compact(self) -> None:
        """Write the ledger's net rows as one, then name the batches it holds: a compaction counts from that mark on. Spent ledgers are deleted after it."""
        batches, old = self.committed(), self._bases()
        name = f"{int(old[-1]) + 1 if old else 0:08d}"
        net = self._ledger().groupBy("doc_id", "source", "lang", "version", "bucket", "n_tokens").agg(F.sum("sign").cast("int").alias("sign")).filter("sign <> 0").select(*[x.split()[0] for x in LEDGER.split(", ")])
        self._write(net, f"{self.path}/base/{name}/ledger")
        self.spark.createDataFrame([(b,) for b in batches], "batch string").coalesce(1).write.mode("overwrite").parquet(f"{self.path}/base/{name}/batches")
        for b in batches:
            delete(self.spark, f"{self.path}/ledger/{b}")
        for b in old:
            delete(self.spark, f"{self.path}/base/{b}")

    @staticmethod
    def _write(rows: DataFrame, path: str) -> None:
        """Rows of one bucket come together before they are written, so that a bucket is a few files."""
        rows.repartition("bucket", F.pmod(F.xxhash64("doc_id", "n_tokens", "source", "lang"), F.lit(4))).write.mode("overwrite").partitionBy("bucket").parquet(path)

    def apply(self, batch: str, changes: DataFrame) -> bool:
        """Commit a batch of (op, doc_id, source, lang, text). False: it was committed before."""
        if self._exists(f"{self.path}/deltas/{batch}/_SUCCESS"):
            return False
        c = pick(changes, op="string", doc_id="long", source="string", lang="string", text="string")
        bad = F.raise_error(F.concat(F.lit("unknown operation: "), F.coalesce("op", F.lit("null"))))
        c = c.withColumn("op", F.when(F.col("op").isin(*OPERATIONS), F.col("op")).otherwise(bad))
        paths = list(self.versions)
        gone = c.filter("op = 'delete'").select("op", "doc_id", "source", "lang", *[F.lit(None).cast("long").alias(f"n{i}") for i in range(len(paths))])
        schema = "op string, doc_id long, source string, lang string, " + ", ".join(f"n{i} long" for i in range(len(paths)))
        versions = self.versions
        own = save(c.filter("op <> 'delete'").mapInArrow(lambda it: count_tokens(it, versions), schema).union(gone))  # each text is encoded once
        fields = ["op", *(f"n{i}" for i in range(len(paths))), "source", "lang"]
        with_id = own.filter("doc_id IS NOT NULL").groupBy("doc_id").agg(F.max(F.struct(*fields)).alias("x")).select("doc_id", "x.*")
        without = own.filter("doc_id IS NULL AND op = 'insert'").select("doc_id", *fields)
        mine = with_id.unionByName(without)
        plus = mine.filter("op <> 'delete'").select("doc_id", "source", "lang", F.explode(F.array(*[F.struct(F.lit(v).alias("version"), F.col(f"n{i}").alias("n_tokens")) for i, v in enumerate(paths)])).alias("x")).select("doc_id", "source", "lang", "x.version", F.lit(1).alias("sign"), "x.n_tokens")
        bucket = F.pmod(F.xxhash64("doc_id"), F.lit(BUCKETS)).cast("int")
        ledger = plus
        if self.committed():
            ids = own.filter("doc_id IS NOT NULL").select(F.col("doc_id").alias("changed")).distinct()
            touched = [r["b"] for r in own.filter("doc_id IS NOT NULL").select(bucket.alias("b")).distinct().collect()]  # at most BUCKETS
            old = self.live(touched).filter(F.col("version").isin(paths)).join(ids, F.col("doc_id") == F.col("changed"), "left_semi")
            ledger = plus.union(old.select("doc_id", "source", "lang", "version", F.lit(-1).alias("sign"), "n_tokens"))
        self._write(ledger.withColumn("bucket", bucket), f"{self.path}/ledger/{batch}")
        rows = self.spark.read.schema(LEDGER).parquet(f"{self.path}/ledger/{batch}")
        sums = rows.groupBy("source", "lang", "version").agg(F.sum("sign").cast("long").alias("n_docs"), F.sum(F.col("sign") * F.col("n_tokens")).alias("n_tokens"))
        sums.coalesce(1).write.mode("overwrite").parquet(f"{self.path}/deltas/{batch}")
        return True

    def totals(self) -> DataFrame:
        d = self._read("deltas", DELTAS).groupBy("source", "lang", "version").agg(F.sum("n_docs").alias("n_docs"), F.sum("n_tokens").alias("n_tokens"))
        return d.filter("n_docs <> 0 OR n_tokens <> 0")
