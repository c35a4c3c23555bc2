"""Event streams as edge sources: windows, late data, degree constraints checked batch by batch, and deltas of a cyclic query."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..guided import guided_evaluate
from ..instance import Instance, semijoin
from ..materialize import keep, scratch
from ..query import ConjunctiveQuery, parse_rule
from ..sources.relations import relation
from ..statistics import degrees, max_degree


def with_time(events: DataFrame) -> DataFrame:
    """ts as an instant, which watermarks need."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def tumbling(events: DataFrame, size: str = "1 hour") -> DataFrame:
    return with_time(events).groupBy(F.window("ts", size).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def sliding(events: DataFrame, size: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    """Distinct edges of each sliding window would need state for each edge; these are its events."""
    own = with_time(events).withWatermark("ts", size).groupBy(F.window("ts", size, step).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return own.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    own = with_time(events).withWatermark("ts", gap).groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return own.select(F.col("w.start").cast("timestamp_ntz").alias("start"), F.col("w.end").cast("timestamp_ntz").alias("end"), "user_id", "n")


def distinct_edges(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each (user, key) once, for as long as the watermark remembers it."""
    own = with_time(events).withColumn("k", F.get_json_object("props", "$.k").cast("bigint")).withWatermark("ts", late)
    return own.dropDuplicatesWithinWatermark(["user_id", "k"]).select("user_id", "k")


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """What a streaming query gives for all that its source holds: run to the end, its rows written to the shared folder."""
    spark, path, mark = stream.sparkSession, scratch(stream.sparkSession), scratch(stream.sparkSession)

    def add(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")  # a batch that comes again replaces itself

    stream.writeStream.outputMode(mode).foreachBatch(add).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(path).select(*stream.columns)


def late_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tumbling counts of a stream whose last file holds the first day's events again, a whole table later: the watermark leaves them out.

    An event far ahead, in a file before, closes every window; its own stays open. Lateness is told by the watermark of the batch before.
    """
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "event_type")
    first = events.agg(F.min("ts").alias("a"), F.max("ts").alias("b")).first()
    early = F.col("ts") < F.lit(first["a"]).cast("timestamp_ntz") + F.expr("INTERVAL 1 DAY")
    ahead = spark.createDataFrame([(-1, "last")], "event_id bigint, event_type string").withColumn("ts", F.lit(first["b"]).cast("timestamp_ntz") + F.expr("INTERVAL 3 DAY")).select(events.columns)
    path = scratch(spark)
    for part in (events, ahead, events.filter(early)):
        part.coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(path)
    own = with_time(stream).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return drained(own.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n"))


def within_an_hour(events: DataFrame) -> DataFrame:
    """Pairs of a user's events at most an hour apart: an equi-join on user and hour buckets, each event in its own and the next bucket, then the range."""
    e = events.select("event_id", "user_id", "ts", F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / 3600).alias("h"))
    a = e.select(F.col("event_id").alias("first"), "user_id", F.col("ts").alias("t1"), F.explode(F.array("h", F.col("h") + 1)).alias("h"))
    b = e.select(F.col("event_id").alias("second"), "user_id", F.col("ts").alias("t2"), "h")
    return a.join(b, ["user_id", "h"]).filter("t2 > t1 AND t2 <= t1 + INTERVAL 1 HOUR").select("first", "second")


def file_stream(spark: SparkSession, sf_dir: str, table: str = "events") -> DataFrame:
    """A table as a stream: a directory or a file, whatever the batch reader lists."""
    source = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    path = scratch(spark)
    source.write.parquet(path)
    return spark.readStream.schema(source.schema).parquet(path)


def streamed_degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct keys of each user, kept by a stream of events: each micro-batch adds its new edges to a stored set."""
    own = file_stream(spark, sf_dir).select("user_id", F.get_json_object("props", "$.k").cast("bigint").alias("k")).dropna()
    return degrees(drained(own).distinct(), ["k"], ["user_id"])


def checked_batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A declared degree constraint, measured again after each of three micro-batches: (batch, max_degree, holds).

    Stored edges are added to by each batch; only the users in a batch are measured, as no other degree can have changed.
    """
    edges = relation(spark, sf_dir, "user_key_buy")
    limit, store, mark = 5, scratch(spark), scratch(spark)
    source = scratch(spark)
    for part in range(3):
        edges.filter(F.pmod("k", F.lit(3)) == part).coalesce(1).write.mode("append").parquet(source)
    found: dict[int, int] = {}

    def check(batch: DataFrame, number: int) -> None:
        batch.distinct().write.mode("overwrite").parquet(f"{store}/batch={number}")
        every = spark.read.schema(edges.schema).parquet(*[f"{store}/batch={i}" for i in range(number + 1)])
        touched = semijoin(every, batch.select("user_id").distinct())
        found[number] = max_degree(touched.distinct(), ["k"], ["user_id"])

    spark.readStream.schema(edges.schema).option("maxFilesPerTrigger", 1).parquet(source).writeStream.foreachBatch(check).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return spark.createDataFrame([(i, d, d <= limit) for i, d in sorted(found.items())], "batch int, max_degree bigint, holds boolean")


def delta_answers(q: ConjunctiveQuery, name: str, old: DataFrame | None, new: DataFrame) -> DataFrame:
    """Answers that new rows of one relation add: for each atom over it, new rows there, old ones in the atoms before, all of them in those after."""
    every = new if old is None else keep(old.union(new).distinct())
    mine = [i for i, a in enumerate(q.atoms) if a.relation == name]
    out = None
    for turn in mine if old is not None else mine[:1]:
        pairs = [(a, new if i == turn or old is None else old if i < turn else every) for i, a in enumerate(q.atoms)]
        got = guided_evaluate(q, Instance.of_atoms(pairs))
        out = got if out is None else out.union(got)
    return out.distinct()


def delta_cycle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 4-cycle of users and keys, kept by a stream of edges in two micro-batches: each adds the answers of its delta, found by the guided evaluator."""
    edges = relation(spark, sf_dir, "user_key_buy")
    q = parse_rule("q(u1, k1) :- e(u1, k1), e(u2, k1), e(u2, k2), e(u1, k2)")
    source, store, answers, mark = (scratch(spark) for _ in range(4))
    for part in range(2):
        edges.filter(F.pmod(F.xxhash64("user_id", "k"), F.lit(8)) == 7 if part else F.pmod(F.xxhash64("user_id", "k"), F.lit(8)) < 7).coalesce(1).write.mode("append").parquet(source)

    def add(batch: DataFrame, number: int) -> None:
        back = [f"{store}/batch={i}" for i in range(number)]
        old = spark.read.schema(edges.schema).parquet(*back) if back else None
        batch.distinct().write.mode("overwrite").parquet(f"{store}/batch={number}")
        new = spark.read.schema(edges.schema).parquet(f"{store}/batch={number}")
        if old is not None:
            new = keep(new.exceptAll(old))
        delta_answers(q, "e", old, new).write.mode("overwrite").parquet(f"{answers}/batch={number}")

    spark.readStream.schema(edges.schema).option("maxFilesPerTrigger", 1).parquet(source).writeStream.foreachBatch(add).option("checkpointLocation", mark).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("k1 bigint, u1 bigint").parquet(answers).select("u1", "k1").distinct()
