"""The registered queries of this package, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pyspark.sql import functions as F

from . import archives, counts, decontaminate, katz, line_dedup, neardup, packing, quality, secrets, tokens, toxicity
from .common import pick, scratch, table


def op1_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality(table(spark, sf_dir, "documents")).drop("cleaned")


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four batches: all documents; revisions (upper case) of those with id % 10 = 3; deletes of id % 10 = 7; the revisions again, which changes nothing."""
    docs = pick(table(spark, sf_dir, "documents"), doc_id="long", source="string", lang="string", text="string")
    rollup = counts.Rollup(spark, scratch(spark), {"byte_bpe_50k": tokens.vocabulary("byte_bpe_50k.json"), "byte_bpe_multi_50k": tokens.vocabulary("byte_bpe_multi_50k.tiktoken")})
    revised = docs.filter("doc_id % 10 = 3").withColumn("op", F.lit("revise")).withColumn("text", F.upper("text"))
    rollup.apply("b1", docs.withColumn("op", F.lit("insert")))
    rollup.apply("b2", revised)
    rollup.apply("b3", docs.filter("doc_id % 10 = 7").drop("text").withColumn("op", F.lit("delete")))
    rollup.apply("b2", revised)
    return rollup.totals()


def op7_near_dup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"), 3, 85, 100)


def fold(doc_id: str, n: int):
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(n))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.train_on(docs, labels, where=lambda c: fold(c, 5) != 0)
    return toxicity.scored(docs, model, spans=True).select("doc_id", (fold("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "spans")


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return archives.round_trip(table(spark, sf_dir, "pages"))


def op2_katz(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = pick(table(spark, sf_dir, "documents"), doc_id="long", text="string")
    return katz.score_texts(docs.withColumn("held_out", fold("doc_id", 7) == 2))


def op3_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.packed(table(spark, sf_dir, "documents"), tokens.vocabulary("byte_bpe_50k.json")).drop("used")


def op4_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), min_cosine=decontaminate.MIN_COSINE)


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = pick(table(spark, sf_dir, "documents"), doc_id="long", text="string", source="string")
    return line_dedup.drop_boilerplate(docs).select("doc_id", "text", "n_lines", "n_dropped")


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secrets_of(pick(table(spark, sf_dir, "documents"), doc_id="long", text="string"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_quality, op2_katz, op3_packing, op4_decontamination, op5_line_dedup, op6_token_counts, op7_near_dup, op8_toxicity, op9_warc, op10_secret_scan)}


def oracle_sql() -> dict[str, str]:
    return {"op1_quality": quality.ORACLE_SQL, "op5_line_dedup": line_dedup.ORACLE_SQL, "op7_near_dup": neardup.ORACLE_SQL, "op9_warc": archives.ORACLE_SQL}
