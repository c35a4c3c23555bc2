"""Queries of the evaluators, variants and baselines on the workloads, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import workloads
from ..baselines import boolean_product, min_plus_cycle
from ..sources.relations import relation, text_for

Entry = tuple[Callable[[SparkSession, str], DataFrame], str]


def entry(name: str, head: str | None = None, engine: str = "guided", stats: str = "none", **options) -> Entry:
    return (lambda spark, d: workloads.run(spark, d, name, engine, head, stats, **options)), workloads.sql(name, head)


def counted(e: Entry) -> Entry:
    """The number of answers. It counts the distinct answers that were made; sums over leaves would count some twice."""
    return (lambda spark, d: e[0](spark, d).agg(F.count(F.lit(1)).alias("n_answers"))), f"SELECT count(*) AS n_answers FROM ({e[1]})"


def registry() -> dict[str, Entry]:
    out: dict[str, Entry] = {
        "w01_bool": entry("w01", ""),
        "w01_head_x": entry("w01", "x"),
        "w01_head_xy": entry("w01", "x, y"),
        "w01_full_count": counted(entry("w01")),
        "w02_full": entry("w02"),
        "w02_keys_full": entry("w02", stats="keys"),
        "w02_by_nation": (lambda s, d: workloads.run(s, d, "w02").groupBy("nationkey").agg(F.count(F.lit(1)).alias("n"), F.min("orderkey").alias("first_order"), F.max("orderkey").alias("last_order")), f"SELECT nationkey, count(*) AS n, min(orderkey) AS first_order, max(orderkey) AS last_order FROM ({workloads.sql('w02')}) GROUP BY nationkey"),
        "w05_head_u": entry("w05", "u1"),
        "w05b_head_u": entry("w05b", "u1"),
        "w06_pairs": (lambda s, d: workloads.run(s, d, "w06").filter("d1 < d2 AND l1 < l2").select("d1", "d2").distinct(), f"SELECT DISTINCT d1, d2 FROM ({workloads.sql('w06')}) WHERE d1 < d2 AND l1 < l2"),
        "w10_mid": entry("w10", "orderkey"),
        "w10_ends": entry("w10", "custkey, partkey"),
        "w12_head_u": entry("w12", "u1"),
        "w13_head_s": entry("w13", "s"),
        "w15_head_v": entry("w15", "v1"),
    }
    for w in ("w03", "w04", "w05", "w06", "w07", "w08", "w09", "w10", "w11", "w14", "w16", "w17"):
        out[f"{w}_full"] = entry(w)
    for k in (2, 4, 8, 16):
        out[f"w18_fanout_{k}"] = entry("w05", "u1, k1", fanout=k)
        out[f"w18_w01_fanout_{k}"] = entry("w01", "x, y", fanout=k)
        out[f"w18_w06_fanout_{k}"] = entry("w06", "d1", fanout=k)
    for s in ("none", "card", "keys", "measured"):
        out[f"w19_{s}"] = entry("w02", stats=s)
        out[f"w19_w08_{s}"] = entry("w08", stats=s)
    out["w20_bool"], out["w20_x"], out["w20_xy"], out["w20_xz_count"] = entry("w05", ""), entry("w05", "u1"), entry("w05", "u1, k1"), counted(entry("w01", "x, z"))
    for v, o in {"prereduce": {"prereduce": True}, "lexicographic": {"tie_break": "lexicographic"}, "smallest_union": {"tie_break": "smallest_union"}, "cheapest_join": {"tie_break": "cheapest_join"}, "per_leaf": {"group_leaves": False}, "no_heavy_reduce": {"heavy_reduce": False}, "verify": {"verify": True}, "nosplit": {"split": False}, "fixed_orientation": {"orientation": "names"}}.items():
        out[f"variant_{v}"] = entry("w02", **o)
    # a branch for each light part, as analysed
    out["variant_separate"] = entry("w04", light_mode="separate", fanout=4)
    out["variant_separate_w01"] = entry("w01", "x, y", light_mode="separate", fanout=2)
    for w, head in (("w01", "x, y"), ("w02", None), ("w03", None), ("w05", None), ("w06", None)):
        for kind, engine in (("pairwise", "pairwise"), ("tree1", "tree:0"), ("trivial", "trivial"), ("dual", "dual"), ("uniform", "uniform")):
            if kind != "uniform" or w in ("w02", "w03"):  # on skewed inputs uniformizing makes very many small jobs
                out[f"base_{kind}_{w}"] = entry(w, head, engine)
        if w != "w03":
            out[f"base_tree2_{w}"] = entry(w, head, "tree:1")
    out["count_w02"], out["count_w05"] = counted(entry("w02")), counted(entry("w05"))
    us, su = text_for("order_supp", True), text_for("supp_nation", True)
    out["base_boolean_product"] = (
        lambda s, d: boolean_product(relation(s, d, "order_supp"), relation(s, d, "supp_nation"), "suppkey"),
        f"SELECT orderkey, nationkey, count(*) AS n_common FROM ({us}) a JOIN ({su}) b USING (suppkey) GROUP BY orderkey, nationkey",
    )

    def least(s, d):
        answers = workloads.run(s, d, "w02")
        cents = s.read.parquet(f"{d}/orders.parquet").select(F.col("o_custkey").alias("custkey"), F.col("o_orderkey").alias("orderkey"), F.round(F.col("o_totalprice") * 100).cast("bigint").alias("weight"))
        lines = s.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_orderkey").alias("orderkey"), F.col("l_suppkey").alias("suppkey"), F.col("l_quantity").cast("bigint").alias("weight"))
        return min_plus_cycle(answers, {"a": cents, "b": lines}, ["nationkey"])

    out["agg_minplus_4cycle"] = (least, f"""
        WITH r AS ({workloads.sql('w02')}),
        a AS (SELECT o_custkey AS custkey, o_orderkey AS orderkey, min(CAST(round(o_totalprice * 100) AS BIGINT)) AS x FROM orders GROUP BY ALL),
        b AS (SELECT l_orderkey AS orderkey, l_suppkey AS suppkey, min(CAST(l_quantity AS BIGINT)) AS y FROM lineitem GROUP BY ALL)
        SELECT nationkey, min(x + y) AS least FROM r JOIN a USING (custkey, orderkey) JOIN b USING (orderkey, suppkey) GROUP BY nationkey""")  # fmt: skip
    return out
