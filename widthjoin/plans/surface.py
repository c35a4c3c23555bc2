"""Queries of the single operators, sources, sinks, functions, windows and aggregates around the evaluators, each with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .. import workloads
from ..baselines import uniformity_gap
from ..functions import degree_profile, dense_rank, register, running_total, sql
from ..instance import Instance, natural_join, project, select_eq, semijoin
from ..materialize import keep, scratch
from ..partition import equal_degree_parts, heavy_light
from ..query import parse_rule
from ..sources import bind_atom, relation, star_of
from ..sources.relations import text_for
from ..statistics import Statistics, check_statistics, collect_statistics, degree_at, degrees, max_degree
from ..streaming import windows

Entry = tuple[Callable[[SparkSession, str], DataFrame], str]


def rows_():
    return F.count(F.lit(1))


def t(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


def one(s: SparkSession, kind: str, *values) -> DataFrame:
    return s.createDataFrame([values], kind)


def q(name: str) -> str:
    return f"({text_for(name, True)})"


def by_format(s, d):
    """A CSV, a JSON and an ORC copy of one relation, written and read as atom sources."""
    own = relation(s, d, "supp_nation")
    out = None
    for kind in ("csv", "json", "orc"):
        path = scratch(s)
        own.write.format(kind).save(path)
        back = s.read.schema(own.schema).format(kind).load(path).withColumn("kind", F.lit(kind))
        out = back if out is None else out.unionByName(back)
    return out.groupBy("kind").agg(rows_().alias("n"), F.sum("suppkey").alias("s"))


def from_view(s, d):
    t(s, d, "supplier").createOrReplaceTempView("supplier_atom_source")
    return s.table("supplier_atom_source").select(F.col("s_suppkey").alias("suppkey"), F.col("s_nationkey").cast("bigint").alias("nationkey")).distinct()


def sink(s, d):
    path = scratch(s)
    relation(s, d, "supp_nation").write.partitionBy("nationkey").parquet(path)
    return s.read.parquet(path).select("suppkey", F.col("nationkey").cast("bigint").alias("nationkey"))


def instance(s, d) -> Instance:
    rule = parse_rule("q(custkey) :- cust_order(custkey, orderkey), order_supp(orderkey, suppkey), supp_nation(suppkey, nationkey), nation_cust(nationkey, custkey)")
    return Instance.load(rule, {a.relation: relation(s, d, a.relation) for a in rule.atoms}, materialize=False)


def measured(s, d):
    f = frozenset
    terms = [(f(["suppkey"]), f(["orderkey"]), f(["orderkey", "suppkey"])), (f(["orderkey"]), f(["custkey"]), f(["custkey", "orderkey"])), (f(["custkey"]), f(["nationkey"]), f(["custkey", "nationkey"]))]
    return collect_statistics(instance(s, d), terms).frame(s).select(F.array_join("y", ",").alias("y"), F.array_join("x", ",").alias("x"), "max_degree")


def violated(s, d):
    bad = check_statistics(instance(s, d), Statistics.declare(("suppkey", "orderkey", 1, ("orderkey", "suppkey")), ("custkey", "orderkey", 1, ("custkey", "orderkey"))))
    return s.createDataFrame([(",".join(sorted(c.y)), m) for c, m in bad], "y string, measured bigint")


def asof(s, d):
    """For each refund-like event the user's latest purchase at or before it."""
    e = t(s, d, "events")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    return e.withColumn("last_buy", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)).filter("event_type <> 'purchase'").select("event_id", "last_buy")


def registry() -> dict[str, Entry]:
    r = relation
    li = "lineitem"
    out: dict[str, Entry] = {
        "op_project": (lambda s, d: project(r(s, d, "order_supp"), ["suppkey"]), "SELECT DISTINCT l_suppkey AS suppkey FROM lineitem"),
        "op_select": (lambda s, d: select_eq(r(s, d, "order_supp"), {"suppkey": 3}), f"SELECT * FROM {q('order_supp')} WHERE suppkey = 3"),
        "op_signature_unique": (lambda s, d: Instance.load(parse_rule("q(p) :- part_supp_r(p, s), part_supp_a(p, s)"), {k: r(s, d, k) for k in ("part_supp_r", "part_supp_a")}, False).relations[frozenset("ps")], f"SELECT partkey AS p, suppkey AS s FROM {q('part_supp_ra')}"),
        "op_augment": (lambda s, d: augmented(s, d), f"SELECT orderkey, suppkey FROM {q('order_supp')} WHERE suppkey <= 5"),
        "deg_at_point": (lambda s, d: one(s, "degree bigint", degree_at(r(s, d, "order_supp"), ["orderkey"], {"suppkey": 1})), f"SELECT count(DISTINCT orderkey) AS degree FROM {q('order_supp')} WHERE suppkey = 1"),
        "deg_max_order_supp": (lambda s, d: one(s, "degree bigint", max_degree(r(s, d, "order_supp"), ["orderkey"], ["suppkey"])), f"SELECT max(n) AS degree FROM (SELECT count(*) AS n FROM {q('order_supp')} GROUP BY suppkey)"),
        "deg_max_doc_line": (lambda s, d: one(s, "degree bigint", max_degree(r(s, d, "doc_line"), ["doc_id"], ["line"])), f"SELECT max(n) AS degree FROM (SELECT count(*) AS n FROM {q('doc_line')} GROUP BY line)"),
        "deg_hist_user_key": (lambda s, d: degrees(r(s, d, "user_key"), ["user_id"], ["k"]), f"SELECT k, count(*) AS degree FROM {q('user_key')} GROUP BY k"),
        "inst_size": (lambda s, d: one(s, "n bigint", instance(s, d).size), "SELECT " + " + ".join(f"(SELECT count(*) FROM {q(x)})" for x in ("cust_order", "order_supp", "supp_nation", "nation_cust")) + " AS n"),
        "stats_collect_w02": (measured, f"SELECT 'suppkey' AS y, 'orderkey' AS x, max(n) AS max_degree FROM (SELECT count(*) n FROM {q('order_supp')} GROUP BY orderkey) UNION ALL SELECT 'orderkey', 'custkey', max(n) FROM (SELECT count(*) n FROM {q('cust_order')} GROUP BY custkey) UNION ALL SELECT 'custkey', 'nationkey', max(n) FROM (SELECT count(*) n FROM {q('nation_cust')} GROUP BY nationkey)"),
        "stats_check": (violated, f"SELECT 'suppkey' AS y, max(n) AS measured FROM (SELECT count(*) n FROM {q('order_supp')} GROUP BY orderkey)"),
        "split_heavy_keys": (lambda s, d: heavy_light(r(s, d, "doc_line"), ["line"], 3)[0], f"SELECT line FROM {q('doc_line')} GROUP BY line HAVING count(*) > 3"),
        "split_light_rows": (lambda s, d: heavy_light(r(s, d, "doc_line"), ["line"], 3)[1], f"SELECT doc_id, line FROM {q('doc_line')} WHERE line NOT IN (SELECT line FROM {q('doc_line')} GROUP BY line HAVING count(*) > 3)"),
        "win_equal_degree": (lambda s, d: equal_degree_parts(r(s, d, "order_supp"), ["suppkey"], 50).groupBy("suppkey", F.col("__part").alias("part")).agg(rows_().alias("n")), f"SELECT suppkey, CAST((rn - 1) // 50 AS INT) AS part, count(*) AS n FROM (SELECT suppkey, row_number() OVER (PARTITION BY suppkey ORDER BY orderkey) AS rn FROM {q('order_supp')}) GROUP BY ALL"),
        "uniformity_doc_line": (lambda s, d: uniformity_gap(r(s, d, "doc_line"), ["line"]).select("n_rows", "n_keys", "max_degree"), f"SELECT CAST(sum(n) AS BIGINT) AS n_rows, count(*) AS n_keys, max(n) AS max_degree FROM (SELECT count(*) AS n FROM {q('doc_line')} GROUP BY line)"),
        "src_parquet": (lambda s, d: t(s, d, "orders").filter("o_orderstatus = 'F'").select("o_orderkey", "o_custkey"), "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'F'"),
        "src_view": (from_view, q("supp_nation")[1:-1]),
        "src_formats": (by_format, f"SELECT k AS kind, count(*) AS n, CAST(sum(suppkey) AS BIGINT) AS s FROM {q('supp_nation')}, (SELECT unnest(['csv', 'json', 'orc']) AS k) GROUP BY k"),
        "src_events_edges": (lambda s, d: r(s, d, "user_key"), q("user_key")[1:-1]),
        "src_page_links": (lambda s, d: r(s, d, "page_link"), q("page_link")[1:-1]),
        "src_doc_lines": (lambda s, d: r(s, d, "doc_line"), q("doc_line")[1:-1]),
        "src_vec_bits": (lambda s, d: r(s, d, "vec_bit"), q("vec_bit")[1:-1]),
        "sink_roundtrip": (sink, q("supp_nation")[1:-1]),
        "filter_range": (lambda s, d: t(s, d, li).filter("l_shipdate >= timestamp_ntz'1995-01-01' AND l_shipdate < timestamp_ntz'1996-01-01'").agg(rows_().alias("n")), "SELECT count(*) AS n FROM lineitem WHERE l_shipdate >= '1995-01-01' AND l_shipdate < '1996-01-01'"),
        "filter_in": (lambda s, d: t(s, d, "part").filter(F.col("p_size").isin(1, 2, 3) & F.col("p_brand").isNotNull()).select("p_partkey", "p_size"), "SELECT p_partkey, p_size FROM part WHERE p_size IN (1, 2, 3) AND p_brand IS NOT NULL"),
        "join_inner": (lambda s, d: natural_join(r(s, d, "cust_order"), r(s, d, "nation_cust")), f"SELECT custkey, nationkey, orderkey FROM {q('cust_order')} JOIN {q('nation_cust')} USING (custkey)"),
        "join_cross": (lambda s, d: natural_join(r(s, d, "region_key"), r(s, d, "supp_nation")), f"SELECT * FROM {q('region_key')}, {q('supp_nation')}"),
        "join_semi": (lambda s, d: semijoin(r(s, d, "cust_order"), r(s, d, "nation_cust").filter("nationkey < 5")), f"SELECT * FROM {q('cust_order')} WHERE custkey IN (SELECT custkey FROM {q('nation_cust')} WHERE nationkey < 5)"),
        "join_anti": (lambda s, d: r(s, d, "nation_cust").join(r(s, d, "cust_order"), "custkey", "left_anti").select("nationkey", "custkey"), f"SELECT * FROM {q('nation_cust')} WHERE custkey NOT IN (SELECT custkey FROM {q('cust_order')})"),
        "join_broadcast": (lambda s, d: r(s, d, "order_supp").join(F.broadcast(degrees(r(s, d, "order_supp"), ["orderkey"], ["suppkey"]).filter("degree > 585").select("suppkey")), "suppkey").select("orderkey", "suppkey"), f"SELECT orderkey, suppkey FROM {q('order_supp')} WHERE suppkey IN (SELECT suppkey FROM {q('order_supp')} GROUP BY suppkey HAVING count(*) > 585)"),
        "join_hints": (lambda s, d: r(s, d, "cust_order").hint("merge").join(r(s, d, "order_part").hint("shuffle_hash"), "orderkey").groupBy("custkey").agg(rows_().alias("n")), f"SELECT custkey, count(*) AS n FROM {q('cust_order')} JOIN {q('order_part')} USING (orderkey) GROUP BY custkey"),
        "join_theta": (lambda s, d: r(s, d, "user_key_buy").select(F.col("user_id").alias("u1"), "k").join(r(s, d, "user_key_buy").select(F.col("user_id").alias("u2"), "k"), "k").filter("u1 < u2").groupBy("u1", "u2").agg(rows_().alias("n")), f"SELECT a.user_id AS u1, b.user_id AS u2, count(*) AS n FROM {q('user_key_buy')} a JOIN {q('user_key_buy')} b ON a.k = b.k AND a.user_id < b.user_id GROUP BY ALL"),
        "join_interval": (lambda s, d: windows.within_an_hour(t(s, d, "events")), "SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"),
        "join_asof": (asof, "SELECT event_id, last_buy FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS last_buy FROM events) WHERE event_type <> 'purchase'"),
        "join_full": (lambda s, d: degrees(r(s, d, "part_supp_r"), ["partkey"], ["suppkey"]).withColumnRenamed("degree", "dr").join(degrees(r(s, d, "supp_order_a"), ["orderkey"], ["suppkey"]).withColumnRenamed("degree", "da"), "suppkey", "full"), f"SELECT coalesce(a.suppkey, b.suppkey) AS suppkey, dr, da FROM (SELECT suppkey, count(*) AS dr FROM {q('part_supp_r')} GROUP BY suppkey) a FULL JOIN (SELECT suppkey, count(*) AS da FROM {q('supp_order_a')} GROUP BY suppkey) b ON a.suppkey = b.suppkey"),
        "agg_grouping_sets": (lambda s, d: s.sql("SELECT l_orderkey, l_suppkey, count(*) AS n FROM {l} GROUP BY GROUPING SETS ((l_orderkey), (l_suppkey), ())", l=t(s, d, li)), "SELECT l_orderkey, l_suppkey, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_orderkey), (l_suppkey), ())"),
        "agg_cube": (lambda s, d: t(s, d, li).cube("l_returnflag", "l_linestatus").agg(rows_().alias("n")), "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
        "agg_rollup": (lambda s, d: t(s, d, li).rollup("l_suppkey", "l_returnflag").agg(F.countDistinct("l_partkey").alias("n")), "SELECT l_suppkey, l_returnflag, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY ROLLUP (l_suppkey, l_returnflag)"),
        "agg_bool_or": (lambda s, d: t(s, d, "orders").groupBy("o_custkey").agg(F.bool_or(F.col("o_orderstatus") == "F").alias("some")), "SELECT o_custkey, bool_or(o_orderstatus = 'F') AS some FROM orders GROUP BY o_custkey"),
        "win_degree": (lambda s, d: r(s, d, "order_supp").withColumn("degree", rows_().over(W.partitionBy("orderkey"))), f"SELECT orderkey, suppkey, count(*) OVER (PARTITION BY orderkey) AS degree FROM {q('order_supp')}"),
        "win_rank_degree": (lambda s, d: dense_rank(degrees(r(s, d, "order_supp"), ["orderkey"], ["suppkey"]), "degree", "rank").withColumn("rank", F.col("rank").cast("int")), f"SELECT suppkey, degree, CAST(dense_rank() OVER (ORDER BY degree DESC) AS INT) AS rank FROM (SELECT suppkey, count(*) AS degree FROM {q('order_supp')} GROUP BY suppkey)"),
        "win_cumulative": (lambda s, d: running_total(degrees(r(s, d, "user_key_buy"), ["user_id"], ["k"]), [F.desc("degree"), F.asc("k")], "degree", "total"), f"SELECT k, degree, CAST(sum(degree) OVER (ORDER BY degree DESC, k ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS total FROM (SELECT k, count(*) AS degree FROM {q('user_key_buy')} GROUP BY k)"),
        "win_lag": (lambda s, d: t(s, d, "events").select("event_id", F.lag("event_type").over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("before"), F.lead("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("after")), "SELECT event_id, lag(event_type) OVER w AS before, lead(event_id) OVER w AS after FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"),
        "win_range": (lambda s, d: t(s, d, "orders").select("o_orderkey", rows_().over(W.partitionBy("o_orderstatus").orderBy("o_custkey").rangeBetween(-10, 10)).alias("n")), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_orderstatus ORDER BY o_custkey RANGE BETWEEN 10 PRECEDING AND 10 FOLLOWING) AS n FROM orders"),
        "topk_heavy": (lambda s, d: degrees(r(s, d, "doc_line"), ["doc_id"], ["line"]).orderBy(F.desc("degree"), "line").limit(10), f"SELECT line, count(*) AS degree FROM {q('doc_line')} GROUP BY line ORDER BY degree DESC, line LIMIT 10"),
        "sort_enumerate": (lambda s, d: r(s, d, "cust_order").orderBy("custkey", "orderkey").limit(100), f"SELECT * FROM {q('cust_order')} ORDER BY custkey, orderkey LIMIT 100"),
        "set_intersect": (lambda s, d: r(s, d, "part_supp_r").intersect(r(s, d, "part_supp_a")), q("part_supp_ra")[1:-1]),
        "set_union": (lambda s, d: r(s, d, "part_supp_r").union(r(s, d, "part_supp_a")).distinct(), f"{q('part_supp_r')} UNION {q('part_supp_a')}"),
        "set_except": (lambda s, d: r(s, d, "part_supp_r").exceptAll(r(s, d, "part_supp_a")), f"{q('part_supp_r')} EXCEPT {q('part_supp_a')}"),
        "set_union_all": (lambda s, d: r(s, d, "part_supp_r").union(r(s, d, "part_supp_a")).groupBy("partkey", "suppkey").agg(rows_().alias("copies")), f"SELECT partkey, suppkey, count(*) AS copies FROM ({q('part_supp_r')} UNION ALL {q('part_supp_a')}) GROUP BY ALL"),
        "fn_string": (lambda s, d: t(s, d, "customer").select("c_custkey", F.lower(F.trim("c_name")).alias("name"), F.sha2("c_name", 256).alias("code"), F.concat_ws("-", F.substring("c_mktsegment", 1, 3), F.length("c_name").cast("string")).alias("tag")), "SELECT c_custkey, lower(trim(c_name)) AS name, sha256(c_name) AS code, concat_ws('-', substring(c_mktsegment, 1, 3), CAST(length(c_name) AS VARCHAR)) AS tag FROM customer"),
        "fn_math": (lambda s, d: degrees(r(s, d, "order_supp"), ["orderkey"], ["suppkey"]).select("suppkey", F.ceil(F.sqrt("degree")).cast("bigint").alias("root"), F.floor(F.col("degree") / 7).cast("bigint").alias("parts"), F.greatest("degree", F.lit(600)).alias("cap")), f"SELECT suppkey, CAST(ceil(sqrt(n)) AS BIGINT) AS root, CAST(floor(n / 7) AS BIGINT) AS parts, greatest(n, 600) AS cap FROM (SELECT suppkey, count(*) AS n FROM {q('order_supp')} GROUP BY suppkey)"),
        "fn_date": (lambda s, d: t(s, d, "orders").groupBy(F.year("o_orderdate").cast("bigint").alias("y"), F.month("o_orderdate").cast("bigint").alias("m")).agg(rows_().alias("n")), "SELECT year(o_orderdate) AS y, month(o_orderdate) AS m, count(*) AS n FROM orders GROUP BY ALL"),
        "fn_array": (lambda s, d: t(s, d, "embeddings").select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("bigint").alias("n_up")), "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x > 0)) AS BIGINT) AS n_up FROM embeddings"),
        "fn_map": (lambda s, d: degrees(r(s, d, "nation_cust"), ["custkey"], ["nationkey"]).groupBy().agg(F.map_from_entries(F.collect_list(F.struct("nationkey", "degree"))).alias("m")).select(F.explode("m").alias("nationkey", "degree")), f"SELECT nationkey, count(*) AS degree FROM {q('nation_cust')} GROUP BY nationkey"),
        "fn_json": (lambda s, d: t(s, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k")), "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events"),
        "fn_cast": (lambda s, d: t(s, d, "nation").select(F.col("n_nationkey").cast("bigint").alias("k"), F.coalesce(F.nullif("n_name", F.lit("FRANCE")), F.lit("-")).alias("name")), "SELECT CAST(n_nationkey AS BIGINT) AS k, coalesce(nullif(n_name, 'FRANCE'), '-') AS name FROM nation"),
        "st_tumbling": (lambda s, d: windows.drained(windows.tumbling(windows.file_stream(s, d)), "complete"), "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL"),
        "st_degree_state": (lambda s, d: windows.streamed_degrees(s, d), f"SELECT user_id, count(*) AS degree FROM {q('user_key')} GROUP BY user_id"),
        "st_delta_cycle": (lambda s, d: windows.delta_cycle(s, d), delta_sql()),
        "st_sliding": (lambda s, d: windows.sliding(t(s, d, "events")), "SELECT start, count(*) AS n FROM (SELECT ts, unnest([time_bucket(INTERVAL 15 MINUTE, ts), time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 15 MINUTE, time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 30 MINUTE, time_bucket(INTERVAL 15 MINUTE, ts) - INTERVAL 45 MINUTE]) AS start FROM events) GROUP BY start"),
        "st_session": (lambda s, d: windows.sessions(t(s, d, "events")), SESSION_SQL),
        "st_late": (lambda s, d: windows.late_events(s, d), "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL"),
        "st_distinct_edges": (lambda s, d: windows.drained(windows.distinct_edges(windows.file_stream(s, d), "100 days")), q("user_key")[1:-1]),
        "st_check_batches": (lambda s, d: windows.checked_batches(s, d), f"SELECT CAST(p AS INT) AS batch, max(n) AS max_degree, max(n) <= 5 AS holds FROM (SELECT p, b.user_id, count(*) AS n FROM (SELECT unnest([0, 1, 2]) AS p), {q('user_key_buy')} b WHERE b.k % 3 <= p AND b.user_id IN (SELECT user_id FROM {q('user_key_buy')} c WHERE c.k % 3 = p) GROUP BY ALL) GROUP BY p"),
        "op_bind_atom": (lambda s, d: bind_atom(t(s, d, li), {"o": "l_orderkey", "s": F.col("l_suppkey")}, "l_returnflag = 'R'").distinct(), "SELECT DISTINCT l_orderkey AS o, l_suppkey AS s FROM lineitem WHERE l_returnflag = 'R'"),
        "op_constants": (lambda s, d: sql(s, "q(p, x) :- lines(p, x, 'R', 1), parts(p, y)", {"lines": t(s, d, li).select("l_partkey", "l_suppkey", "l_returnflag", "l_linenumber"), "parts": t(s, d, "part").select("p_partkey", "p_brand")}), "SELECT DISTINCT l_partkey AS p, l_suppkey AS x FROM lineitem JOIN part ON l_partkey = p_partkey WHERE l_returnflag = 'R' AND l_linenumber = 1"),
        "src_star": (lambda s, d: star_of(t(s, d, "orders").select(F.col("o_orderkey") + 1)), "SELECT o_orderkey + 1 AS a, CAST(0 AS BIGINT) AS b FROM orders UNION ALL SELECT 0, o_orderkey + 1 FROM orders"),
        "sql_entry": (by_sql, "SELECT DISTINCT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"),
        "udtf_decompositions": (lambda s, d: lateral(s, d, "SELECT t.query, t.n_orders, f.bags FROM {rules} t, LATERAL decompositions(t.rule) f"), f"SELECT query, n_orders, bags FROM (VALUES ('cycle', 4, 'wxy|wyz'), ('cycle', 4, 'wxz|xyz'), ('triangle', 3, 'xyz')) AS t(query, n_parts, bags) JOIN {ORDERS_BY_PARTS} USING (n_parts)"),
        "udtf_widths": (lambda s, d: lateral(s, d, "SELECT t.query, t.n_orders, f.measure, f.value FROM {rules} t, LATERAL widths(t.rule, t.n_orders) f"), f"SELECT query, n_orders, measure, value FROM (VALUES ('cycle', 4, 'width', 1.5), ('cycle', 4, 'single tree', 2.0), ('triangle', 3, 'width', 1.5), ('triangle', 3, 'single tree', 1.5)) AS t(query, n_parts, measure, value) JOIN {ORDERS_BY_PARTS} USING (n_parts)"),
        "udaf_degree_profile": (lambda s, d: profiled(s, d), f"SELECT flag, count(*) || ' ' || max(n) AS profile FROM (SELECT l_returnflag AS flag, l_suppkey, count(*) AS n FROM lineitem GROUP BY ALL) GROUP BY flag"),
        "agg_approx_distinct": (lambda s, d: t(s, d, li).groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("n_parts")).select("l_returnflag", "n_parts", (F.abs(F.col("a") - F.col("n_parts")) <= 0.1 * F.col("n_parts")).alias("near")), "SELECT l_returnflag, count(DISTINCT l_partkey) AS n_parts, true AS near FROM lineitem GROUP BY l_returnflag"),
        "agg_sketch_prefilter": (lambda s, d: sketched(r(s, d, "doc_line"), "line", 3), f"SELECT line, count(*) AS degree FROM {q('doc_line')} GROUP BY line HAVING count(*) > 3"),
        "topk_answers": (lambda s, d: workloads.run(s, d, "w03").orderBy("orderkey", "partkey", "suppkey").limit(20), f"SELECT * FROM ({workloads.sql('w03')}) ORDER BY orderkey, partkey, suppkey LIMIT 20"),
        "win_ntile": (lambda s, d: r(s, d, "order_supp").withColumn("tile", F.ntile(4).over(W.partitionBy("suppkey").orderBy("orderkey"))), f"SELECT orderkey, suppkey, CAST(ntile(4) OVER (PARTITION BY suppkey ORDER BY orderkey) AS INT) AS tile FROM {q('order_supp')}"),
        "join_skewed": (lambda s, d: salted_join(r(s, d, "doc_line").select(F.col("doc_id").alias("d1"), "line"), r(s, d, "doc_line").select(F.col("doc_id").alias("d2"), "line"), "line").groupBy("d1").agg(rows_().alias("n")), f"SELECT a.doc_id AS d1, count(*) AS n FROM {q('doc_line')} a JOIN {q('doc_line')} b ON a.line = b.line GROUP BY a.doc_id"),
    }
    return out


SESSION_SQL = """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
n AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS session FROM g)
SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", user_id, count(*) AS n FROM n GROUP BY user_id, session"""


def by_sql(s, d):
    for name in ("customer", "nation", "region"):
        t(s, d, name).createOrReplaceTempView(f"{name}_for_sql")
    return sql(s, "SELECT DISTINCT c.c_custkey, n.n_name FROM customer_for_sql c, nation_for_sql AS n, region_for_sql r WHERE c.c_nationkey = n.n_nationkey AND n.n_regionkey = r.r_regionkey")


def lateral(s, d, text):
    """Over two rules, each with the number of orders that have as many parts as it has atoms."""
    register(s)
    parts = t(s, d, "lineitem").groupBy("l_orderkey").agg(F.countDistinct("l_partkey").alias("n_parts")).groupBy("n_parts").agg(rows_().alias("n_orders"))
    rules = s.createDataFrame([("triangle", "q() :- a(x, y), b(y, z), c(z, x)", 3), ("cycle", "q() :- a(x, y), b(y, z), c(z, w), d(w, x)", 4)], "query string, rule string, n_parts bigint")
    return s.sql(text, rules=rules.join(parts, "n_parts"))


#: (n_parts, n_orders): how many orders have that many parts.
ORDERS_BY_PARTS = "(SELECT n_parts, count(*) AS n_orders FROM (SELECT count(DISTINCT l_partkey) AS n_parts FROM lineitem GROUP BY l_orderkey) GROUP BY n_parts)"


def profiled(s, d):
    """The aggregate's first two figures; the others are floating point."""
    own = t(s, d, "lineitem").groupBy(F.col("l_returnflag").alias("flag"), "l_suppkey").agg(rows_().alias("n"))
    return own.groupBy("flag").agg(degree_profile()("n").alias("p")).select("flag", F.substring_index("p", " ", 2).alias("profile"))


def sketched(rel: DataFrame, key: str, above: int, cells: int = 1 << 16) -> DataFrame:
    """Keys with more than `above` rows. A sketch of hashed cells, which never counts a key too low, leaves few candidates, and only these are counted."""
    cell = F.pmod(F.xxhash64(key), F.lit(cells))
    full = rel.groupBy(cell.alias("__cell")).agg(rows_().alias("n")).filter(F.col("n") > above).select("__cell")
    likely = rel.withColumn("__cell", cell).join(F.broadcast(full), "__cell", "left_semi").drop("__cell")  # at most `cells` rows
    return degrees(likely, rel.columns, [key]).filter(F.col("degree") > above)


def salted_join(a: DataFrame, b: DataFrame, key: str, salts: int = 8, above: int = 100) -> DataFrame:
    """An equi-join whose heavy keys, counted on the left, are dealt over `salts` tasks; rows of the right follow their keys there."""
    hot = degrees(a, a.columns, [key]).filter(F.col("degree") > above).select(key, F.lit(True).alias("__hot"))
    deal = F.when(F.col("__hot"), F.pmod(F.xxhash64(*a.columns), F.lit(salts)).cast("int")).otherwise(0)
    left = a.join(hot, key, "left").withColumn("__salt", deal).drop("__hot")
    right = b.join(hot, key, "left").withColumn("__salt", F.explode(F.when(F.col("__hot"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("__hot")
    return left.join(right, [key, "__salt"]).drop("__salt")


def augmented(s, d):
    inst = Instance({frozenset(["orderkey", "suppkey"]): relation(s, d, "order_supp")})
    inst.augment(frozenset(["orderkey", "suppkey"]), relation(s, d, "order_supp").filter("suppkey <= 5"))
    return keep(inst.relations[frozenset(["orderkey", "suppkey"])])


def delta_sql() -> str:
    return workloads.sql("w05", "u1, k1")
