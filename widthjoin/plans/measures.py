"""Queries of the cost and accuracy measures: widths, traces, peak rows, exactness, duplication, delay."""

from __future__ import annotations

import math
from collections.abc import Callable
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import workloads
from ..acyclic import acyclic_evaluate, reduce_bags
from ..baselines import disjunctive_rule, pairwise_evaluate, single_tree_evaluate
from ..closure import close_bounds, settle
from ..decomposition import bag_selectors, enumerate_decompositions
from ..enumerate import delay_bound, enumerate_answers
from ..guided import Options, depth_limit, guided_evaluate, join_profile
from ..instance import Instance, columns
from ..materialize import keep
from ..query import parse_rule, show
from ..sources.relations import relation, star, text_for
from ..statistics import cardinalities, edge_domination
from ..width import cover_number, submodular_width, width_certificate, width_report

Entry = tuple[Callable[[SparkSession, str], DataFrame], str | None]
CYCLE = "q({}) :- a(x, y), b(y, z), c(z, w), d(w, x)"
NAMED = {
    "triangle": "q() :- a(x, y), b(y, z), c(z, x)",
    "cycle4": CYCLE.format(""),
    "cycle4_xz": CYCLE.format("x, z"),
    "cycle5": "q() :- a(v, w), b(w, x), c(x, y), d(y, z), e(z, v)",
    "k23": "q() :- a(u, x), b(u, y), c(u, z), d(v, x), e(v, y), f(v, z)",
    "path3": "q() :- a(w, x), b(x, y), c(y, z)",
}


def atom_rows(spark: SparkSession, sf_dir: str) -> int:
    """Distinct rows of the relation that every atom of the named queries stands for here: orders and their parts."""
    return relation(spark, sf_dir, "order_part").count()


ATOM_ROWS = f"(SELECT count(*) FROM ({text_for('order_part', True)}))"


def widths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Classical widths: every atom has at most the N rows of orders and their parts, which are counted."""
    n_rows = atom_rows(spark, sf_dir)
    own = [(n, q := parse_rule(t), edge_domination(q, n_rows), n_rows) for n, t in NAMED.items()]
    return width_report(spark, own).withColumn("n_rows", F.lit(n_rows).cast("bigint"))


#: Published widths of these queries, rounded to six places; selectors count the bag of the head too.
WIDTHS_SQL = f"""SELECT t.*, {ATOM_ROWS} AS n_rows FROM (VALUES
 ('triangle', '', 1, 1, 1.5, 1.5, 2, 1.5, 1.5, 3.0), ('cycle4', '', 2, 4, 1.5, 2.0, 2, 1.5, 1.5, 3.0), ('cycle4_xz', 'xz', 1, 3, 2.0, 2.0, 2, 2.0, 2.0, 4.0),
 ('cycle5', '', 5, 21, 1.666667, 2.0, 2, 1.666667, 1.666667, 3.333333), ('k23', '', 2, 6, 1.666667, 2.0, 2, 1.666667, 1.666667, 3.333333), ('path3', '', 1, 3, 1.0, 1.0, 1, 1.0, 1.0, 2.0))
 AS t(query, head, n_trees, n_selectors, width, single_width, cover_width, guided_exponent, dual_exponent, uniformizing_exponent)"""


def measured_widths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Widths on the instance at hand: sizes alone, then with keys."""
    own = []
    for name in ("w02", "w08"):
        w = workloads.build(spark, sf_dir, name)
        for kind in ("card", "keys"):
            own.append((f"{name}_{kind}", w.query, workloads.statistics(w, name, kind), float(w.instance.size)))
    return width_report(spark, own)


def certificate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The proof of the cycle's width, where every atom has at most the rows of orders and their parts."""
    q, n_rows = parse_rule(NAMED["cycle4"]), atom_rows(spark, sf_dir)
    _, selector, dual = width_certificate(q, edge_domination(q, n_rows), n_rows)
    return spark.createDataFrame([(",".join(sorted(map(show, selector))), n, round(float(d), 6)) for n, d in dual], "selector string, inequality string, weight double")


def trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The decompositions, and what bounds their bags: cover atoms cover each bag, each of at most the n_rows rows of orders and their parts, so none has more than n_rows^cover rows."""
    n_rows, rows = atom_rows(spark, sf_dir), []
    for n, x in NAMED.items():
        q = parse_rule(x)
        rows += [(n, "|".join(sorted(map(show, t.bags))), n_rows, max(cover_number(q, b) for b in t.bags)) for t in enumerate_decompositions(q)]
    return spark.createDataFrame(rows, "query string, bags string, n_rows bigint, cover int")


#: The undominated decompositions of these queries, known from the literature, by their bags.
TREES_SQL = f"""SELECT query, bags, {ATOM_ROWS} AS n_rows, cover FROM (VALUES
 ('triangle', 'xyz', 2), ('cycle4', 'wxy|wyz', 2), ('cycle4', 'wxz|xyz', 2), ('cycle4_xz', 'wxz|xyz|xz', 2), ('path3', 'wx|xy|yz', 1),
 ('k23', 'uvx|uvy|uvz', 2), ('k23', 'uxyz|vxyz', 3),
 ('cycle5', 'vwx|vxy|vyz', 2), ('cycle5', 'vwx|vxz|xyz', 2), ('cycle5', 'vwy|vyz|wxy', 2), ('cycle5', 'vwz|wxy|wyz', 2), ('cycle5', 'vwz|wxz|xyz', 2)) AS t(query, bags, cover)"""


def traced(name: str, head: str | None = None, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        w = workloads.build(spark, sf_dir, name, head)
        return guided_evaluate(w.query, w.instance, options=Options(**options), with_run=True)[1].frame(spark)

    return run


SUMMARY = [("w01", "x, y"), ("w02", None), ("w03", None), ("w04", None), ("w05", "u1, k1"), ("w07", None), ("w10", None), ("w11", None), ("w16", None), ("w17", None)]
SMALL_WIDTH = 4  # variables up to which the linear program is solved here


def light_runs(trace: list[dict]) -> list[list[dict]]:
    """The splits along each path of light branches that cannot go on, from its start."""
    by = {r["branch"]: r for r in trace}
    inner = {r["parent"] for r in trace if r["kind"] == "light"}
    out = []
    for r in trace:
        if r["branch"] not in inner:
            path = [r]
            while path[-1]["kind"] == "light":
                path.append(by[path[-1]["parent"]])
            out.append([x for x in reversed(path) if x.get("outcome") == "split"])
    return out


def analysis_checks(name: str, head: str | None, w, run) -> tuple:
    """What the analysis claims of every run, on this one."""
    split = [r for r in run.trace if r.get("outcome") == "split"]
    by = {r["branch"]: r for r in run.trace}
    runs = light_runs(run.trace)
    width = workloads_width(w, run.n) if len(w.query.variables) <= SMALL_WIDTH else None

    def above(r):  # potentials of the restarts over a branch, the nearest first
        while r["parent"] >= 0:
            r = by[r["parent"]]
            if r.get("phi") is not None:
                return r["phi"]
        return None

    restarts = [(r["phi"], above(r)) for r in run.trace if r.get("phi") is not None]
    return (
        name,
        all(r["ok"] for r in split),
        width is None or all(r["c_log"] <= width + 1e-6 for r in split),
        all(r["n_heavy"] <= r["heavy_bound"] for r in split if "n_heavy" in r),
        all(len(x) <= 2 ** len(w.query.variables) for x in runs),
        all(a["c_size"] <= b["c_size"] + 1e-6 for x in runs for a, b in zip(x, x[1:])),
        all(a["low_family"] < b["low_family"] for x in runs for a, b in zip(x, x[1:]) if a["c_size"] == b["c_size"]),
        all(up is None or phi < up for phi, up in restarts),
        all(r["depth"] <= depth_limit(len(w.query.variables), run.n, run.fanout) for r in run.trace),
    )


def trace_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of every workload: joins within c, c within the width, few heavy keys, short light runs with rising c and growing low families, potentials that fall."""
    out = []
    for name, head in SUMMARY:
        w = workloads.build(spark, sf_dir, name, head)
        _, run = guided_evaluate(w.query, w.instance, with_run=True)
        out.append(analysis_checks(name, head, w, run))
    return spark.createDataFrame(out, "workload string, joins_ok boolean, defects_ok boolean, heavy_ok boolean, runs_ok boolean, c_rises boolean, family_grows boolean, potential_falls boolean, depth_ok boolean")


def workloads_width(w, n: int) -> float:
    return submodular_width(w.query, cardinalities(w.instance), n)


TRACE_SQL = "SELECT unnest([" + ", ".join(f"'{n}'" for n, _ in SUMMARY) + "]) AS workload, true AS joins_ok, true AS defects_ok, true AS heavy_ok, true AS runs_ok, true AS c_rises, true AS family_grows, true AS potential_falls, true AS depth_ok"


def warm_up(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The warm-up, branch by branch as analysed: the star's sizes and bounds, its first split, and the tree of each leaf with its largest bag."""
    w = workloads.build(spark, sf_dir, "w01", "x, y, z, w")
    _, run = guided_evaluate(w.query, w.instance, options=Options(light_mode="separate", fanout=2), with_run=True)
    size = max(w.instance.measure().values())
    _, bounds = close_bounds(cardinalities(w.instance), w.instance, {k: Fraction(n) for k, n in w.instance.sizes.items()}, w.query.variables)
    first, by = run.trace[0], {r["branch"]: r for r in run.trace}
    splits = [r for r in run.trace if r.get("outcome") == "split"]
    largest = max(max(i.measure().values()) for _, i in run.leaves)
    facts = {
        "rows of an atom": size,
        "bounded sets": len([s for s in bounds if s]),
        "sets with that bound": sum(v == size for s, v in bounds.items() if s),
        "variables shared by the first pair": len(first["w"]),
        "theta of the first split": int(first["theta"]),
        "heavy keys of the first split": first["n_heavy"],
        "trees that leaves take": len({t.bag_set for t, _ in run.leaves}),
        "splits that keep within c": int(all(r["ok"] for r in splits)),
        "rows of the largest relation over rows of an atom": largest // size,
        "deepest heavy chain": max(heavies(r, by) for r in run.trace),
    }
    return spark.createDataFrame([(k, int(v)) for k, v in facts.items()], "fact string, value bigint")


WARM_SQL = """WITH s AS (SELECT 2 * count(*) - 1 AS n FROM customer)
SELECT 'rows of an atom' AS fact, n AS value FROM s UNION ALL SELECT * FROM (VALUES
 ('bounded sets', 8), ('sets with that bound', 8), ('variables shared by the first pair', 1), ('theta of the first split', 1), ('heavy keys of the first split', 1),
 ('trees that leaves take', 2), ('splits that keep within c', 1), ('rows of the largest relation over rows of an atom', 1), ('deepest heavy chain', 1)) AS t(fact, value)"""


def heavies(r: dict, by: dict) -> int:
    n = 0
    while True:
        n += r["kind"] == "heavy"
        if r["parent"] < 0:
            return n
        r = by[r["parent"]]


def peak_slopes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exponent of the largest intermediate relation on the star, over three sizes. Bags of single trees and first joins are counted from degrees, not made."""
    n = spark.read.parquet(f"{sf_dir}/customer.parquet").count()
    q, points = workloads.rule("w01", "x, y"), {"guided": [], "single_tree": [], "pairwise": []}
    for k in (n // 4, n // 2, n):
        edges = star(spark, k)
        inst = Instance.load(q, {"star_edges": edges})
        _, run = guided_evaluate(q, inst, with_run=True)
        points["guided"].append((inst.size, run.peak_rows))
        e = sorted(inst.relations, key=show)
        near = [(a, b) for a in e for b in e if show(a) < show(b) and len(a & b) == 1]
        joined = [join_profile(inst.relations[a], inst.relations[b], a & b, 0, 0).joined for a, b in near]
        points["single_tree"].append((inst.size, max(joined)))
        points["pairwise"].append((inst.size, joined[0]))
    return spark.createDataFrame([(k, round(workloads.slope(v), 1)) for k, v in points.items()], "engine string, exponent double")


def closure_work(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that the bound closure reads and writes for each relation it makes, against the rows of the instance."""
    out = []
    for name in ("w02", "w08"):
        for kind in ("card", "keys", "measured"):
            w = workloads.build(spark, sf_dir, name)
            stats = workloads.statistics(w, name, kind)
            _, steps = settle(stats, w.query.variables, {k: Fraction(n) for k, n in w.instance.measure().items()})
            made, bounds = close_bounds(stats, w.instance, {k: Fraction(n) for k, n in w.instance.sizes.items()}, w.query.variables)
            sizes = made.measure()
            rows = sum(sizes[s.to] + sizes.get(s.source, 0) for s in steps)
            out.append((name, kind, all(sizes[k] <= v for k, v in bounds.items() if k in sizes), rows <= 2 * max(1, len(steps)) * max(sizes.values())))
    return spark.createDataFrame(out, "workload string, stats string, within_bounds boolean, linear boolean")


CLOSURE_SQL = "SELECT w AS workload, s AS stats, true AS within_bounds, true AS linear FROM (SELECT unnest(['w02', 'w08']) AS w), (SELECT unnest(['card', 'keys', 'measured']) AS s)"


def rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of each disjunctive rule of two queries: rows of the body's join that no head table has."""
    out = []
    for name in ("w02", "w03"):
        w = workloads.build(spark, sf_dir, name)
        body = keep(pairwise_evaluate(w.query, w.instance))
        for s in bag_selectors(enumerate_decompositions(w.query)):
            left = body
            for k, df in disjunctive_rule(w.query, w.instance, s).items():
                left = left.join(df, columns(k), "left_anti")
            out.append((name, " or ".join(sorted(map(show, s))), left.count()))
    return spark.createDataFrame(out, "workload string, heads string, n_uncovered bigint")


RULES_SQL = """SELECT * FROM (VALUES
 ('w02', 'custkey,nationkey,orderkey or custkey,nationkey,suppkey', 0), ('w02', 'custkey,nationkey,orderkey or custkey,orderkey,suppkey', 0),
 ('w02', 'custkey,nationkey,suppkey or nationkey,orderkey,suppkey', 0), ('w02', 'custkey,orderkey,suppkey or nationkey,orderkey,suppkey', 0), ('w03', 'orderkey,partkey,suppkey', 0)) AS t(workload, heads, n_uncovered)"""


def peak_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest intermediate relation on the star: guided against a single tree."""
    w = workloads.build(spark, sf_dir, "w01", "x, y")
    _, run = guided_evaluate(w.query, w.instance, with_run=True)
    sizes: dict = {}
    single_tree_evaluate(w.query, w.instance, 0, sizes)
    n = max(w.instance.measure().values())
    return spark.createDataFrame([(run.peak_rows <= 3 * n, max(sizes.values()))], "guided_is_linear boolean, single_tree_rows bigint")


PEAK_SQL = "SELECT true AS guided_is_linear, n * n + n - 1 AS single_tree_rows FROM (SELECT count(*) AS n FROM customer)"


def exactness(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = workloads.build(spark, sf_dir, "w02")
    got, ref = guided_evaluate(w.query, w.instance), pairwise_evaluate(w.query, w.instance)
    return spark.createDataFrame([(ref.exceptAll(got).count(), got.exceptAll(ref).count())], "missing bigint, extra bigint")


def duplication(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct answers, and whether the sum over leaves counts some of them twice: on the star, where branches overlap, it does."""
    out = []
    for name, head in (("w01", "x, z"), ("w02", None)):
        w = workloads.build(spark, sf_dir, name, head)
        _, run = guided_evaluate(w.query, w.instance, options=Options(fanout=2), with_run=True)
        every = None
        for t, leaf in run.leaves:
            a = acyclic_evaluate(t, reduce_bags(leaf.relations, t), w.query.head)
            every = a if every is None else every.union(a)
        per = every.groupBy(*every.columns).agg(F.count(F.lit(1)).alias("leaves"))
        r = per.agg(F.count(F.lit(1)).alias("n"), F.sum("leaves").alias("s"), F.max("leaves").alias("m")).first()
        out.append((name, r["n"], r["s"] >= r["n"], r["m"] <= len(run.leaves)))
    return spark.createDataFrame(out, "workload string, n_answers bigint, sums_never_fall_short boolean, at_most_once_a_leaf boolean")


DELAYS = [("w01", "x"), ("w01", "x, y"), ("w02", None), ("w04", None)]


def delay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Enumeration from indexed bags: answers, repeats, and whether the most steps between two stay within a bound that does not know N."""
    out = []
    for name, head in DELAYS:
        w = workloads.build(spark, sf_dir, name, head)
        _, run = guided_evaluate(w.query, w.instance, with_run=True)
        seen, n, gap = set(), 0, 0
        for a, steps in enumerate_answers(w.query, run):
            n, gap = n + 1, max(gap, steps)
            seen.add(a)
        out.append((f"{name} {head or 'full'}", n, n - len(seen), gap <= delay_bound(run)))
    return spark.createDataFrame(out, "workload string, n_answers bigint, n_repeats bigint, gap_is_bounded boolean")


def widths_with_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Measured widths: keys never raise them, and their certificates' weights add up to them."""
    out = []
    for name in ("w02", "w08"):
        w = workloads.build(spark, sf_dir, name)
        n = float(w.instance.size)
        value = {}
        for kind in ("card", "keys"):
            stats = workloads.statistics(w, name, kind)
            value[kind], _, dual = width_certificate(w.query, stats, n)
            logs = {f"degree of {show(t.y)} given {show(t.x) or 'nothing'}": math.log(t.max_degree) / math.log(n) for t in stats.terms}
            proved = sum(d * logs[x] for x, d in dual if x in logs)
            out.append((name, kind, bool(abs(proved - value[kind]) < 1e-6), bool(value[kind] <= value["card"] + 1e-9)))
    return spark.createDataFrame(out, "workload string, stats string, proved boolean, not_above_sizes boolean")


def registry() -> dict[str, Entry]:
    return {
        "width_known": (widths, WIDTHS_SQL),
        "width_measured": (measured_widths, None),
        "width_certificate": (certificate, None),
        "td_list": (trees, TREES_SQL),
        "trace_w01": (traced("w01", "x, y"), None),
        "trace_w02": (traced("w02"), None),
        "trace_summary": (trace_summary, TRACE_SQL),
        "peak_rows": (peak_rows, PEAK_SQL),
        "exactness": (exactness, "SELECT CAST(0 AS BIGINT) AS missing, CAST(0 AS BIGINT) AS extra"),
        "warmup_w01": (warm_up, WARM_SQL),
        "peak_slopes": (peak_slopes, "SELECT * FROM (VALUES ('guided', 1.0), ('single_tree', 2.0), ('pairwise', 2.0)) AS t(engine, exponent)"),
        "closure_work": (closure_work, CLOSURE_SQL),
        "disj_rules": (rules, RULES_SQL),
        "width_proofs": (widths_with_keys, "SELECT w AS workload, s AS stats, true AS proved, true AS not_above_sizes FROM (SELECT unnest(['w02', 'w08']) AS w), (SELECT unnest(['card', 'keys']) AS s)"),
        "dup_report": (duplication, " UNION ALL ".join(f"SELECT '{n}' AS workload, count(*) AS n_answers, true AS sums_never_fall_short, true AS at_most_once_a_leaf FROM ({workloads.sql(n, h)})" for n, h in (("w01", "x, z"), ("w02", None)))),
        "delay_report": (delay, " UNION ALL ".join(f"SELECT '{n} {h or 'full'}' AS workload, count(*) AS n_answers, CAST(0 AS BIGINT) AS n_repeats, true AS gap_is_bounded FROM ({workloads.sql(n, h)})" for n, h in DELAYS)),
    }
