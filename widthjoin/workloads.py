"""Workloads on the given tables: rules, statistics, engines, and the SQL they are checked against."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .baselines import dual_rules_evaluate, pairwise_evaluate, single_tree_evaluate, uniformize_evaluate
from .baselines.single_tree import trivial
from .guided import Options, guided_evaluate
from .instance import Instance, as_set, widened
from .materialize import LARGE, SENT, collected, keep, most_rows, sendable
from .query import ConjunctiveQuery, parse_rule
from .sources.relations import relation, text_for
from .statistics import Statistics, cardinalities, collect_statistics

#: name -> rule; relation names are those of sources.relations.
RULES = {
    "w01": "q(x, y, z, w) :- star_edges(x, y), star_edges(y, z), star_edges(z, w), star_edges(w, x)",
    "w02": "q(custkey, orderkey, suppkey, nationkey) :- cust_order(custkey, orderkey), order_supp(orderkey, suppkey), supp_nation(suppkey, nationkey), nation_cust(nationkey, custkey)",
    "w03": "q(orderkey, partkey, suppkey) :- order_part(orderkey, partkey), part_supp(partkey, suppkey), order_supp(orderkey, suppkey)",
    "w04": "q(partkey, suppkey, orderkey) :- part_supp_r(partkey, suppkey), supp_order_a(suppkey, orderkey), order_part_n(orderkey, partkey)",
    "w05": "q(u1, k1, u2, k2) :- user_key_buy(u1, k1), user_key_buy(u2, k1), user_key_buy(u2, k2), user_key_buy(u1, k2)",
    "w05b": "q(u1, k1, u2, k2) :- user_key(u1, k1), user_key(u2, k1), user_key(u2, k2), user_key(u1, k2)",
    "w06": "q(d1, l1, d2, l2) :- doc_line(d1, l1), doc_line(d2, l1), doc_line(d2, l2), doc_line(d1, l2)",
    "w07": "q(p1, h1, p2, h2) :- page_link(p1, h1), page_link(p2, h1), page_link(p2, h2), page_link(p1, h2)",
    "w08": "q(partkey, suppkey, nationkey, custkey, orderkey) :- part_supp(partkey, suppkey), supp_nation(suppkey, nationkey), nation_cust(nationkey, custkey), cust_order(custkey, orderkey), order_part(orderkey, partkey)",
    "w09": "q(o, p, s, l) :- line_ops(o, p, s), line_psl(p, s, l), line_slo(s, l, o), line_lop(l, o, p)",
    "w10": "q(custkey, orderkey, partkey) :- cust_order(custkey, orderkey), order_part(orderkey, partkey)",
    "w11": "q(conv_id, turn, role) :- conv_turn(conv_id, turn), turn_role(turn, role), role_conv(role, conv_id)",
    "w12": "q(u1, u2, k1, k2, k3) :- user_key_buy(u1, k1), user_key_buy(u1, k2), user_key_buy(u1, k3), user_key_buy(u2, k1), user_key_buy(u2, k2), user_key_buy(u2, k3)",
    "w13": "q(s, p1, o1, p2, o2) :- part_supp_r(p1, s), supp_order_a(s, o1), order_part_n(o1, p1), part_supp_r(p2, s), supp_order_a(s, o2), order_part_n(o2, p2)",
    "w14": "q(o, p, s, custkey, nationkey, regionkey) :- line_ops(o, p, s), cust_order(custkey, o), nation_cust(nationkey, custkey), nation_region(nationkey, regionkey), region_key(regionkey)",
    "w15": "q(v1, b1, v2, b2) :- vec_bit(v1, b1), vec_bit(v2, b1), vec_bit(v2, b2), vec_bit(v1, b2)",
    "w16": "q(partkey, suppkey, orderkey) :- part_supp_r(partkey, suppkey), part_supp_a(partkey, suppkey), supp_order_a(suppkey, orderkey), order_part_n(orderkey, partkey)",
    "w17": "q(doc_id, lang, source) :- doc_lang(doc_id, lang), lang_source(lang, source), source_doc(source, doc_id)",
}

#: Degree-1 statistics that the tables' keys imply: (y, x, guard).
KEYS = {
    "w02": [("custkey", "orderkey", ("custkey", "orderkey")), ("nationkey", "suppkey", ("suppkey", "nationkey")), ("nationkey", "custkey", ("nationkey", "custkey"))],
    "w14": [("custkey", "o", ("custkey", "o")), ("nationkey", "custkey", ("nationkey", "custkey")), ("regionkey", "nationkey", ("nationkey", "regionkey"))],
    "w17": [("lang", "doc_id", ("doc_id", "lang")), ("source", "doc_id", ("source", "doc_id"))],
}
KEYS["w08"] = KEYS["w02"]


@dataclass
class Workload:
    query: ConjunctiveQuery
    instance: Instance


def rule(name: str, head: str | None = None) -> ConjunctiveQuery:
    """head: comma-separated variables, "" for a Boolean query, None for the rule's own."""
    q = parse_rule(RULES[name])
    return q if head is None else q.with_head(v.strip() for v in head.split(",") if v.strip())


def build(spark: SparkSession, sf_dir: str, name: str, head: str | None = None) -> Workload:
    q = rule(name, head)
    tables = {r: relation(spark, sf_dir, r) for r in {a.relation for a in q.atoms}}
    return Workload(q, Instance.load(q, numbered(q, tables)))


def build_in_place(spark: SparkSession, sf_dir: str, name: str, head: str | None = None) -> Workload | None:
    """The workload with numbers for all strings, and the head's strings kept beside those atoms that the evaluator joins first.
    None where that does not pay or cannot be done: without strings in the head, with uneven atoms, or if a relation is too long to be sent to the others' join."""
    q = rule(name, head)
    tables = {r: relation(spark, sf_dir, r) for r in {a.relation for a in q.atoms}}
    kinds = {r: [k for _, k in df.dtypes] for r, df in tables.items()}
    strings = {v for a in q.atoms for v, k in zip(a.vars, kinds[a.relation], strict=False) if k == "string"}
    if not strings & q.head or any(a.values or len(a.set) < len(a.vars) for a in q.atoms) or len(q.edges) < len(q.atoms):
        return None
    carriers: list = []  # atoms that bind the head's strings, all with a variable in common
    for pivot in sorted(q.variables - strings):
        own = [next((a for a in q.atoms if {v, pivot} <= a.set), None) for v in sorted(strings & q.head)]
        if all(own):
            carriers = list(dict.fromkeys(own))
            break
    if not carriers:
        return None
    tables = {r: keep(as_set(df)) for r, df in tables.items()}
    if any(most_rows(df) > SENT for df in tables.values()):
        return None
    texts: dict[str, DataFrame] = {}
    inst = Instance.load(q, numbered(q, tables, texts))
    if not all(sendable(df) for df in inst.relations.values()) or not all(a.relation in texts for a in carriers):
        return None
    for a in carriers:
        own = texts[a.relation]
        c = own.columns[: len(a.vars)]
        inst.texts[a.set] = own.select(*[widened(F.col(x), k).alias(v) for v, x, k in zip(a.vars, c, [k for _, k in own.dtypes], strict=False)], *[F.col(f"__text_{x}").alias(f"__text_{v}") for v, x in zip(a.vars, c, strict=True) if f"__text_{x}" in own.columns and v in q.head])
    return Workload(q, inst)


def numbered(q: ConjunctiveQuery, tables: dict[str, DataFrame], texts: dict[str, DataFrame] | None = None) -> dict[str, DataFrame]:
    """The tables with numbers in place of strings that only join: those of variables that the head does not have.

    Places that share a variable share the numbers, which are exact: one for each distinct string, written once. Answers
    do not change, and the relations, bags and shuffles of the evaluators hold 8 bytes in place of, say, a line of text.
    texts: strings of the head are numbered too, and it gets the tables with a column __text_c for a numbered column c.
    """
    if any(a.values for a in q.atoms):  # constants are compared with strings
        return tables
    linked: dict[tuple[str, int], set] = {}
    for a in q.atoms:
        for i, v in enumerate(a.vars):
            if dict(tables[a.relation].dtypes)[tables[a.relation].columns[i]] == "string":
                linked.setdefault((a.relation, i), set()).add(v)
    classes: list[tuple[set, set]] = []  # (places, variables)
    for place, own in linked.items():
        touched = [c for c in classes if c[1] & own]
        classes = [c for c in classes if not c[1] & own] + [({place}.union(*(c[0] for c in touched)), own.union(*(c[1] for c in touched)))]
    out = dict(tables)
    for places, own in classes:
        mixed = any(v in own and (a.relation, i) not in places for a in q.atoms for i, v in enumerate(a.vars))
        if (own & q.head and texts is None) or mixed:
            continue
        named = [out[r].select(F.col(tables[r].columns[i]).alias("__text")) for r, i in sorted(places)]
        strings = keep(reduce(DataFrame.union, named).dropna().distinct().withColumn("__number", F.monotonically_increasing_id()))
        for r, i in sorted(places):
            c = tables[r].columns
            joined = out[r].join(strings.withColumnRenamed("__text", c[i]), c[i])
            also = [] if texts is None else [x for x in out[r].columns if x not in c] + [F.col(c[i]).alias(f"__text_{c[i]}")]
            out[r] = joined.select(*[F.col("__number").alias(x) if x == c[i] else x for x in c], *also)
    out = {r: df if df is tables[r] else keep(df) for r, df in out.items()}
    if texts is not None:
        texts |= out
        collected(next(iter(out.values())).sparkSession, LARGE)
    return {r: df.select(tables[r].columns) for r, df in out.items()} if texts is not None else out


def statistics(w: Workload, name: str, kind: str) -> Statistics | None:
    """none; card: sizes; keys: sizes and keys; measured: sizes and the largest degree of each atom's variables, both ways."""
    if kind == "none":
        return None
    card = cardinalities(w.instance)
    if kind == "card":
        return card
    if kind == "keys":
        return card + Statistics.declare(*[(y, x, 1, g) for y, x, g in KEYS.get(name, [])])
    if kind == "measured":
        terms = [(e - {v}, frozenset([v]), e) for e in sorted(w.query.edges, key=sorted) for v in sorted(e)]
        return card + collect_statistics(w.instance, terms)
    raise ValueError(kind)


def run(spark: SparkSession, sf_dir: str, name: str, engine: str = "guided", head: str | None = None, stats: str = "none", **options) -> DataFrame:
    """engine: guided, pairwise, tree:<i>, trivial, dual, uniform."""
    w = (build_in_place(spark, sf_dir, name, head) if engine in ("pairwise", "trivial") else None) or build(spark, sf_dir, name, head)
    own = statistics(w, name, stats)
    if engine == "guided":
        return guided_evaluate(w.query, w.instance, own, Options(**options))
    if engine == "pairwise":
        return pairwise_evaluate(w.query, w.instance)
    if engine == "trivial":
        return single_tree_evaluate(w.query, w.instance, trivial(w.query))
    if engine.startswith("tree:"):
        return single_tree_evaluate(w.query, w.instance, int(engine[5:]))
    if engine == "dual":
        return dual_rules_evaluate(w.query, w.instance, own, Options(**options))
    if engine == "uniform":
        return uniformize_evaluate(w.query, w.instance, **options)
    raise ValueError(engine)


def sql(name: str, head: str | None = None) -> str:
    """The workload as one DuckDB statement: distinct rows of plain joins."""
    q = parse_rule(RULES[name])
    names = sorted({a.relation for a in q.atoms})
    ctes = ", ".join(f"{n} AS ({text_for(n, True)})" for n in names)
    first: dict[str, str] = {}
    joins, conds = [], []
    for i, a in enumerate(q.atoms):
        aliased = ", ".join(f"v{k}" for k in range(len(a.vars)))
        joins.append(f"{a.relation} AS t{i}({aliased})")
        for k, v in enumerate(a.vars):
            if v in first:
                conds.append(f"t{i}.v{k} = {first[v]}")
            else:
                first[v] = f"t{i}.v{k}"
    where = f" WHERE {' AND '.join(conds)}" if conds else ""
    own = sorted(q.head if head is None else (v.strip() for v in head.split(",") if v.strip()))
    if not own:
        return f"WITH {ctes} SELECT count(*) > 0 AS answer FROM (SELECT 1 FROM {', '.join(joins)}{where} LIMIT 1)"
    return f"WITH {ctes} SELECT DISTINCT {', '.join(f'{first[v]} AS {v}' for v in own)} FROM {', '.join(joins)}{where}"


def slope(points: list[tuple[int, int]]) -> float:
    """Least-squares slope of log rows against log N."""
    xs, ys = [math.log(n) for n, _ in points], [math.log(max(r, 1)) for _, r in points]
    mx, my = sum(xs) / len(xs), sum(ys) / len(ys)
    return sum((x - mx) * (y - my) for x, y in zip(xs, ys, strict=True)) / sum((x - mx) ** 2 for x in xs)
