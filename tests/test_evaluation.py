import datetime
import os
import random
import re
import time
from fractions import Fraction

import pytest
from pyspark.sql import functions as F

from widthjoin import materialize, sql, workloads
from widthjoin.baselines import disjunctive_rule, dual_rules_evaluate, pairwise_evaluate, single_tree_evaluate, uniformize_evaluate
from widthjoin.baselines import single_tree
from widthjoin.baselines.pairwise import connected_order, estimates
from widthjoin.baselines.single_tree import bag_relation, bag_relations, bag_size
from widthjoin.decomposition import bag_selectors, enumerate_decompositions
from widthjoin.closure import close_bounds
from widthjoin.enumerate import TreeAnswers, delay_bound, enumerate_answers, union_of
from widthjoin.functions import dense_rank, running_total
from widthjoin.guided import Options, Run, batches, check_invariants, evaluate_leaves, guided_evaluate, join_profile
from widthjoin.acyclic import reduced
from widthjoin.instance import Instance, columns, natural_join, project, semijoin
from widthjoin.partition import equal_degree_parts, heavy_light
from widthjoin.plans import measures, surface
from widthjoin.query import parse_rule
from widthjoin.materialize import cleaned, keep_counted, scratch
from widthjoin.sources import bind_atom, star
from widthjoin.statistics import Statistics, cardinalities, check_statistics, max_degree
from widthjoin.streaming import windows
from widthjoin.width import submodular_width

CYCLE = "q({}) :- a(x, y), b(y, z), c(z, w), d(w, x)"


def tables(spark, **rows):
    return {k: spark.createDataFrame(v, "a bigint, b bigint") for k, v in rows.items()}


def rows(df):
    return sorted(tuple(r) for r in df.select(sorted(df.columns)).collect())


def brute(q, data):
    names = sorted(q.variables)
    found = [{}]
    for atom in q.atoms:
        new = []
        for s in found:
            for t in data[atom.relation]:
                if None not in t and all(s.get(v, x) == x for v, x in zip(atom.vars, t)) and len({v: x for v, x in zip(atom.vars, t)}) == len(set(atom.vars)):
                    own = dict(s)
                    if all(own.setdefault(v, x) == x for v, x in zip(atom.vars, t)):
                        new.append(own)
        found = new
    head = sorted(q.head)
    return sorted({tuple(s[v] for v in head) for s in found}) if names else []


TWO_HUBS = [(0, i) for i in range(1, 9)] + [(i, 1) for i in range(1, 6)] + [(9, 9), (9, 0), (1, 0), (4, 0), (None, 3), (2, None)] + [(0, 1)]


ENGINES = {
    "guided": lambda q, i: guided_evaluate(q, i, options=Options(fanout=4)),
    "separate": lambda q, i: guided_evaluate(q, i, options=Options(fanout=2, light_mode="separate")),
    "pairwise": pairwise_evaluate,
    "dual": lambda q, i: dual_rules_evaluate(q, i, options=Options(fanout=8)),
    "uniform": lambda q, i: uniformize_evaluate(q, i, 0.7),
    "tree": lambda q, i: single_tree_evaluate(q, i, 0),
}


@pytest.mark.parametrize("head,engines", [("", ["guided", "tree"]), ("x, z", ["guided", "tree"]), ("x, y, z, w", ["guided", "pairwise", "tree"])])
def test_all_engines_agree_with_brute_force(spark, head, engines):
    q = parse_rule(CYCLE.format(head))
    data = dict(a=TWO_HUBS, b=[(y, x) for x, y in TWO_HUBS], c=TWO_HUBS, d=[(y, x) for x, y in TWO_HUBS])
    inst = Instance.load(q, tables(spark, **data))
    expected = brute(q, data)
    for name in engines:
        assert rows(ENGINES[name](q, inst)) == (expected if head else [(bool(expected),)]), name


def test_dual_and_uniformizing_baselines_agree(spark):
    q = parse_rule("q(x, y, z) :- a(x, y), b(y, z), c(z, x)")
    data = dict(a=TWO_HUBS, b=TWO_HUBS, c=TWO_HUBS)
    inst = Instance.load(q, tables(spark, **data))
    for name in ("guided", "separate", "dual", "uniform"):
        assert rows(ENGINES[name](q, inst)) == brute(q, data), name


def many_nations(spark):
    """Few nations with many customers and suppliers each; an order has one customer and two suppliers."""
    q = parse_rule("q(c, o, s, n) :- co(c, o), os(o, s), sn(s, n), nc(n, c)")
    data = {"co": [(i % 60, i) for i in range(240)], "os": [(i, (i * k) % 60) for i in range(240) for k in (1, 7)], "sn": [(i, i % 2) for i in range(60)], "nc": [(i % 2, i) for i in range(60)]}
    return q, data, Instance.load(q, tables(spark, **data))


def test_pairwise_joins_take_the_order_with_the_smallest_joins(spark):
    q, data, inst = many_nations(spark)
    most, order = connected_order(q.edges, estimates(inst, q.edges))
    assert most <= 500 and set().union(*order[:3]) == {"c", "o", "s", "n"}
    assert not {frozenset("sn"), frozenset("cn")} <= set(order[:2]) and order.index(frozenset("os")) < 3  # no join over the nation alone
    assert rows(pairwise_evaluate(q, inst)) == brute(q, data)


def test_a_bag_is_made_from_what_its_neighbour_leaves_of_it(spark):
    q, data, inst = many_nations(spark)
    for i, t in enumerate(enumerate_decompositions(q)):
        made, sizes = bag_relations(q, inst, t), {}
        assert rows(single_tree_evaluate(q, inst, i, sizes)) == brute(q, data)
        assert max(df.count() for df in made.values()) <= 480
        assert sizes == {b: bag_relation(q, inst, b).count() for b in t.bags}  # counted from degrees, but of the whole bag


def bag_sizes(q, inst):
    return [bag_size(q, inst, b) for t in enumerate_decompositions(q) for b in t.bags]


def test_bags_of_two_atoms_are_counted_without_joining(spark, monkeypatch):
    q, _, inst = many_nations(spark)
    monkeypatch.setattr(single_tree, "bag_relation", lambda *a: pytest.fail("the bag was made"))
    assert 1800 in bag_sizes(q, inst)


def test_edge_cases(spark):
    q = parse_rule(CYCLE.format("x"))
    none = Instance.load(q, tables(spark, a=[], b=[(1, 2)], c=[(1, 2)], d=[(1, 2)]))
    assert rows(guided_evaluate(q, none)) == []
    assert rows(guided_evaluate(q.with_head([]), none)) == [(False,)]
    one = Instance.load(q, tables(spark, a=[(1, 2)], b=[(2, 3)], c=[(3, 4)], d=[(4, 1)]))
    assert rows(guided_evaluate(q, one)) == [(1,)]
    nothing = Instance.load(q, tables(spark, a=[(1, 2)], b=[(3, 3)], c=[(3, 4)], d=[(4, 1)]))
    assert rows(guided_evaluate(q.with_head([]), nothing)) == [(False,)]
    apart = parse_rule("q(x, z) :- a(x, y), b(z, w)")
    assert rows(guided_evaluate(apart, Instance.load(apart, tables(spark, a=[(1, 2), (1, 3)], b=[(5, 6), (7, 7)])))) == [(1, 5), (1, 7)]
    same = parse_rule("q(x, y) :- a(x, y), b(x, y)")
    inst = Instance.load(same, tables(spark, a=[(1, 2), (1, 3)], b=[(1, 3), (2, 2)]))
    assert inst.matches(same) and rows(guided_evaluate(same, inst)) == [(1, 3)]
    loop = parse_rule("q(x) :- a(x, x)")
    assert rows(guided_evaluate(loop, Instance.load(loop, tables(spark, a=[(1, 2), (4, 4), (None, None)])))) == [(4,)]


def test_split_is_disjoint_and_complete(spark):
    rel = spark.createDataFrame([(k, i) for k in range(1, 6) for i in range(k)], "x bigint, y bigint")
    heavy, light = heavy_light(rel, ["x"], 3)
    assert sorted(r[0] for r in heavy.collect()) == [4, 5]
    assert {r[0] for r in light.collect()} == {1, 2, 3}
    parts = equal_degree_parts(light, ["x"], 2)
    assert rows(parts.drop("__part")) == rows(light)
    assert all(max_degree(parts.filter(f"__part = {i}").drop("__part"), ["x", "y"], ["x"]) <= 2 for i in (0, 1))


def test_wrong_statistics_are_found(spark):
    q = parse_rule("q(x) :- a(x, y)")
    inst = Instance.load(q, tables(spark, a=[(1, 2), (1, 3)]))
    bad = check_statistics(inst, Statistics.declare(("y", "x", 1, "xy")))
    assert bad[0][1] == 2
    with pytest.raises(ValueError):
        guided_evaluate(q, inst, Statistics.declare(("y", "x", 1, "xy")), Options(verify=True))


def test_trace_keeps_the_bounds_on_the_star(spark):
    n = 40
    edge = [(i, 0) for i in range(n)] + [(0, i) for i in range(n)]
    q = parse_rule("q(x, y) :- e(x, y), e(y, z), e(z, w), e(w, x)")
    inst = Instance.load(q, tables(spark, e=edge))
    out, run = guided_evaluate(q, inst, options=Options(fanout=2), with_run=True)
    assert out.count() == 2 * n - 1
    split = [r for r in run.trace if r.get("outcome") == "split"]
    width = submodular_width(q, workloads.cardinalities(inst), run.n)
    assert split and all(r["ok"] and r["c_log"] <= width + 1e-9 for r in split)
    assert all(r["n_heavy"] <= r["heavy_bound"] for r in split if "n_heavy" in r)
    assert run.peak_rows <= 2 * (2 * n - 1) < n * n
    sizes = {}
    single_tree_evaluate(q, inst, 0, sizes)
    assert max(sizes.values()) == n * n + n - 1
    assert run.frame(spark).count() == len(run.trace)
    by_parent = {r["branch"]: r for r in run.trace}
    run_length = lambda r: 0 if r["kind"] != "light" else 1 + run_length(by_parent[r["parent"]])
    assert max(map(run_length, run.trace)) <= 2 ** len(q.variables)


def test_sandwich_and_rule_cover(spark):
    q = parse_rule(CYCLE.format("x, y, z, w"))
    data = dict(a=TWO_HUBS, b=TWO_HUBS, c=TWO_HUBS, d=TWO_HUBS)
    inst = Instance.load(q, tables(spark, **data))
    full = set(brute(q, data))
    _, run = guided_evaluate(q, inst, options=Options(fanout=4), with_run=True)
    for t, leaf in run.leaves:
        from widthjoin.acyclic import acyclic_evaluate, reduce_bags

        answers = set(rows(acyclic_evaluate(t, reduce_bags(leaf.relations, t), q.head)))
        node = leaf.node_query(q.head)
        own = set(rows(pairwise_evaluate(node, leaf)))
        assert own <= answers <= full
    names = sorted(q.variables)
    for s in bag_selectors(enumerate_decompositions(q))[:1]:
        covered = disjunctive_rule(q, inst, s, options=Options(fanout=8))
        have = {k: set(rows(v)) for k, v in covered.items()}
        assert all(any(tuple(x[names.index(v)] for v in columns(k)) in h for k, h in have.items()) for x in full)


def test_workload_sql_names(spark):
    for name in workloads.RULES:
        assert "SELECT DISTINCT" in workloads.sql(name)


def test_every_join_stays_within_its_bound_and_relations_within_theirs(spark):
    edge = [(i, j) for i in range(6) for j in range(6) if (i * j) % 5 < 2] + [(0, i) for i in range(14)]
    q = parse_rule("q(x, y, z) :- a(x, y), b(y, z), c(z, x)")
    inst = Instance.load(q, tables(spark, a=edge, b=edge, c=edge))
    for mode in ("batched", "separate"):
        out, run = guided_evaluate(q, inst, options=Options(fanout=2, light_mode=mode), with_run=True)
        split = [r for r in run.trace if r.get("outcome") == "split"]
        assert split and all(r["ok"] and r["n_rows"] <= r["row_bound"] * max(1, r["n_light"]) for r in split)
        assert rows(out) == rows(pairwise_evaluate(q, inst))


def test_parts_are_taken_together_within_the_bound():
    got = batches({0: 5, 1: 4, 2: 3, 3: 1}, Fraction(8))
    assert sorted(sum(got, [])) == [0, 1, 2, 3] and all(sum({0: 5, 1: 4, 2: 3, 3: 1}[k] for k in own) <= 8 for own in got) and len(got) == 2


def test_profiles_count_joins_without_making_them(spark):
    a = spark.createDataFrame([(1, i) for i in range(5)] + [(2, 9), (3, 1)], "w bigint, x bigint")
    b = spark.createDataFrame([(1, i) for i in range(3)] + [(2, 1), (7, 1), (7, 2)], "w bigint, y bigint")
    p = join_profile(a, b, frozenset("w"), 2, 1)
    assert (p.rows_x, p.rows_y, p.max_x, p.max_y, p.heavy_x, p.heavy_y, p.light_x, p.light_y, p.joined) == (7, 6, 5, 3, 1, 1, 1, 1, 16)
    t = p.turned()
    assert (t.rows_x, t.heavy_y, t.light_y, t.joined) == (6, 1, 1, 16)
    none = join_profile(a.limit(0), b.limit(0), frozenset("w"), 1, 1)
    assert none.joined == 0 and none.max_x == 0


def test_bounds_passed_in_must_keep_the_invariants(spark):
    q = parse_rule(CYCLE.format("x, z"))
    inst = Instance.load(q, tables(spark, a=TWO_HUBS, b=TWO_HUBS, c=TWO_HUBS, d=TWO_HUBS))
    stats = cardinalities(inst)
    closed, own = close_bounds(stats, inst, {k: Fraction(n) for k, n in inst.sizes.items()}, q.variables)
    assert not check_invariants(closed, own, stats, q.variables)
    assert rows(guided_evaluate(q, closed, stats, bounds=own)) == rows(guided_evaluate(q, inst))
    x, xy = frozenset("x"), frozenset("xy")
    for broken in (own | {xy: Fraction(1)}, {k: v for k, v in own.items() if k != x}, own | {frozenset("xyz"): Fraction(99)}, own | {frozenset(): Fraction(2)}, own | {x: own[xy] + 1}):
        assert check_invariants(closed, broken, stats, q.variables)
        with pytest.raises(ValueError):
            guided_evaluate(q, closed, stats, bounds=broken)


def test_answers_come_one_by_one_at_bounded_delay(spark):
    data = dict(a=TWO_HUBS, b=[(y, x) for x, y in TWO_HUBS], c=TWO_HUBS, d=[(y, x) for x, y in TWO_HUBS])
    for head in ("x, y", "x, y, z, w"):
        q = parse_rule(CYCLE.format(head))
        _, run = guided_evaluate(q, Instance.load(q, tables(spark, **data)), options=Options(fanout=2), with_run=True)
        for per in (10**6, 60):  # at once, and part by part
            got = list(enumerate_answers(q, run, per))
            assert sorted(a for a, _ in got) == brute(q, data)
            if per > 60:
                assert max(n for _, n in got) <= delay_bound(run)
    with pytest.raises(ValueError):
        next(enumerate_answers(q.with_head([]), run))


def test_delay_does_not_grow_with_the_star(spark):
    gaps, answers = [], []
    for n in (10, 80):
        q = parse_rule("q(x, y) :- e(x, y), e(y, z), e(z, w), e(w, x)")
        _, run = guided_evaluate(q, Instance.load(q, {"e": star(spark, n)}), options=Options(fanout=2), with_run=True)
        own = list(enumerate_answers(q, run))
        gaps.append(max(s for _, s in own))
        answers.append(len({a for a, _ in own}))
        assert len(own) == answers[-1]
    assert answers == [20, 160] and gaps[0] == gaps[1]


def test_unions_give_each_answer_once():
    def of(rows_):
        return TreeAnswers([("x", "y")], [()], [{(): rows_}], [set(rows_)], ("x", "y"))

    sets = [of([(1, 1), (2, 2), (3, 3)]), of([(3, 3), (4, 4), (1, 1)]), of([(1, 1)]), of([])]
    assert sorted(union_of(sets)) == [(1, 1), (2, 2), (3, 3), (4, 4)]


@pytest.mark.parametrize("name", ["src_star", "td_list", "udtf_decompositions", "udtf_widths", "width_certificate", "width_known"])
def test_queries_read_a_given_table(spark, tmp_path, name):
    made = lambda n, kinds: spark.createDataFrame(n, kinds)
    made([(i, i % 7) for i in range(40)], "o_orderkey bigint, o_custkey bigint").write.parquet(f"{tmp_path}/orders.parquet")
    made([(i, 100 * i + j) for i in range(40) for j in range(3 + (i % 4 > 0))], "l_orderkey bigint, l_partkey bigint").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = (measures.registry() | surface.registry())[name][0](spark, str(tmp_path)).collect()
    expected = {"n_rows": {150}, "n_orders": {10, 30}}
    for column in {"n_rows", "n_orders"} & set(got[0].asDict()):
        assert {r[column] for r in got} == expected[column]
    if name == "src_star":
        assert sorted(map(tuple, got)) == sorted([(i, 0) for i in range(1, 41)] + [(0, i) for i in range(1, 41)])
    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist"):
        (measures.registry() | surface.registry())[name][0](spark, str(tmp_path / "none")).collect()


def test_constants_sql_and_rules_by_name(spark):
    lines = spark.createDataFrame([(1, 2, "R"), (1, 3, "it's"[:2]), (4, 4, "R"), (5, None, "R")], "a bigint, b int, f string")
    assert rows(sql(spark, "q(x) :- lines(x, y, 'R')", {"lines": lines})) == [(1,), (4,)]
    assert rows(sql(spark, "q(x, y) :- lines(x, y, 'it')", {"lines": lines})) == [(1, 3)]
    assert rows(sql(spark, "q(f) :- lines(4, y, f)", {"lines": lines})) == [("R",)]
    assert rows(sql(spark, "SELECT DISTINCT p.a FROM lines p, lines AS r WHERE p.b = r.b AND r.a = p.a", {"lines": lines})) == [(1,), (4,)]
    for bad in ("q() :- lines(1, 2, 'x')", "q(x) :- lines(x, 'open, y)", "q(x) :- lines(x, __y, z)"):
        with pytest.raises(ValueError):
            parse_rule(bad)
    own = bind_atom(lines, {"v": "a + 1", "u": lines.b}, "f = 'R'")
    assert own.columns == ["v", "u"] and own.count() == 3


def test_running_totals_over_ranges(spark):
    r = random.Random(1)
    data = [(i, r.randint(0, 5)) for i in range(200)]
    df = spark.createDataFrame(data, "i bigint, n bigint").repartition(3)
    got = {x["i"]: (x["t"], x["n"]) for x in running_total(df, [F.desc("n"), F.asc("i")], "n", "t", 5).collect()}
    at = 0
    for i, n in sorted(data, key=lambda x: (-x[1], x[0])):
        at += n
        assert got[i] == (at, n)
    ranks = {x["n"]: x["r"] for x in dense_rank(df, "n", "r").collect()}
    assert ranks == {n: k for k, n in enumerate(sorted({n for _, n in data}, reverse=True), 1)}
    assert running_total(df.limit(0), [F.asc("i")], "n", "t").count() == 0


def test_relations_kept_on_the_way_are_deleted(spark):
    q = parse_rule("q(x, z) :- a(x, y), b(y, z)")
    before = set(os.listdir(os.path.dirname(scratch(spark).removeprefix("file:"))))
    out = cleaned(spark, lambda: guided_evaluate(q, Instance.load(q, tables(spark, a=TWO_HUBS, b=TWO_HUBS))))
    after = set(os.listdir(os.path.dirname(scratch(spark).removeprefix("file:"))))
    assert out.count() == len(brute(q, dict(a=TWO_HUBS, b=TWO_HUBS))) and len(after - before) == 1


def test_streams_leave_late_events_out(spark, tmp_path):
    hour = lambda h, m=0: datetime.datetime(2024, 1, 1 + h // 24, h % 24, m)
    events = spark.createDataFrame([(i, hour(h), 1, "a", 0.0, '{"k": 1}') for i, h in enumerate((0, 0, 3, 30, 60))], "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string")
    events.write.parquet(f"{tmp_path}/events.parquet")
    got = sorted((x["start"], x["n"]) for x in windows.late_events(spark, str(tmp_path)).collect())
    assert got == [(hour(0), 2), (hour(3), 1), (hour(30), 1), (hour(60), 1)]
    assert windows.drained(windows.distinct_edges(windows.file_stream(spark, str(tmp_path)), "100 days")).count() == 1
    assert sorted(x["n"] for x in windows.sliding(spark.read.parquet(f"{tmp_path}/events.parquet")).collect()) == [1] * 12 + [2] * 4
    assert sorted(x["n"] for x in windows.sessions(spark.read.parquet(f"{tmp_path}/events.parquet")).collect()) == [1, 1, 1, 2]


def scans(df):
    return df._jdf.queryExecution().optimizedPlan().toString().count("Relation [")


def test_the_plan_of_the_answers_does_not_grow_with_the_leaves(spark):
    q = parse_rule("q(x, y, z) :- a(x, y), b(y, z)")
    data = dict.fromkeys("ab", TWO_HUBS)
    inst = Instance.load(q, tables(spark, **data))
    t, = enumerate_decompositions(q)
    few, many = (evaluate_leaves(q, Run(1, 1, leaves=[(t, inst)] * n), True, spark, None) for n in (2, 8))
    assert scans(few) == scans(many) and rows(many) == brute(q, data)


def test_a_relation_whose_files_are_small_is_not_broadcast_if_its_rows_are_not(spark):
    many, _ = keep_counted(spark.range(1_200_000).selectExpr("CAST(0 AS BIGINT) AS x", "id % 2 AS y"))
    few, _ = keep_counted(spark.range(5).selectExpr("id AS x", "id AS z"))
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan(few.join(many, ["x"], "left_semi"))  # what Spark does on its own
    assert "SortMergeJoin" in plan(semijoin(few, project(many, {"x"}))) and "SortMergeJoin" in plan(semijoin(few, semijoin(many, few)))
    assert "BroadcastHashJoin" in plan(semijoin(many, few)) and rows(semijoin(few, many)) == [(0, 0)]


def test_a_table_of_the_dual_rules_is_one_scan_however_many_leaves_fill_it(spark):
    q = parse_rule(CYCLE.format("x, y, z, w"))
    inst = Instance.load(q, tables(spark, **dict.fromkeys("abcd", TWO_HUBS)))
    heads = bag_selectors(enumerate_decompositions(q))[0]
    made = disjunctive_rule(q, inst, heads, options=Options(fanout=1))
    assert made and all(scans(df) == 1 for df in made.values())
    assert all(rows(df) == sorted(set(rows(df))) for df in made.values())


def test_strings_that_only_join_are_numbered(spark):
    data = [("a", "one long line"), ("b", "one long line"), ("b", "two"), ("c", None), ("d", "three"), ("d", "two"), ("a", "two")]
    t = {"r": spark.createDataFrame(data, "doc string, line string")}
    cycle = parse_rule("q(d1) :- r(d1, l1), r(d2, l1), r(d2, l2), r(d1, l2)")
    own = workloads.numbered(cycle, t)["r"]
    assert dict(own.dtypes) == {"doc": "string", "line": "bigint"} and own.count() == 6  # a row without a line joins with nothing
    assert rows(guided_evaluate(cycle, Instance.load(cycle, {"r": own}))) == brute(cycle, {"r": data}) == [("a",), ("b",), ("d",)]
    for head in ("q(d1, l1)", "q(d1, l2)", "q(d1, l1, d2, l2)"):
        assert dict(workloads.numbered(parse_rule(f"{head} :- r(d1, l1), r(d2, l1), r(d2, l2), r(d1, l2)"), t)["r"].dtypes)["line"] == "string", head
    bool_query = parse_rule("q() :- r(x, y), r(y, z)")  # places joined with one another share their numbers
    both = workloads.numbered(bool_query, {"r": spark.createDataFrame([("a", "b"), ("b", "c")], "x string, y string")})["r"]
    assert set(dict(both.dtypes).values()) == {"bigint"} and guided_evaluate(bool_query, Instance.load(bool_query, {"r": both})).first()["answer"]


def test_without_splits_the_join_with_the_fewest_rows_is_made(spark):
    q, data, inst = many_nations(spark)
    out, run = guided_evaluate(q, inst, options=Options(split=False), with_run=True)
    assert run.peak_rows <= 480 and rows(out) == brute(q, data)  # 1800 rows by the nation alone


def test_shuffle_files_of_steps_that_are_over_go(spark, monkeypatch):
    monkeypatch.setattr(materialize, "LARGE", 1)
    on_disk = lambda: set(re.findall(r"shuffle_(\d+)_", spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ")))
    before = on_disk()
    q = parse_rule(CYCLE.format("x"))
    kept = Instance.load(q, {r: spark.range(2000).selectExpr("id % 70", "id % 30") for r in "abcd"})
    until = time.time() + 20
    while len(left := on_disk() - before) > 1 and time.time() < until:
        time.sleep(0.5)
    assert len(left) <= 1 and kept.sizes[frozenset("xy")] == 210


@pytest.mark.parametrize("engine", ["pairwise", "trivial"])
def test_joins_that_explode_shuffle_nothing_and_move_no_text(spark, tmp_path, engine):
    texts = [None, "", "x\nx\n ", *["a\nb"] * 9, "b\nc", "c\na", "é\nb", *[f"own {i}\na" for i in range(5)]]
    spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    got = workloads.run(spark, str(tmp_path), "w06", engine)
    of = {(i, x) for i, t in enumerate(texts) for x in (t or "").split("\n") if x.strip()}
    want = {(d1, d2, l1, l2) for d1, l1 in of for d2, l in of if l == l1 for d, l2 in of if d == d2 and (d1, l2) in of}
    assert got.columns == ["d1", "d2", "l1", "l2"] and got.count() == len(want)
    assert {tuple(r) for r in got.collect()} == want
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert plan.count("BroadcastHashJoin") >= 2 and "ENSURE_REQUIREMENTS" not in plan  # the only shuffles deal out the first atoms


def test_joins_of_a_crowded_hub_stay_where_the_hub_is(spark, monkeypatch):
    q = parse_rule("q(x, y) :- a(x, y), a(y, z), a(z, w), a(w, x)")
    inst = Instance.load(q, {"a": star(spark, 200)})
    got = pairwise_evaluate(q, inst)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert plan.count("BroadcastHashJoin") == 3 and "SortMergeJoin" not in plan
    assert "LeftSemi" in plan
    assert rows(got) == rows(star(spark, 200).select(F.col("a").alias("x"), F.col("b").alias("y")))
    spread = Instance.load(q, {"a": spark.createDataFrame([(i, i + 1) for i in range(50)] + [(3, 2)], "a bigint, b bigint")})
    assert rows(pairwise_evaluate(q, spread)) == [(2, 3), (3, 2)]


def dense_and_sparse(spark):
    """Four ternary relations over lines of orders: two of them share few distinct keys, two share almost as many as they have rows."""
    n = 4000
    line = spark.range(n).selectExpr("id AS o", "id % 1999 AS p", "id % 7 AS s", "id % 5 AS l")
    q = parse_rule("q(o, p, s, l) :- a(o, p, s), b(p, s, l), c(s, l, o), d(l, o, p)")
    return q, {k: line.select(*v) for k, v in {"a": "ops", "b": "psl", "c": "slo", "d": "lop"}.items()}, n


def test_of_pairs_with_like_bounds_that_with_the_fewest_expected_rows_is_joined(spark, monkeypatch):
    monkeypatch.setattr("widthjoin.guided.LARGE", 1)
    monkeypatch.setattr("widthjoin.acyclic.LARGE", 1)
    q, own, n = dense_and_sparse(spark)
    got, run = guided_evaluate(q, Instance.load(q, own), with_run=True)
    assert run.peak_rows <= 2 * n and len(run.leaves) == 1 and all(r.get("ok", True) for r in run.trace)
    assert rows(got) == sorted((r["l"], r["o"], r["p"], r["s"]) for r in spark.range(n).selectExpr("id AS o", "id % 1999 AS p", "id % 7 AS s", "id % 5 AS l").collect())


def test_a_bag_is_not_semijoined_by_what_its_rows_agree_with(spark):
    a, b = (keep_counted(df)[0] for df in tables(spark, a=[(1, 2), (3, 4)], b=[(2, 5)]).values())
    a, b = a.toDF("x", "y"), b.toDF("y", "z")
    xy, yz, y = frozenset("xy"), frozenset("yz"), project(b, {"y"})
    joined = keep_counted(natural_join(a, b))[0]
    assert reduced({xy: a, yz: b, frozenset("y"): y}, xy | yz, joined) is joined
    other = spark.createDataFrame([(7,)], "y bigint")
    assert reduced({xy: a, yz: b, frozenset("y"): other}, xy | yz, joined).count() == 0


def test_rows_do_not_agree_with_variables_that_they_lack(spark):
    a, b = (df.toDF(*c) for df, c in zip(tables(spark, a=[(1, 2)], b=[(2, 5)]).values(), ("xy", "yz"), strict=True))
    xy, z = semijoin(a, b), spark.createDataFrame([(5,), (6,)], "z bigint")
    joined = natural_join(xy, z)
    assert rows(reduced({frozenset("xy"): a, frozenset("yz"): b}, frozenset("xyz"), joined)) == [(1, 2, 5)]
