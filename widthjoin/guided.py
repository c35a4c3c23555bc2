"""The guided evaluator: split data where the size bounds break submodularity, join where a bound allows it, stop when a tree is covered.

The driver works through a queue of branches. A branch is an instance, an
augmented form of the input, and bounds for its relations. All decisions come
from bounds and a few measured scalars; rows stay in Spark. Splits cover every
row, and every relation stays within its bound: a join is made only where the
degrees, counted before, say that it is no larger.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .acyclic import acyclic_boolean, acyclic_evaluate, reduce_bags
from .bounds import EMPTY, Bounds, Defect, defects, low_family, lowest_defect, satisfies, subsets
from .closure import close_bounds
from .decomposition import TreeDecomposition, covered_by, enumerate_decompositions
from .instance import Instance, columns, natural_join, project, semijoin
from .materialize import LARGE, agreeing, collected, keep, keep_counted, keep_union
from .partition import equal_degree_parts, heavy_light
from .query import ConjunctiveQuery, Vars, show
from .statistics import Statistics, cardinalities, check_statistics


@dataclass
class Options:
    """eps or fanout: the slack of a light part's degree, N^eps; auto: eps 1/4 below a million rows, 1/8 above.

    light_mode: "separate" makes a branch of each light part, as the analysis has it; "batched" makes as few
    branches as keep every join within c: a pair whose whole join is that small is not split at all, and
    light parts are taken together while the sum of their joins stays within c.
    orientation: "auto" splits the side with the smaller measured degree, relative to what the bounds allow.
    """

    eps: float | None = None
    fanout: int | None = None
    light_mode: str = "batched"
    tie_break: str | Callable[[Defect], tuple] = "default"
    orientation: str = "auto"
    heavy_reduce: bool = True
    prereduce: bool = False
    verify: bool = False
    group_leaves: bool = True
    split: bool = True
    max_depth: int | None = None
    parallel: int = 4


@dataclass
class Branch:
    number: int
    parent: int
    kind: str
    inst: Instance
    bounds: Bounds | None
    depth: int


@dataclass
class Run:
    """What a run did: a trace row for each branch, leaves with their tree or bag, N and the fan-out."""

    n: int
    fanout: int
    trace: list[dict] = field(default_factory=list)
    leaves: list[tuple[object, Instance]] = field(default_factory=list)

    def frame(self, spark: SparkSession) -> DataFrame:
        kinds = {"branch": "int", "parent": "int", "kind": "string", "depth": "int", "outcome": "string", "x": "string", "y": "string", "w": "string", "c_size": "double", "c_log": "double", "theta": "double", "threshold": "bigint", "n_rows": "bigint", "row_bound": "double", "ok": "boolean", "n_heavy": "bigint", "heavy_bound": "double", "n_light": "int", "n_relations": "int", "largest": "bigint", "phi": "double", "low_family": "int"}
        return spark.createDataFrame([tuple(r.get(k) for k in kinds) for r in self.trace], ", ".join(f"{k} {v}" for k, v in kinds.items()))

    @property
    def peak_rows(self) -> int:
        return max([r["n_rows"] for r in self.trace if r.get("n_rows") is not None] + [r["largest"] for r in self.trace if r.get("largest") is not None] + [0])


def fan_out(n: int, options: Options) -> int:
    if options.fanout is not None:
        return max(1, options.fanout)
    eps = options.eps if options.eps is not None else (0.25 if n < 1_000_000 else 0.125)
    return max(1, math.ceil(max(n, 1) ** eps))


@dataclass
class Profile:
    """Of two relations over common variables: rows, largest degrees, heavy keys that have a partner, and the rows of their join, whole and without heavy keys."""

    rows_x: int
    rows_y: int
    max_x: int
    max_y: int
    heavy_x: int
    heavy_y: int
    light_x: int
    light_y: int
    joined: int

    def turned(self) -> Profile:
        return Profile(self.rows_y, self.rows_x, self.max_y, self.max_x, self.heavy_y, self.heavy_x, self.light_y, self.light_x, self.joined)


def join_profile(rx: DataFrame, ry: DataFrame, w: Vars, limit_x: int, limit_y: int) -> Profile:
    """From degrees alone, in one job: no row of the join is made. light_y: joined rows of the keys that are not heavy in ry."""
    own, n = columns(w), lambda c: F.coalesce(c, F.lit(0)).cast("decimal(19,0)")
    dx, dy = (r.groupBy(*own).agg(F.count(F.lit(1)).alias(c)) for r, c in ((rx, "nx"), (ry, "ny")))
    j = dx.join(dy, own, "full_outer").select(n(F.col("nx")).alias("nx"), n(F.col("ny")).alias("ny"))
    total = lambda c: F.coalesce(F.sum(c), F.lit(0)).cast("decimal(38,0)")
    both = F.col("nx") * F.col("ny")
    r = j.agg(
        total(F.col("nx")), total(F.col("ny")), F.coalesce(F.max("nx"), F.lit(0)), F.coalesce(F.max("ny"), F.lit(0)),
        F.count_if((F.col("nx") > limit_x) & (F.col("ny") > 0)), F.count_if((F.col("ny") > limit_y) & (F.col("nx") > 0)),
        total(F.when(F.col("nx") <= limit_x, both)), total(F.when(F.col("ny") <= limit_y, both)), total(both),
    ).first()
    return Profile(*map(int, r))


def smallest_join(inst: Instance, bounds: Bounds, bags: list[Vars], counted: dict) -> Defect | None:
    """Where nothing is split, bounds do not hold for joins on keys of uneven degree; so, of the pairs of measured relations that make one inside a bag, that whose join has the fewest rows by count.
    counted: joins that are known already."""
    own = inst.relations
    found = [d for d in defects(bounds) if d.w and {d.x, d.y} <= set(inst.sizes) & set(own) and d.x | d.y not in own and any(d.x | d.y <= b for b in bags)]
    for x, y in [(own[d.x], own[d.y]) for d in found if len(found) > 1]:
        if (x, y) not in counted:
            counted[x, y] = join_profile(x, y, frozenset(x.columns) & frozenset(y.columns), 0, 0).joined
    return min(found, key=lambda d: (counted.get((own[d.x], own[d.y]), 0), len(d.x | d.y), show(d.x | d.y), show(d.y)), default=None)


def distinct_keys(inst: Instance, found: list[Defect], counted: dict) -> None:
    """counted gets, by relation and common variables, about how many keys the pairs' sides have: one scan a relation, of which nothing is shuffled."""
    for e in {s for d in found for s in (d.x, d.y)}:
        r = inst.relations[e]
        if own := sorted({d.w for d in found if e in (d.x, d.y) and (r, d.w) not in counted}, key=sorted):
            got = r.agg(*[F.approx_count_distinct(F.xxhash64(*columns(w))) for w in own]).first()
            counted |= {(r, w): max(int(n), 1) for w, n in zip(own, got, strict=True)}


def likely_join(inst: Instance, bounds: Bounds, bags: list[Vars], counted: dict, slack: int) -> Defect | None:
    """Of the pairs of measured relations inside a bag whose bounds are within the slack of the lowest, that whose join is expected to have the fewest rows, if they are within it too.

    Bounds of relations that are about as long differ little, the rows of their joins much: a pair that shares few distinct keys
    is split into many branches. The estimates choose the pair alone: its join is counted from degrees before it is made.
    """
    low, own = lowest_defect(bounds), inst.relations
    if low is None:
        return None
    most = low.value * slack
    found = [d for d in defects(bounds) if d.w and d.value <= most and {d.x, d.y} <= set(inst.sizes) & set(own) and d.x | d.y not in own and any(d.x | d.y <= b for b in bags)]
    if len(found) < 2:
        return None
    distinct_keys(inst, found, counted)
    rows = {d: inst.sizes[d.x] * inst.sizes[d.y] / max(counted[own[d.x], d.w], counted[own[d.y], d.w]) for d in found}
    best = min(found, key=lambda d: (rows[d], show(d.x | d.y), show(d.y), show(d.x)))
    return best if rows[best] <= most else None


def batches(counts: dict[int, int], most: Fraction) -> list[list[int]]:
    """Parts in as few groups as first fit by falling size finds, each of at most `most` rows; a part never has more."""
    out: list[tuple[int, list[int]]] = []
    for k in sorted(counts, key=lambda k: (-counts[k], k)):
        i = next((i for i, (n, _) in enumerate(out) if n + counts[k] <= most), None)
        if i is None:
            out.append((counts[k], [k]))
        else:
            out[i] = (out[i][0] + counts[k], [*out[i][1], k])
    return [own for _, own in out]


def preference(options: Options, bags: list[Vars], light_side: dict) -> Callable[[Defect], tuple] | None:
    """Order of tied defects: unions inside a bag, splits on nothing, small unions; or the cheaper join, or small unions, or names."""
    if callable(options.tie_break):
        return options.tie_break
    if options.tie_break == "lexicographic":
        return lambda d: (show(d.x), show(d.y))
    if options.tie_break == "smallest_union":
        return lambda d: (len(d.x | d.y), show(d.x | d.y))
    if options.tie_break == "cheapest_join":
        return lambda d: (light_side.get(d.x, math.inf) + light_side.get(d.y, math.inf), show(d.x | d.y))
    return lambda d: (not any(d.x | d.y <= b for b in bags), bool(d.w), len(d.x | d.y), show(d.x | d.y), show(d.y))


def prereduced(inst: Instance) -> Instance:
    """Every relation reduced by every other that shares variables, once in each direction."""
    out = inst.copy()
    keys = sorted(out.relations, key=lambda k: (len(k), sorted(k)))
    for order in (keys, keys[::-1]):
        for a in order:
            df = out.relations[a]
            for b in order:
                if a != b and a & b:
                    df = semijoin(df, project(out.relations[b], a & b))
            out.relations[a] = keep(df)  # written before others use it, so that plans do not nest
    out.sizes = {}
    out.measure()
    return out


def explore(q: ConjunctiveQuery, inst: Instance, stats: Statistics | None, options: Options, stop: Callable[[set[Vars]], object | None], bags: list[Vars], early: Callable[[object, Instance], bool] | None = None, bounds: Bounds | None = None) -> Run:
    """Run the branches until `stop` names what each leaf has covered. early: called on a leaf; true ends the run."""
    if not inst.includes(q):
        raise ValueError("the instance lacks relations of the query")
    n = inst.size
    if options.prereduce:
        inst = prereduced(inst)
    stats = stats if stats is not None else cardinalities(inst)
    if bounds is not None and (broken := check_invariants(inst, bounds, stats, q.variables)):
        raise ValueError(f"the bounds break invariants: {broken}")
    if options.verify and (bad := check_statistics(inst, stats)):
        raise ValueError(f"the instance violates statistics: {[(show(t.y), show(t.x), t.max_degree, m) for t, m in bad]}")
    run, counted = Run(n, fan_out(n, options)), {}
    vars_ = q.variables
    deepest = options.max_depth or depth_limit(len(vars_), n, run.fanout)

    def step(b: Branch) -> tuple[dict, list[tuple[str, Instance, Bounds | None]], object | None]:
        """A branch's trace row, its children, and what it has covered, if it is a leaf."""
        row = {"branch": b.number, "parent": b.parent, "kind": b.kind, "depth": b.depth}
        if b.bounds is None:
            sizes = b.inst.measure()
            row["largest"] = max(sizes.values(), default=0)
            if not all(sizes.values()):
                return row | {"outcome": "empty"}, [], None
            b.bounds = {EMPTY: Fraction(1)} | {k: Fraction(v) for k, v in sizes.items()}
            row["phi"] = potential(sizes, vars_, n)
            b.inst, b.bounds = close_bounds(stats, b.inst, b.bounds, vars_)
        row["n_relations"] = len(b.inst.relations)
        if (leaf := stop(set(b.inst.relations))) is not None:
            return row | {"outcome": "leaf"}, [], leaf
        if b.depth >= deepest:
            raise RuntimeError(f"branch {b.number} is {b.depth} deep; trace: {run.trace[-5:]}")
        likely = None
        if options.split:
            choose = n >= LARGE and options.light_mode != "separate" and options.tie_break == "default"
            d = likely = likely_join(b.inst, b.bounds, bags, counted, run.fanout) if choose else None
        else:
            d = smallest_join(b.inst, b.bounds, bags, counted)
        d = d or lowest_defect(b.bounds, preference(options, bags, b.inst.sizes))
        if d is None:
            raise RuntimeError("no defect is left and no tree is covered")
        whole = options.light_mode != "separate"
        rx, ry = b.inst.relations[d.x], b.inst.relations[d.y]
        profile = None
        if d.w and options.split:
            profile = join_profile(rx, ry, d.w, *(int(b.bounds[side] / b.bounds[d.w] * run.fanout) for side in (d.x, d.y)))
            if options.orientation == "auto" and profile.max_x * b.bounds[d.y] < profile.max_y * b.bounds[d.x]:
                d, rx, ry, profile = Defect(d.y, d.x, d.value), ry, rx, profile.turned()
            b.inst.sizes[d.x], b.inst.sizes[d.y] = profile.rows_x, profile.rows_y
            collected(rx.sparkSession, n)
            if likely and d.value < profile.joined <= d.value * run.fanout:  # within the slack, it is made whole and bounded by its own rows
                d = Defect(d.x, d.y, Fraction(profile.joined))
        theta = b.bounds[d.y] / b.bounds[d.w]
        limit = int(theta * run.fanout)
        row |= {"outcome": "split", "x": show(d.x), "y": show(d.y), "w": show(d.w), "c_size": float(d.value), "c_log": math.log(d.value) / math.log(max(n, 2)), "theta": float(theta), "threshold": limit, "low_family": len(low_family(b.bounds, d.value))}
        union = d.x | d.y

        def joined(part: DataFrame) -> DataFrame:
            have = b.inst.relations.get(union)  # never rebuilt, only filtered by both sides
            return natural_join(rx, part) if have is None else natural_join(semijoin(have, rx), part) if len(part.columns) > len(d.y) else semijoin(semijoin(have, rx), part)

        heavy, light, children = None, ry, []
        fits = profile is None or (whole and profile.joined <= d.value)
        if profile is not None:
            row |= {"n_heavy": 0 if fits else profile.heavy_y, "heavy_bound": profile.rows_y / max(limit, 1)}
            if row["n_heavy"]:
                heavy = keep(semijoin(heavy_light(ry, d.w, limit)[0], rx))
                light = agreeing(ry.join(heavy, columns(d.w), "left_anti").select(ry.columns), ry)
        sizes: list[int] = []

        def light_child(own: DataFrame, size: int) -> None:
            child = b.inst.copy()
            child.relations[union], child.sizes[union] = own, size
            sizes.append(size)
            if size:
                children.append(("light", *close_bounds(stats, child, b.bounds | {union: d.value}, vars_)))

        if not d.w or not options.split or fits or (whole and profile.light_y <= d.value):
            light_child(*keep_counted(joined(light)))
        else:
            own = keep(joined(agreeing(equal_degree_parts(light, d.w, int(theta)), light)))
            counts = {r["__part"]: r["n"] for r in own.groupBy("__part").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most twice the fan-out
            for batch in batches(counts, d.value) if whole else [[k] for k in sorted(counts)]:
                light_child(agreeing(own.filter(F.col("__part").isin(batch)).drop("__part"), own), sum(counts[k] for k in batch))
        row |= {"n_rows": sum(sizes), "row_bound": float(d.value), "ok": max(sizes, default=0) <= d.value, "n_light": len(sizes)}
        if heavy is not None:
            child = b.inst.copy()
            child.augment(d.w, heavy)
            child.relations[d.w] = heavy if d.w not in b.inst.relations else keep(child.relations[d.w])
            if options.heavy_reduce:
                child.relations[d.y], child.sizes[d.y] = keep_counted(semijoin(ry, child.relations[d.w]))
            children.append(("heavy", child, None))
        return row, children, None

    # branches of one depth do not depend on each other: their small jobs run side by side
    wave, made = [Branch(0, -1, "root", inst, bounds, 0)], 1
    with ThreadPoolExecutor(options.parallel) as pool:
        while wave:
            after = []
            for b, (row, children, leaf) in zip(wave, list(pool.map(step, wave)), strict=True):
                run.trace.append(row)
                if leaf is not None:
                    run.leaves.append((leaf, b.inst))
                    if early and early(leaf, b.inst):
                        return run
                for kind, child, lowered in children:
                    after.append(Branch(made, b.number, kind, child, lowered, b.depth + 1))
                    made += 1
            wave = after
            for df in list(inst.relations.values())[:1]:
                collected(df.sparkSession, n)
    for df in list(inst.relations.values())[:1]:  # once more, when the threads that made the last joins are gone
        collected(df.sparkSession, n)
    return run


def depth_limit(n_vars: int, n: int, fanout: int) -> int:
    """What the analysis allows: at most 2^V light branches between two heavy ones, each of which lowers a potential of at most 2^V (V + 1) by the slack's exponent."""
    eps = max(math.log(max(fanout, 2)) / math.log(max(n, 3)), 1e-3)
    return 2**n_vars * (math.ceil(2**n_vars * (n_vars + 1) / eps) + 1)


def potential(sizes: dict[Vars, int], vars_: Vars, n: int) -> float:
    """Sum of logarithmic sizes over all variable sets, those without a relation charged above the full join."""
    base = math.log(max(n, 2))
    present = sum(math.log(max(v, 1)) / base for v in sizes.values())
    return present + (2 ** len(vars_) - 1 - len(sizes)) * (len(vars_) + 1)


def check_invariants(inst: Instance, bounds: Bounds, stats: Statistics, vars: Vars) -> list[str]:
    """Why bounds may not be passed in: a relation without a bound or larger than it, a bound without a relation, no monotone function, a violated constraint."""
    own = bounds | {EMPTY: bounds.get(EMPTY, Fraction(1))}
    out = [f"{show(k)}: {n} rows, bound {own.get(k)}" for k, n in inst.measure().items() if k and (k not in own or n > own[k])]
    out += [f"{show(k)}: a bound without a relation" for k in own if k and k not in inst.relations]
    out += [] if own[EMPTY] == 1 else ["the empty set is not bounded by one row"]
    for x in subsets(vars):
        for y in own:
            if x < y and (x not in own or own[x] > own[y]):
                out.append(f"{show(x)} is above {show(y)}")
    return out + ([] if satisfies(own, stats) else ["a degree constraint does not hold"])


def leaf_stop(trees: list[TreeDecomposition]) -> Callable[[set[Vars]], TreeDecomposition | None]:
    return lambda signatures: next((t for t in trees if covered_by(t, signatures)), None)


def grouped(leaves: list[tuple[TreeDecomposition, Instance]]) -> list[tuple[TreeDecomposition, dict[Vars, DataFrame]]]:
    """One set of bags a tree: its leaves' reduced bags together. Each still satisfies every atom that it covers.

    Of several leaves each bag is written, side by side, and read by one scan: a union of their plans would be as long as all
    branches together, and the semijoins along the tree use it several times. Rows of several leaves come several times.
    """
    if len(leaves) == 1:
        return [(t, reduce_bags(i.relations, t)) for t, i in leaves]
    by: dict[TreeDecomposition, dict[Vars, list[DataFrame]]] = {}
    for t, inst in leaves:
        for k, df in reduce_bags(inst.relations, t).items():
            by.setdefault(t, {}).setdefault(k, []).append(df)
    return [(t, {k: keep_union(parts) for k, parts in bags.items()}) for t, bags in by.items()]


def evaluate_leaves(q: ConjunctiveQuery, run: Run, group: bool, spark: SparkSession, schema) -> DataFrame:
    """Distinct answers over the head, columns by name."""
    trees = grouped(run.leaves) if group else [(t, reduce_bags(i.relations, t)) for t, i in run.leaves]
    answers = [acyclic_evaluate(t, bags, q.head, group and len(run.leaves) > 1) for t, bags in trees]
    if not answers:
        return spark.createDataFrame([], schema)
    out = answers[0]
    for a in answers[1:]:
        out = out.union(a)
    return out.distinct() if len(answers) > 1 else out


def guided_evaluate(q: ConjunctiveQuery, inst: Instance, stats: Statistics | None = None, options: Options | None = None, bounds: Bounds | None = None, with_run: bool = False):
    """The query's answers; a Boolean query gives one row, answer."""
    options = options or Options()
    trees = enumerate_decompositions(q)
    bags = [x for t in trees for x in t.bags]
    spark = next(iter(inst.relations.values())).sparkSession
    if q.is_boolean:
        found = []

        def early(t, leaf):
            found.append(acyclic_boolean(t, reduce_bags(leaf.relations, t)))
            return found[-1]

        run = explore(q, inst, stats, options, leaf_stop(trees), bags, early, bounds)
        out = spark.createDataFrame([(any(found),)], "answer boolean")
    else:
        run = explore(q, inst, stats, options, leaf_stop(trees), bags, None, bounds)
        kinds = {c: t for df in inst.relations.values() for c, t in df.dtypes}
        out = evaluate_leaves(q, run, options.group_leaves, spark, ", ".join(f"{c} {kinds[c]}" for c in columns(q.head)))
    return (out, run) if with_run else out
