"""Relations as sets of rows, and instances: at most one relation for each set of variables."""

from __future__ import annotations

from collections.abc import Iterable, Mapping
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .materialize import agreeing, at_most, collected, count_all, keep_counted, most_rows, too_long
from .query import Atom, ConjunctiveQuery, Vars


def columns(vars: Iterable[str]) -> list[str]:
    return sorted(vars)


def as_set(df: DataFrame, unique: bool = False) -> DataFrame:
    """Set semantics: no null in any column, no row twice. unique: the rows are known to be distinct."""
    df = df.dropna()
    return df if unique else df.distinct()


def project(rel: DataFrame, vars: Iterable[str]) -> DataFrame:
    own = columns(vars)
    if own == sorted(rel.columns):
        return rel
    out = at_most(rel.select(own).distinct(), most_rows(rel))
    agreeing(rel, out)
    return out


def select_eq(rel: DataFrame, values: Mapping[str, object]) -> DataFrame:
    for v, x in values.items():
        rel = rel.filter(F.col(v) == F.lit(x))
    return rel


def semijoin(rel: DataFrame, by: DataFrame) -> DataFrame:
    """Rows of rel that agree with some row of `by`; without common variables, all of them if `by` has a row."""
    on = sorted(set(rel.columns) & set(by.columns))
    if on:
        out = rel.join(by.hint("merge") if too_long(by) else by, on, "left_semi").select(columns(rel.columns))
        return agreeing(at_most(out, most_rows(rel)), rel, *([by] if len(on) == len(by.columns) else []))
    return rel if not by.isEmpty() else rel.limit(0)


def natural_join(a: DataFrame, b: DataFrame) -> DataFrame:
    """On the common variables; a product where there are none (one side then consists of few keys, or the query asks for it)."""
    on = sorted(set(a.columns) & set(b.columns))
    out = a.join(b.hint("merge") if too_long(a) and too_long(b) else b, on) if on else a.crossJoin(b)
    return agreeing(out.select(columns(out.columns)), a, b)


def met(long: DataFrame, by: DataFrame) -> DataFrame:
    """natural_join() of a long side that stays where it is and a relation that is sent to every task: nothing of the long side is shuffled.

    Several common integers are looked up by one hash of 64 bits and then compared; a relation without new variables only filters.
    """
    on, kinds = sorted(set(long.columns) & set(by.columns)), dict(by.dtypes)
    own = by.select(*[F.col(c).alias(f"__by_{c}") for c in by.columns])
    if len(on) > 1 and all(kinds[c] == "bigint" for c in on):
        own = own.withColumn("__key", F.xxhash64(*[f"__by_{c}" for c in on]))
        same = [F.xxhash64(*on) == F.col("__key"), *[F.col(c).bitwiseXOR(F.col(f"__by_{c}")) == 0 for c in on]]
    else:
        same = [F.col(c) == F.col(f"__by_{c}") for c in on]
    more = [c for c in by.columns if c not in on]
    out = long.join(F.broadcast(own), reduce(Column.__and__, same), "inner" if more else "left_semi")
    return out.select(*long.columns, *[F.col(f"__by_{c}").alias(c) for c in more])


@dataclass
class Instance:
    """relations: variable set -> DataFrame with these columns, sorted by name. sizes: those that are measured.

    texts: some relations once more, with the strings that numbers stand for; variable v's are in column __text_v.
    """

    relations: dict[Vars, DataFrame] = field(default_factory=dict)
    sizes: dict[Vars, int] = field(default_factory=dict)
    texts: dict[Vars, DataFrame] = field(default_factory=dict)

    @staticmethod
    def load(query: ConjunctiveQuery, tables: Mapping[str, DataFrame], materialize: bool = True) -> Instance:
        """Bind the atoms: a table's columns are an atom's variables by position. Atoms over the same variables are intersected."""
        return Instance.of_atoms(((atom, tables[atom.relation]) for atom in query.atoms), materialize)

    @staticmethod
    def of_atoms(pairs: Iterable[tuple[Atom, DataFrame]], materialize: bool = True) -> Instance:
        out = Instance()
        for atom, table in pairs:
            out.augment(atom.set, bound(atom, table))
        if materialize:  # two at a time are written and counted side by side
            for some in (list(out.relations)[i : i + 2] for i in range(0, len(out.relations), 2)):
                with ThreadPoolExecutor(2) as pool:
                    made = list(pool.map(keep_counted, [out.relations[k] for k in some]))
                for k, (df, n) in zip(some, made, strict=True):
                    out.relations[k], out.sizes[k] = df, n
                collected(df.sparkSession, sum(out.sizes.values()))
        out.measure()
        return out

    def copy(self) -> Instance:
        return Instance(dict(self.relations), dict(self.sizes), dict(self.texts))

    def augment(self, vars: Vars, df: DataFrame) -> None:
        """Add a relation, or intersect the one over these variables with it."""
        df = df if df.columns == columns(vars) else agreeing(at_most(df.select(columns(vars)), most_rows(df)), df)
        own = self.relations.get(vars)
        self.relations[vars] = df if own is None else semijoin(own, df)
        self.sizes.pop(vars, None)

    def measure(self) -> dict[Vars, int]:
        """Sizes of all relations; only what has changed is counted, in one job."""
        self.sizes |= count_all({k: v for k, v in self.relations.items() if k not in self.sizes})
        return self.sizes

    @property
    def size(self) -> int:
        """Total rows of all relations."""
        return sum(self.measure().values())

    def includes(self, query: ConjunctiveQuery) -> bool:
        return query.edges <= set(self.relations)

    def matches(self, query: ConjunctiveQuery) -> bool:
        return query.edges == set(self.relations)

    def node_query(self, head: Vars) -> ConjunctiveQuery:
        """The query whose body is the join of all relations here."""
        return ConjunctiveQuery(head, tuple(Atom("_".join(columns(k)), tuple(columns(k))) for k in self.relations if k))


def bound(atom: Atom, table: DataFrame) -> DataFrame:
    """An atom's relation: a constant or a repeated variable is a filter; null rows and doubles go; integers are widened, so that variables join across tables."""
    if len(table.columns) != len(atom.vars) + len(atom.values):
        raise ValueError(f"{atom.relation} has {len(table.columns)} columns, the atom has {len(atom.vars) + len(atom.values)} places")
    kinds = dict(table.dtypes)
    own = table.select(*[widened(F.col(f"`{c}`"), kinds[c]).alias(f"c{i}") for i, c in enumerate(table.columns)])
    first: dict[str, int] = {}
    own = select_eq(own, {f"c{i}": x for i, x in atom.values})
    places = [i for i in range(len(table.columns)) if i not in dict(atom.values)]
    for i, v in zip(places, atom.vars, strict=True):
        if v in first:
            own = own.filter(F.col(f"c{i}") == F.col(f"c{first[v]}"))
        else:
            first[v] = i
    return as_set(own.select(*[F.col(f"c{first[v]}").alias(v) for v in columns(first)]))


def widened(c, kind: str):
    if kind in ("tinyint", "smallint", "int"):
        return c.cast("bigint")
    if kind in ("double", "float"):  # one zero and one NaN
        return F.when(c == 0, F.lit(0.0)).when(F.isnan(c), F.lit(float("nan"))).otherwise(c)
    return c
