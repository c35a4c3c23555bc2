"""Conjunctive queries: atoms, head, and two notations for them."""

from __future__ import annotations

import re
from collections import defaultdict
from dataclasses import dataclass

Vars = frozenset[str]


def show(s) -> str:
    """A variable set in print: sorted, joined."""
    return "".join(sorted(s)) if all(len(v) == 1 for v in s) else ",".join(sorted(s))


@dataclass(frozen=True)
class Atom:
    """values: (position, constant) of the places of the relation that hold no variable."""

    relation: str
    vars: tuple[str, ...]
    values: tuple[tuple[int, object], ...] = ()

    @property
    def set(self) -> Vars:
        return frozenset(self.vars)


@dataclass(frozen=True)
class ConjunctiveQuery:
    head: Vars
    atoms: tuple[Atom, ...]

    def __post_init__(self):
        if not self.atoms:
            raise ValueError("a query needs an atom")
        if not self.head <= self.variables:
            raise ValueError(f"head variables {sorted(self.head - self.variables)} stand in no atom")

    @property
    def variables(self) -> Vars:
        return frozenset().union(*(a.set for a in self.atoms))

    @property
    def edges(self) -> frozenset[Vars]:
        """The hypergraph: variable sets of the atoms."""
        return frozenset(a.set for a in self.atoms)

    @property
    def is_boolean(self) -> bool:
        return not self.head

    @property
    def is_full(self) -> bool:
        return self.head == self.variables

    def with_head(self, head) -> ConjunctiveQuery:
        return ConjunctiveQuery(frozenset(head), self.atoms)


TERM = r"(\w+)\s*\(((?:[^()']|'[^']*')*)\)"


def constant(token: str):
    """The value of a number or of a string in single quotes; None: it is neither."""
    if re.fullmatch(r"'[^']*'", token):
        return token[1:-1]
    if re.fullmatch(r"-?\d+", token):
        return int(token)
    return float(token) if re.fullmatch(r"-?\d+\.\d+", token) else None


def parse_rule(text: str) -> ConjunctiveQuery:
    """`q(x, z) :- r(x, y), s(y, z, 'F', 3)`. A constant selects the rows that have it in its place."""
    head, mark, body = text.partition(":-")
    if not mark:
        raise ValueError("a rule needs ':-'")
    terms = re.findall(TERM, body)
    left = re.fullmatch(r"\s*\w+\s*\(([^()]*)\)\s*", head)
    if not terms or not left or re.sub(rf"{TERM}|[,.\s]", "", body):
        raise ValueError(f"not a rule: {text!r}")
    names = lambda s: tuple(v.strip() for v in re.findall(r"'[^']*'|[^,']+", s) if v.strip())
    atoms = []
    for r, a in terms:
        own = names(a)
        values = tuple((i, constant(v)) for i, v in enumerate(own) if constant(v) is not None)
        vars_ = tuple(v for v in own if constant(v) is None)
        if bad := [v for v in vars_ if not re.fullmatch(r"[A-Za-z]\w*", v)]:
            raise ValueError(f"not variable names: {bad}")
        if not vars_:
            raise ValueError(f"an atom without variables: {r}({a})")
        atoms.append(Atom(r, vars_, values))
    return ConjunctiveQuery(frozenset(names(left[1])), tuple(atoms))


def parse_sql(text: str) -> tuple[ConjunctiveQuery, dict[str, dict[str, str]]]:
    """`SELECT DISTINCT a.x, b.y FROM t a, u b WHERE a.k = b.k`: the query, and for each alias {column: variable}.

    Equalities of columns make variables; anything else in WHERE is refused.
    """
    m = re.fullmatch(r"\s*select\s+distinct\s+(.*?)\s+from\s+(.*?)(?:\s+where\s+(.*?))?\s*;?\s*", text, re.I | re.S)
    if not m:
        raise ValueError("expected SELECT DISTINCT ... FROM ... [WHERE ...]")
    tables = {}
    for part in m[2].split(","):
        words = re.sub(r"\bas\b", " ", part, flags=re.I).split()
        tables[words[-1]] = words[0]
    root: dict[str, str] = {}

    def find(c):
        while root.setdefault(c, c) != c:
            c = root[c]
        return c

    for cond in re.split(r"\s+and\s+", m[3], flags=re.I) if m[3] else []:
        e = re.fullmatch(r"\s*(\w+\.\w+)\s*=\s*(\w+\.\w+)\s*", cond)
        if not e:
            raise ValueError(f"only equalities of columns: {cond!r}")
        root[find(e[1])] = find(e[2])
    head = [c.strip().split()[0] for c in m[1].split(",")]
    for c in head:
        find(c)
    own: dict[str, dict[str, str]] = defaultdict(dict)
    names: dict[str, str] = {}
    for c in head:  # a variable takes the name of its first selected column
        names.setdefault(find(c), c.split(".")[1])
    for c in sorted(root):
        alias, column = c.split(".")
        if alias not in tables:
            raise ValueError(f"unknown alias {alias}")
        own[alias][column] = names.setdefault(find(c), c.replace(".", "_"))
    atoms = tuple(Atom(tables[a], tuple(cols.values())) for a, cols in own.items())
    return ConjunctiveQuery(frozenset(names[find(c)] for c in head), atoms), dict(own)
