"""Answers one by one, without repeats, with a number of steps between two that does not depend on the data.

After preprocessing, the head's bags of a tree are fully reduced and indexed by
what they share with their parents: every partial answer goes on, so each answer
costs a few look-ups. An answer belongs to a tree if its parts stand in the tree's
bags, which is how repeats between trees are told without remembering answers.

Indexes are of a part of the answers at a time, by the hash of one head variable,
so that the driver holds about `rows` rows of bags, however many answers there are.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .acyclic import full_reduction
from .decomposition import TreeDecomposition
from .guided import Run, grouped
from .instance import columns, semijoin
from .materialize import count_all, keep
from .query import ConjunctiveQuery, Vars

#: Rows of bags that are indexed at a time.
INDEX_ROWS = 1_000_000


@dataclass
class Steps:
    """Look-ups and pulls so far."""

    n: int = 0


@dataclass
class TreeAnswers:
    """The answers of one tree over the head, from its reduced and indexed head bags. Iteration and membership cost a few steps each."""

    bags: list[tuple[str, ...]]
    shared: list[tuple[str, ...]]
    index: list[dict[tuple, list[tuple]]]
    rows: list[set[tuple]]
    head: tuple[str, ...]
    steps: Steps = field(default_factory=Steps)

    def __iter__(self) -> Iterator[tuple]:
        return self.below(0, {})

    def below(self, i: int, own: dict) -> Iterator[tuple]:
        if i == len(self.bags):
            yield tuple(own[v] for v in self.head)
            return
        self.steps.n += 1
        for row in self.index[i].get(tuple(own[v] for v in self.shared[i]), ()):
            self.steps.n += 1
            yield from self.below(i + 1, own | dict(zip(self.bags[i], row, strict=True)))

    def __contains__(self, answer: tuple) -> bool:
        own = dict(zip(self.head, answer, strict=True))
        self.steps.n += len(self.bags)
        return all(tuple(own[v] for v in b) in r for b, r in zip(self.bags, self.rows, strict=True))


def indexed(t: TreeDecomposition, rel: dict[int, DataFrame], head: Vars) -> TreeAnswers:
    """Head bags in an order in which a bag comes after its parent."""
    order = [i for i in reversed(t.bottom_up()) if i in t.head_nodes]
    bags, shared, index, rows, seen = [], [], [], [], set()
    for i in order:
        own = tuple(columns(t.bags[i]))
        common = tuple(v for v in own if v in seen)
        at = [own.index(v) for v in common]
        by: dict[tuple, list[tuple]] = {}
        for r in map(tuple, rel[i].select(*own).toLocalIterator(prefetchPartitions=True)):
            by.setdefault(tuple(r[k] for k in at), []).append(r)
        bags.append(own)
        shared.append(common)
        index.append(by)
        rows.append({r for group in by.values() for r in group})
        seen |= set(own)
    return TreeAnswers(bags, shared, index, rows, tuple(columns(head)))


def union_of(sets: list[TreeAnswers]) -> Iterator[tuple]:
    """Every answer of some set once, at bounded delay and without memory of answers: an answer of the first set that the
    others have too is held back, and one of theirs is given in its place."""
    if len(sets) == 1:
        yield from sets[0]
        return
    rest = union_of(sets[1:])
    for a in sets[0]:
        if any(a in s for s in sets[1:]):
            yield next(rest)  # they have as many as have been held back
        else:
            yield a
    yield from rest


def prepared(run: Run) -> list[tuple[TreeDecomposition, dict[int, DataFrame]]]:
    """Preprocessing: of each tree that leaves have covered, the fully reduced bags of its head nodes."""
    out = []
    for t, bags in grouped(run.leaves):
        rel = full_reduction(t, bags)
        out.append((t, {i: keep(rel[i].distinct()) for i in t.head_nodes}))  # rows of several leaves come several times
    return out


def reduced_head(t: TreeDecomposition, rel: dict[int, DataFrame]) -> dict[int, DataFrame]:
    """The head nodes, a subtree of their own, reduced again after some rows have been left out."""
    order = [i for i in t.bottom_up() if i in rel]
    out = dict(rel)
    for i in order:
        if t.parent[i] in out:
            out[t.parent[i]] = semijoin(out[t.parent[i]], out[i])
    for i in reversed(order):
        if t.parent[i] in out:
            out[i] = semijoin(out[i], out[t.parent[i]])
    return out


def enumerate_answers(q: ConjunctiveQuery, run: Run, rows: int = INDEX_ROWS) -> Iterator[tuple[tuple, int]]:
    """(answer, steps since the last one) over the trees of a run; answers' values are in the order of columns(q.head)."""
    if q.is_boolean:
        raise ValueError("a Boolean query has no answers to list")
    trees = prepared(run)
    total = sum(count_all({(k, i): df for k, (_, rel) in enumerate(trees) for i, df in rel.items()}).values())
    parts, by = -(-total // rows), columns(q.head)[0]
    for part in range(parts):
        sets = []
        for t, rel in trees:
            own = rel
            if parts > 1:
                mine = F.pmod(F.xxhash64(by), F.lit(parts)) == part
                own = reduced_head(t, {i: df.filter(mine) if by in df.columns else df for i, df in rel.items()})
            sets.append(indexed(t, own, q.head))
        steps = Steps()
        for s in sets:
            s.steps = steps
        last = 0
        for a in union_of(sets):
            yield a, steps.n - last
            last = steps.n


def delay_bound(run: Run) -> int:
    """Steps between two answers at most: a pull and a look-up for each bag of each tree, and each tree's membership test, whatever N is."""
    trees = {t for t, _ in run.leaves}
    return sum(2 * len(t.head_nodes) + len(trees) * len(t.head_nodes) for t in trees) + 1


def merge_without_duplicates(iters: list[Iterable], copies: int) -> Iterator[tuple[object, int]]:
    """For iterators without membership tests: (answer, pulls since the last one). At most `copies` of an answer come in all, so one
    new answer is due every `copies` pulls; new ones wait in a queue. It remembers all answers: where these are many, use union_of()."""
    seen, waiting, pulls = set(), deque(), 0
    for it in iters:
        for row in it:
            pulls += 1
            if row not in seen:
                seen.add(row)
                waiting.append(row)
            if pulls >= copies and waiting:
                yield waiting.popleft(), pulls
                pulls = 0
    while waiting:
        yield waiting.popleft(), pulls
        pulls = 0


def measure_delay(answers: Iterator[tuple[object, int]]) -> tuple[int, int]:
    """Answers, and the most steps before one of them."""
    n = gap = 0
    for _, steps in answers:
        n, gap = n + 1, max(gap, steps)
    return n, gap
