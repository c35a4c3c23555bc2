"""Katz backoff language model: Good-Turing discounted counts, exactly normalised backoff weights, recursive evaluation.

Texts are cut into chunks of tokens that are written once, with a local table of
word hashes. Counts of each order live in a table partitioned by context. Chunks
do not carry n-grams around one by one: each sends its distinct (context, word)
pairs, sorted and compressed, to the partitions that own them, these answer with
the counts in the same order, and the chunk then evaluates each token
recursively: the longest n-gram seen in training gives the discounted
probability, otherwise the context's backoff weight times the probability of the
shorter n-gram, down to unigrams and the unseen word.

For contexts with seen followers, mass(context) = sum of discounted conditional
probabilities, lower(context) = sum of the followers' lower-order probabilities,
and the backoff weight is (1 - mass) / (1 - lower): sums to one exactly, over the
vocabulary and one unseen word. Weights are worked out where some text backs off.

fit() stores the tables of all orders, by partition; a stored model scores other
texts by the same exchange, its rows being one more sender of counts.

Null or empty text: the end token alone. The first token of a text has no
context and takes its unigram probability, the second one its bigram's. Repeated
rows are texts of their own, also in training. No training text: every word is
the unseen word. A row without an id is not held out. Only id and text are read.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import coded, delete, hashes, mixed, pieces, save, scratch, words

#: Bytes of text in a chunk at most (one text may be longer), and tokens that a partition should answer for.
CHUNK_BYTES, PART_TOKENS = 8 << 20, 1_500_000
#: Good-Turing discounts apply to counts up to this.
TOP = 5
END = np.uint64(0x9D39247E33776D41)  # hash of the end token
ORDER = 3
#: A context is hot, and its followers spread over all partitions, above this many tokens and above 8 times an even share.
MIN_SPREAD = 50_000
CHUNKS = "chunk long, n long, docs binary, offs binary, held binary, vocab binary, ids binary"


def packed(x: np.ndarray) -> bytes:
    """Compressed, byte plane by byte plane: of small numbers most planes are empty."""
    import zstandard

    x = np.ascontiguousarray(x)
    own = x.view(np.uint8).reshape(-1, x.itemsize) if len(x) else np.zeros((0, x.itemsize), np.uint8)
    planes = np.empty(own.shape[::-1], np.uint8)
    for i in range(x.itemsize):  # several times faster than a copy of the transposed whole
        planes[i] = own[:, i]
    return zstandard.ZstdCompressor(level=1).compress(planes.reshape(-1).data)


def unpacked(b, kind) -> np.ndarray:
    import zstandard

    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(b), np.uint8).reshape(np.dtype(kind).itemsize, -1)
    out = np.empty(planes.shape[1], kind)
    own = out.view(np.uint8).reshape(-1, len(planes))
    for i, plane in enumerate(planes):
        own[:, i] = plane
    return out


def chunked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row a chunk: ids of rows, offsets, held-out marks, hashes of the local words, and each token's local word."""
    number = TaskContext.get().partitionId() << 24
    for b in pieces(batches, most=CHUNK_BYTES):
        text, doc, held = (b.column(b.schema.get_field_index(c)) for c in ("text", "doc_id", "held_out"))
        offs, flat = words(text, lower=True)
        ids, names = coded(flat)
        vocab = np.append(hashes(names), END)
        order = np.argsort(-np.append(np.bincount(ids, minlength=len(names)), len(offs) - 1), kind="stable")  # frequent words get small numbers
        rank = np.empty(len(vocab), np.int32)
        rank[order] = np.arange(len(vocab))
        n = len(offs) - 1
        new = offs + np.arange(n + 1)
        own = np.full(int(new[-1]), rank[-1], np.int32)
        inner = np.ones(len(own), bool)
        inner[new[1:] - 1] = False
        own[inner] = rank[ids]
        doc_ids = pc.fill_null(doc, np.iinfo(np.int64).min).to_numpy(zero_copy_only=False)
        yield pa.RecordBatch.from_arrays(
            [pa.array([number], pa.int64()), pa.array([int(new[-1])], pa.int64())] + [pa.array([packed(x)], pa.binary()) for x in (doc_ids.astype(np.int64), new, held.to_numpy(zero_copy_only=False).astype(bool), vocab[order], own)],
            names=[x.split()[0] for x in CHUNKS.split(", ")],
        )
        number += 1


def read_chunk(row: dict) -> tuple[np.ndarray, ...]:
    kinds = {"docs": np.int64, "offs": np.int64, "held": bool, "vocab": np.uint64, "ids": np.int32}
    return tuple(unpacked(row[k], t) for k, t in kinds.items())


def owner(h: np.ndarray, parts: int) -> np.ndarray:
    return (h % np.uint64(parts)).astype(np.int64)


def rows_in(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    for b in batches:
        for i in range(b.num_rows):
            yield {n: b.column(k)[i].as_py() for k, n in enumerate(b.schema.names)}


def batch_of(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = {"long": pa.int64(), "int": pa.int32(), "binary": pa.binary(), "double": pa.float64(), "boolean": pa.bool_()}
    fields = [x.split() for x in schema.split(", ")]
    cols = zip(*rows, strict=True) if rows else [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(cols, fields, strict=True)], names=[n for n, _ in fields])



def by_part(part: np.ndarray, parts: int) -> Iterator[tuple[int, np.ndarray]]:
    """The places of each partition that occurs, in their order."""
    order = np.argsort(part.astype(np.uint16) if parts < 1 << 16 else part, kind="stable")  # short numbers are sorted by radix
    cuts = np.searchsorted(part[order], np.arange(parts + 1))
    for p in np.flatnonzero(np.diff(cuts)):
        yield int(p), order[cuts[p] : cuts[p + 1]]


WORDS = "part long, chunk long, words binary, counts binary"


def word_requests(batches, parts: int):
    """A chunk's words, to the partitions that own them, with the counts in its training texts."""
    for r in rows_in(batches):
        _, offs, held, vocab, ids = read_chunk(r)
        train = np.repeat(~held, np.diff(offs))
        n = np.bincount(ids[train], minlength=len(vocab))
        yield batch_of([(p, r["chunk"], packed(vocab[at]), packed(n[at])) for p, at in by_part(owner(vocab, parts), parts)], WORDS)


def total_counts(keys: list[np.ndarray], counts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct keys, sorted; the sums of their counts; and the place of each given key among them."""
    k = np.concatenate(keys) if keys else np.zeros(0, np.uint64)
    order = np.argsort(k)  # ties in any order: sums and places are the same
    k = k[order]
    first = np.concatenate([np.ones(min(1, len(k)), bool), k[1:] != k[:-1]])
    place = np.empty(len(k), np.int64)
    place[order] = np.cumsum(first) - 1
    c = np.concatenate(counts)[order].astype(np.int64) if keys else np.zeros(0, np.int64)
    at = np.flatnonzero(first)
    return k[at], np.add.reduceat(c, at) if len(c) else c, place


def histogram(c: np.ndarray) -> list[int]:
    """Tokens, types, and types of count 1 to TOP + 1."""
    return [int(c.sum()), int((c > 0).sum()), *(int((c == r).sum()) for r in range(1, TOP + 2))]


def discounts(spectrum: list[int]) -> np.ndarray:
    """Katz's discount ratios of counts 1..TOP; ratios that the counts of counts put out of (0, 1] are 1, as for large counts."""
    n = [0, *spectrum]
    out = np.ones(TOP + 1)
    if not n[1]:
        return out
    common = (TOP + 1) * n[TOP + 1] / n[1]
    for r in range(1, TOP + 1):
        if n[r] and common < 1:
            d = ((r + 1) * n[r + 1] / (r * n[r]) - common) / (1 - common)
            out[r] = d if 0 < d <= 1 else 1.0
    return out


def discounted(c: np.ndarray, d: np.ndarray) -> np.ndarray:
    return c * d[np.where(c <= TOP, c, 0)]


def unigram(c: np.ndarray, model: dict) -> np.ndarray:
    """Probability of a word by its training count; the unseen word takes what the discounts leave."""
    return np.where(c > 0, discounted(c, model["d1"]) / max(model["tokens"], 1), model["unseen"])


def finish_unigrams(model: dict) -> dict:
    """If no discount leaves mass, the unseen word takes that of one more token."""
    n, types, *spectrum = model["h1"]
    d = discounts(spectrum)
    lost = sum(r * spectrum[r - 1] * (1 - d[r]) for r in range(1, TOP + 1))
    model |= {"d1": d, "tokens": n, "types": types, "unseen": lost / n if n else 1.0}
    if n and not lost > 0:
        model |= {"tokens": n + 1, "unseen": 1 / (n + 1)}
    return model


#: Senders that are no chunk: a partition's totals for the driver, and a stored model's rows.
TOTALS, MODEL = -1, -2
ANSWER = "chunk long, part long, counts binary, ids binary"


def word_counter(parts: int, spread: int, store: bool):
    """Answers to all chunks that asked a partition: counts and numbers of words, frequent words first. TOTALS: the histogram, and words above `spread` with their counts."""

    def run(t: pa.Table) -> pa.Table:
        asked = [(r["chunk"], unpacked(r["words"], np.uint64), unpacked(r["counts"], np.int64)) for r in t.to_pylist()]
        keys, total, place = total_counts([a[1] for a in asked], [a[2] for a in asked])
        rank = np.empty(len(keys), np.int64)
        rank[np.lexsort((keys, -total))] = np.arange(len(keys))
        part = t.column("part")[0].as_py()
        out, at = [], 0
        for c, w, _ in asked:
            own = place[at : at + len(w)]
            at += len(w)
            if c != MODEL:
                out.append((c, part, packed(total[own]), packed(rank[own] * parts + part)))
        hot = np.flatnonzero(total > spread)
        own = np.array([*histogram(total), *(rank[hot] * parts + part), *total[hot]], np.int64)
        out.append((TOTALS, part, packed(own), packed(np.zeros(0, np.int64))))
        if store:
            out.append((MODEL, part, packed(total), packed(keys)))
        return pa.Table.from_batches([batch_of(out, ANSWER)])

    return run


K1, K2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def joined(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The hash by which a context and its follower, or the two words of a context, are known."""
    with np.errstate(over="ignore"):
        return mixed(a.astype(np.uint64) * K1 + b.astype(np.uint64) * K2)


def ranks(keys: np.ndarray) -> np.ndarray:
    """Places in the order of distinct keys."""
    out = np.empty(len(keys), np.int64)
    out[np.argsort(keys)] = np.arange(len(out))
    return out


@dataclass
class Level:
    """A chunk's distinct n-grams of one order: context and follower of each; each token's n-gram, or -1; contexts whose weight a text needs in any case.

    And what the tables answered: counts of n-grams, divisors and backoff weights of contexts.
    """

    context: np.ndarray
    follower: np.ndarray
    place: np.ndarray
    need: np.ndarray
    count: np.ndarray | None = None
    by: np.ndarray | None = None
    weight: np.ndarray | None = None


class Local:
    """A chunk with the answers it has got so far, order by order."""

    def __init__(self, chunk: dict, answers: list[dict], parts: int, spread: int):
        self.parts, self.spread = parts, spread
        self.docs, self.offs, self.held, vocab, self.ids = read_chunk(chunk)
        self.count, self.number = np.zeros(len(vocab), np.int64), np.zeros(len(vocab), np.int64)
        got = {r["part"]: r for r in answers if r["kind"] == 1}
        for p, at in by_part(owner(vocab, parts), parts):
            self.count[at], self.number[at] = unpacked(got[p]["counts"], np.int64), unpacked(got[p]["ids"], np.int64)
        self.answers = answers
        self.held_token = np.repeat(self.held, np.diff(self.offs))
        self.levels: dict[int, Level] = {}

    def keys(self, order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of the contexts of an order: their key, their training count, and the second word's number (nought for words)."""
        if order == 2:
            return self.number, self.count, np.zeros_like(self.number)
        two = self.levels[2]
        return joined(self.number[two.context], self.number[two.follower]).view(np.int64), two.count, self.number[two.follower]

    def ngrams(self, order: int) -> Level:
        """The n-grams of tokens whose context has been seen in training. The follower must be known; an unknown one needs the context's weight."""
        ids, v = self.ids, len(self.count)
        own = ids if order == 2 else self.levels[2].place
        context = np.full(len(ids), -1, np.int64)
        context[1:] = own[:-1]
        context[self.offs[:-1]] = -1
        seen = context >= 0
        _, times, _ = self.keys(order)
        seen[seen] = times[context[seen]] > 0
        known = self.count[ids] > 0
        need = np.zeros(len(times), bool)
        need[context[seen & ~known]] = True
        key = np.where(seen & known, context * v + ids, -1)
        distinct, inv = np.unique(key, return_inverse=True)
        skip = int(len(distinct) > 0 and distinct[0] < 0)
        distinct = distinct[skip:]
        out = Level(distinct // v, distinct % v, inv - skip, need)
        self.levels[order] = out
        return out

    def split(self, order: int):
        """For each partition: its n-grams, its contexts in the order of their numbers, and how many of these n-grams each has.

        A context's n-grams are in one partition, but for hot contexts, whose followers are dealt over all.
        """
        own = self.levels[order]
        key, times, _ = self.keys(order)
        word = ranks(self.number)  # every word has a number of its own
        home = owner(mixed(key.view(np.uint64)), self.parts)
        hot = times > self.spread
        part = home[own.context]
        away = hot[own.context]
        part[away] = owner(joined(key[own.context[away]], self.number[own.follower[away]]), self.parts)
        rank = word if order == 2 else ranks(word[self.levels[2].context] * len(word) + word[self.levels[2].follower])
        by_rank = np.empty(len(rank), np.int64)
        by_rank[rank] = np.arange(len(rank))
        order_ = np.argsort((part * len(rank) + rank[own.context]) * len(word) + word[own.follower])  # no two are equal
        cuts = np.searchsorted(part[order_], np.arange(self.parts + 1))
        alone = np.flatnonzero(own.need & ~hot)
        alone = alone[np.argsort(home[alone] * len(rank) + rank[alone])]
        ends = np.searchsorted(home[alone], np.arange(self.parts + 1))
        for p in range(self.parts):
            at = order_[cuts[p] : cuts[p + 1]]
            r = rank[own.context[at]]  # by size
            starts = np.flatnonzero(np.concatenate([np.ones(min(1, len(r)), bool), r[1:] != r[:-1]]))
            ctx = np.concatenate([r[starts], rank[alone[ends[p] : ends[p + 1]]]])
            ctx.sort()
            ctx = ctx[np.concatenate([np.ones(min(1, len(ctx)), bool), ctx[1:] != ctx[:-1]])]
            if len(ctx):
                runs = np.zeros(len(ctx), np.int32)
                runs[np.searchsorted(ctx, r[starts])] = np.diff(np.append(starts, len(r)))
                yield p, at, by_rank[ctx], runs

    def learn(self, order: int, d: np.ndarray, hot: dict[int, tuple]) -> Level:
        """Take in the tables' answers."""
        own = self.ngrams(order)
        key, times, _ = self.keys(order)
        got = {r["part"]: r for r in self.answers if r["kind"] == order}
        own.count, own.by, own.weight = np.zeros(len(own.context), np.int64), times.astype(np.float64), np.ones(len(times))
        less = sum(1 << r for r in range(1, TOP + 1) if d[r] < 1)
        lower_by = None if order == 2 else self.levels[2].by[self.levels[2].follower]
        for p, at, ctx, _ in self.split(order):
            x = got[p]
            own.count[at] = unpacked(x["counts"], np.int64)
            own.by[ctx] += (unpacked(x["present"], np.uint8) & less) == 0
            some = ctx[unpacked(x["which"], np.int32)]
            lower = unpacked(x["lower"], np.float64)
            _, own.weight[some] = backoff(unpacked(x["stats"], np.int64).reshape(TOP + 1, -1), lower if order == 2 else lower / lower_by[some], d)
        for i in np.flatnonzero(times > self.spread):
            if int(key[i]) in hot:
                stats, lower = hot[int(key[i])]
                by, weight = backoff(stats.reshape(-1, 1), np.array([lower if order == 2 else lower / lower_by[i]]), d)
                own.by[i], own.weight[i] = by[0], weight[0]
        return own


LEVEL = "part long, chunk long, contexts binary, seconds binary, runs binary, followers binary, counts binary, asked binary, lower binary, need binary"


def requester(order: int, parts: int, spread: int, model: dict, hot: dict):
    """A chunk's n-grams of an order, to the partitions that own them: counts in training texts, which ones held-out texts have, and the counts of the next shorter ones."""

    def run(key, chunk: pa.Table, answers: pa.Table) -> pa.Table:
        out = []
        for r in chunk.to_pylist():
            own = Local(r, answers.to_pylist(), parts, spread)
            for k in range(2, order):
                own.learn(k, model[f"d{k}"], hot[k])
            x = own.ngrams(order)
            used = x.place >= 0
            n = np.bincount(x.place[used & ~own.held_token], minlength=len(x.context))
            asked = np.bincount(x.place[used & own.held_token], minlength=len(x.context)) > 0
            if order == 2:
                first, second, lower = own.number, None, own.count[x.follower]
            else:
                two = own.levels[2]
                first, second = own.number[two.context], own.number[two.follower]
                # the shorter n-gram is the token's own bigram
                lower = np.zeros(len(x.context), np.int64)
                lower[x.place[used]] = two.count[two.place[used]]
            for p, at, ctx, runs in own.split(order):
                gaps = np.diff(first[ctx], prepend=0)
                out.append((p, r["chunk"], packed(gaps), None if second is None else packed(second[ctx]), packed(runs), packed(own.number[x.follower[at]]), packed(n[at]), packed(asked[at]), packed(lower[at]), packed(x.need[ctx])))
        return pa.Table.from_batches([batch_of(out, LEVEL)])

    return run


LEVEL_ANSWER = "chunk long, part long, counts binary, present binary, which binary, stats binary, lower binary"


def level_counter(order: int, model: dict, hot: np.ndarray, spread: int, store: bool):
    """Answers: counts of n-grams; for each context which counts up to TOP its followers have; and for contexts from which a held-out text backs off
    its followers by count (1 to TOP), the sum of larger counts, and their lower-order mass. TOTALS: the histogram, shares of hot contexts, keys above `spread`."""

    def run(t: pa.Table) -> pa.Table:
        part, asked = t.column("part")[0].as_py(), []
        for r in t.to_pylist():
            ctx = np.cumsum(unpacked(r["contexts"], np.int64))
            if r["seconds"] is not None:
                ctx = joined(ctx, unpacked(r["seconds"], np.int64)).view(np.int64)
            runs = unpacked(r["runs"], np.int32)
            a = np.repeat(ctx, runs)
            asked.append((r["chunk"], ctx, a, joined(a, unpacked(r["followers"], np.int64)), unpacked(r["counts"], np.int64), unpacked(r["asked"], bool), unpacked(r["lower"], np.int64), unpacked(r["need"], bool), r))
        keys, total, place = total_counts([x[3] for x in asked], [x[4] for x in asked])
        a, low = np.zeros(len(keys), np.int64), np.zeros(len(keys), np.int64)
        every = np.concatenate([x[2] for x in asked])
        a[place] = every
        low[place] = np.concatenate([x[6] for x in asked])
        contexts, inv = np.unique(a, return_inverse=True)
        present = np.zeros(len(contexts), np.uint8)
        for r in range(1, TOP + 1):
            present[inv[total == r]] |= np.uint8(1 << r)
        wanted = np.zeros(len(contexts), bool)
        gone = np.concatenate([x[5] for x in asked]) & (total[place] == 0)
        wanted[inv[place[gone]]] = True
        of = lambda c: np.minimum(np.searchsorted(contexts, c), max(len(contexts) - 1, 0))
        for x in asked:
            c = x[1][x[7]]
            if len(c) and len(contexts):
                at = of(c)
                wanted[at[contexts[at] == c]] = True
        is_hot = np.isin(contexts, hot)
        wanted |= is_hot
        some = np.flatnonzero(wanted)
        at = np.full(len(contexts), -1, np.int64)
        at[some] = np.arange(len(some))
        own = np.flatnonzero((at[inv] >= 0) & (total > 0)) if len(inv) else np.zeros(0, np.int64)
        where, c = at[inv[own]], total[own]
        stats = [np.bincount(where, weights=c == r, minlength=len(some)) for r in range(1, TOP + 1)]
        stats.append(np.bincount(where, weights=np.where(c > TOP, c, 0), minlength=len(some)))
        stats = np.stack(stats).astype(np.int64)
        shorter = unigram(low[own], model) if order == 2 else discounted(low[own], model["d2"])
        lower = np.bincount(where, weights=shorter, minlength=len(some))
        out, begin = [], 0
        for chunk, ctx, mine, _, _, held, _, need, r in asked:
            counts = total[place[begin : begin + len(mine)]]
            begin += len(mine)
            if chunk == MODEL:
                continue
            k = of(ctx) if len(contexts) else np.zeros(len(ctx), np.int64)
            found = contexts[k] == ctx if len(contexts) else np.zeros(len(ctx), bool)
            bits = np.where(found, present[k] if len(present) else 0, 0).astype(np.uint8)
            backs = need.copy()  # a chunk gets the weights that its own held-out texts need
            backs[np.repeat(np.arange(len(ctx)), unpacked(r["runs"], np.int32))[held & (counts == 0)]] = True
            which = np.flatnonzero(found & backs & (wanted[k] if len(wanted) else False)).astype(np.int32)
            out.append((chunk, part, packed(counts), packed(bits), packed(which), packed(stats[:, at[k[which]]].ravel()), packed(lower[at[k[which]]])))
        i = at[np.flatnonzero(is_hot)]
        above = keys[total > spread].view(np.int64)
        whole = np.array([*histogram(total), len(i), *contexts[is_hot], *stats[:, i].ravel(), *above], np.int64)
        out.append((TOTALS, part, packed(whole), None, None, None, packed(lower[i])))
        if store:  # sorted by context, as a sender's rows are
            full = np.flatnonzero(total > 0)
            out.append((MODEL, part, *model_row(asked, place, total, low, full)))
        return pa.Table.from_batches([batch_of(out, LEVEL_ANSWER)])

    return run


def model_row(asked: list, place: np.ndarray, total: np.ndarray, low: np.ndarray, full: np.ndarray) -> tuple:
    """The partition's n-grams as a sender would send them: contexts, runs, followers, counts, counts of shorter ones, in the columns of LEVEL_ANSWER."""
    n, three = len(total), asked[0][8]["seconds"] is not None
    first, second, follower = (np.zeros(n, np.int64) for _ in range(3))
    begin = 0
    for _, ctx, mine, *_, r in asked:
        runs = unpacked(r["runs"], np.int32)
        at = place[begin : begin + len(mine)]
        begin += len(mine)
        first[at] = np.repeat(np.cumsum(unpacked(r["contexts"], np.int64)), runs)
        if three:
            second[at] = np.repeat(unpacked(r["seconds"], np.int64), runs)
        follower[at] = unpacked(r["followers"], np.int64)
    order = full[np.lexsort((follower[full], second[full], first[full]))]
    f, s = first[order], second[order]
    starts = np.flatnonzero(np.concatenate([np.ones(min(1, len(f)), bool), (f[1:] != f[:-1]) | (s[1:] != s[:-1])]))
    runs = np.diff(np.append(starts, len(f))).astype(np.int32)
    two = packed(s[starts]) if three else None
    return packed(total[order]), two, packed(runs), packed(np.concatenate([np.diff(f[starts], prepend=0), follower[order]])), packed(low[order])


def stored_requests(rows: DataFrame, order: int) -> DataFrame:
    """A stored model's rows as requests."""

    def run(batches):
        for r in rows_in(batches):
            runs, both, n = unpacked(r["which"], np.int32), unpacked(r["stats"], np.int64), unpacked(r["counts"], np.int64)
            gaps, followers = both[: len(runs)], both[len(runs) :]
            yield batch_of([(r["part"], MODEL, packed(gaps), r["present"], r["which"], packed(followers), packed(n), packed(np.zeros(len(n), bool)), r["lower"], packed(np.zeros(len(runs), bool)))], LEVEL)

    return rows.filter(F.col("chunk") == MODEL).mapInArrow(run, LEVEL)


def backoff(stats: np.ndarray, lower: np.ndarray, d: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of contexts: the divisor of their followers' counts, and the backoff weight. Where no discount leaves mass, the divisor is larger by one."""
    r = np.arange(1, TOP + 1)[:, None]
    times = (stats[:TOP] * r).sum(0) + stats[TOP]
    mass = (stats[:TOP] * r * d[1:, None]).sum(0) + stats[TOP]
    by = np.where(mass >= times, times + 1.0, times)
    return np.where(times > 0, by, 1.0), np.where(times > 0, (1 - mass / np.maximum(by, 1)) / (1 - lower), 1.0)


SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def scorer(order: int, parts: int, spread: int, model: dict, hot: dict):
    def run(key, chunk: pa.Table, answers: pa.Table) -> pa.Table:
        out = []
        for r in chunk.to_pylist():
            own = Local(r, answers.to_pylist(), parts, spread)
            ids, n, offs = own.ids, np.diff(own.offs), own.offs
            base = np.log10((own.count + 1.0) / (model["h1"][0] + model["h1"][1] + 1.0))
            p = unigram(own.count, model)[ids]
            for k in range(2, order + 1):
                x = own.learn(k, model[f"d{k}"], hot[k])
                _, times, _ = own.keys(k)
                context = np.full(len(ids), -1, np.int64)
                context[1:] = (ids if k == 2 else own.levels[2].place)[:-1]
                context[offs[:-1]] = -1
                at = np.flatnonzero(context >= 0)
                at = at[times[context[at]] > 0]
                place = x.place[at]
                seen = (place >= 0) & (x.count[place] > 0) if len(x.count) else np.zeros(len(at), bool)
                p[at[~seen]] *= x.weight[context[at[~seen]]]
                g = place[seen]
                p[at[seen]] = discounted(x.count[g], model[f"d{k}"]) / x.by[x.context[g]]
            total = lambda x: np.add.reduceat(x, offs[:-1]) if len(n) else np.zeros(0)  # noqa: E731  every text has its end token
            cols = (own.docs, own.held, n, total((own.count[ids] > 0).astype(np.int64)), np.full(len(n), model["h1"][0]), total(base[ids]), total(np.log10(p)))
            out.append(pa.RecordBatch.from_arrays([pa.array(c) for c in cols], names=[x.split()[0] for x in SCORES.split(", ")]))
        return pa.Table.from_batches(out)

    return run


#: Answers of all orders in one table: kind is the order.
REPLY = {"chunk": "long", "kind": "int", "part": "long", "counts": "binary", "ids": "binary", "present": "binary", "which": "binary", "stats": "binary", "lower": "binary"}


def replies(answers: DataFrame, kind: int) -> DataFrame:
    have = set(answers.columns)
    return answers.filter("chunk >= 0").withColumn("kind", F.lit(kind)).select(*[(F.col(c) if c in have or c == "kind" else F.lit(None)).cast(t).alias(c) for c, t in REPLY.items()])


def score_texts(documents: DataFrame, order: int = ORDER, store: str | None = None, model_path: str | None = None) -> DataFrame:
    """SCORES of all rows of (doc_id, text, held_out); rows with held_out = false train the model.

    store: a folder for the tables of all orders. model_path: such a folder, whose model scores all rows; they train nothing then.
    """
    if not 1 <= order <= ORDER:
        raise ValueError(f"order {order}: only orders 1 to {ORDER} are implemented")
    spark = documents.sparkSession
    held = F.lit(True) if model_path else F.coalesce("held_out", F.lit(False))
    docs = documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string"), held.alias("held_out"))
    first = scratch(spark)
    chunks = save(docs.mapInArrow(chunked, CHUNKS), "none", first, rows=None)  # a chunk is at most a batch
    n, tokens = chunks.agg(F.count(F.lit(1)), F.coalesce(F.sum("n"), F.lit(0))).first()
    if not n:
        return spark.createDataFrame([], SCORES)
    chunks = bucketed(chunks, "chunk", n)
    delete(spark, first)
    collected(spark)
    parts = max(8, -(-tokens // PART_TOKENS))
    spread = max(MIN_SPREAD, 8 * tokens // parts)
    if model_path:
        meta = spark.read.parquet(f"{model_path}/meta").first()
        parts, spread, order = meta["parts"], meta["spread"], min(order, meta["order"])
    stored = lambda k, schema: spark.read.schema(schema).parquet(f"{model_path}/order={k}")
    asked = chunks.select("chunk", "docs", "offs", "held", "vocab", "ids").mapInArrow(lambda it: word_requests(it, parts), WORDS)
    if model_path:
        asked = asked.union(stored(1, ANSWER).select("part", "chunk", F.col("ids").alias("words"), "counts"))
    keep_rows = store is not None
    answers = save(asked.groupBy("part").applyInArrow(word_counter(parts, spread, keep_rows), ANSWER), "none")
    if store:
        answers.filter(F.col("chunk") == MODEL).write.mode("overwrite").parquet(f"{store}/order=1")
    h1, hot_keys = np.zeros(TOP + 3, np.int64), []
    for r in answers.filter(F.col("chunk") == TOTALS).select("counts").toLocalIterator():  # a histogram and a few hot words each
        x = unpacked(r["counts"], np.int64)
        h1 += x[: TOP + 3]
        hot_keys += x[TOP + 3 : TOP + 3 + (len(x) - TOP - 3) // 2].tolist()
    model = finish_unigrams({"h1": h1.tolist(), "order": order})
    got, hot = replies(answers, 1), {}
    for k in range(2, order + 1):
        collected(spark)
        wanted = chunks.groupBy("chunk").cogroup(got.groupBy("chunk")).applyInArrow(requester(k, parts, spread, model, dict(hot)), LEVEL)
        if model_path:
            wanted = wanted.union(stored_requests(stored(k, LEVEL_ANSWER), k))
        level = save(wanted.groupBy("part").applyInArrow(level_counter(k, model, np.array(sorted(hot_keys), np.int64), spread, keep_rows), LEVEL_ANSWER), "none")
        if store:
            level.filter(F.col("chunk") == MODEL).write.mode("overwrite").parquet(f"{store}/order={k}")
        h, shares, hot_keys = np.zeros(TOP + 3, np.int64), {}, []
        for r in level.filter(F.col("chunk") == TOTALS).select("counts", "lower").toLocalIterator():
            x, low = unpacked(r["counts"], np.int64), unpacked(r["lower"], np.float64)
            h += x[: TOP + 3]
            m, x = int(x[TOP + 3]), x[TOP + 4 :]
            stats = x[m : m + (TOP + 1) * m].reshape(TOP + 1, m)
            for i, c in enumerate(x[:m].tolist()):
                before, w = shares.get(c, (np.zeros(TOP + 1, np.int64), 0.0))
                shares[c] = (before + stats[:, i], w + low[i])
            hot_keys += x[m + (TOP + 1) * m :].tolist()
        model |= {f"d{k}": discounts(h.tolist()[2:]), f"h{k}": h.tolist()}
        hot[k] = shares
        got = got.union(replies(level, k))
        collected(spark)
    if store:
        spark.createDataFrame([(parts, spread, order)], "parts long, spread long, `order` int").coalesce(1).write.mode("overwrite").parquet(f"{store}/meta")
    out = chunks.groupBy("chunk").cogroup(got.groupBy("chunk")).applyInArrow(scorer(order, parts, spread, model, hot), SCORES)
    return out.withColumn("doc_id", F.when(F.col("doc_id") != F.lit(-(2**63)), F.col("doc_id")))


def bucketed(df: DataFrame, key: str, n: int) -> DataFrame:
    """Saved by the hash of a key, so that grouping by it reads the rows where they are: only answers are shuffled to chunks."""
    spark, name = df.sparkSession, f"katz_{uuid.uuid4().hex}"
    df.repartition(n, key).write.format("parquet").bucketBy(n, key).option("compression", "none").option("path", scratch(spark)).saveAsTable(name)
    out = spark.table(name)
    spark.sql(f"DROP TABLE {name}")  # its name alone: the files are not the catalog's
    return out


def fit(documents: DataFrame, path: str, order: int = ORDER) -> None:
    """Store the model of all rows of (doc_id, text) in a folder: a table for each order, a row for each partition of it."""
    score_texts(documents.withColumn("held_out", F.lit(False)), order, store=path)


def score(documents: DataFrame, path: str) -> DataFrame:
    """SCORES of (doc_id, text) by a stored model."""
    return score_texts(documents.withColumn("held_out", F.lit(True)), model_path=path)


def collected(spark) -> None:
    """Let Spark drop the shuffle files of steps that are over."""
    spark.sparkContext._jvm.System.gc()
