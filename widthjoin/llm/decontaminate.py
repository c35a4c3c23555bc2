"""Benchmark decontamination by latent semantic retrieval.

Benchmark items are cut into passages. Their TF-IDF matrix, with document
frequencies of the whole corpus, gets a distributed randomised SVD; passages and
windows of documents are projected on its singular directions. A window is a
candidate for a passage if it has so many of the passage's words that a leak is
possible at all, whatever its latent cosine, which is reported; a candidate is a
leak if the longest common subsequence of words covers enough of the passage, or
somewhat less of it and the passage's answer stands in the window.

All windows of all rows are searched. A leak lacks few of a passage's words, so
that it has some of the passage's rarest ones: only these are looked up, and no
pair that the subsequence check would accept is left out before it. Null or empty text or item: no windows, no passages. Items
without a letter or digit match nothing. Repeated rows and items are reported as
one pair. An empty benchmark or table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import coded, hashes, pick, pieces, save, trim, without, words

#: Words of a window, and between the starts of two; a passage has at most STRIDE words, so some window holds it whole.
WINDOW, STRIDE = 64, 32
RANK, OVERSAMPLE, POWERS = 128, 16, 2
#: Hashed dimensions of TF-IDF vectors; the projection is a table of DIMS x RANK, whatever the corpus.
DIMS, GROUP = 1 << 15, 1 << 9
#: Words in at most one document of twenty or so (inverse document frequency, natural logarithm) are selective.
SELECTIVE = 3.0
#: Covered share of a passage's words, without and with its answer in the window. Answers: the last ANSWER words of a passage, where the benchmark states none.
MIN_COVER, MIN_COVER_ANSWER, ANSWER = 0.8, 0.6, 4
#: Without the answer, the lesser share is enough if the matched stretch has this latent cosine with the passage, and so many words in common.
MIN_COSINE, MIN_COMMON = 0.7, 8
#: Bytes of text searched at once: each selective word is written out for each passage that has it.
SLICE = 3 << 20
#: Looked-up words written out at once.
EXPANDED = 1 << 20
#: Benchmark passages a broadcast block holds; longer benchmarks are searched block by block.
BLOCK = 20_000


def normal(names: pa.Array) -> pa.Array:
    """Words in lower case, letters and digits alone."""
    return pc.replace_substring_regex(pc.utf8_lower(names.cast(pa.string())), r"[^\p{L}\p{N}]+", "")


def terms(text: pa.Array, vocabulary: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Offsets, and each word's place in the vocabulary, -1 where it has none; words that normal() empties are left out."""
    offs, flat = words(text)
    ids, names = coded(flat)
    n = normal(names)
    place = pc.fill_null(pc.index_in(n, vocabulary), -1).to_numpy(zero_copy_only=False).astype(np.int32)
    place[pc.equal(pc.binary_length(n), 0).to_numpy(zero_copy_only=False).astype(bool)] = -2
    own = place[ids] if len(ids) else np.zeros(0, np.int32)
    if (own == -2).any():
        keep = own != -2
        return np.concatenate([[0], np.cumsum(keep)])[offs], own[keep]
    return offs, own


def passages(items: list[tuple]) -> tuple[pa.Array, list[tuple[int, np.ndarray, np.ndarray]]]:
    """The benchmark's words, and (item, words, answer's words) of passages: items cut into even parts of at most STRIDE words."""
    texts = pa.array([t or "" for _, t, _ in items] + [a or "" for *_, a in items], pa.large_string())
    vocabulary = normal(words(texts)[1]).unique()
    vocabulary = vocabulary.filter(pc.greater(pc.binary_length(vocabulary), 0))
    offs, own = terms(texts, vocabulary)
    out = []
    for i, (item, *_) in enumerate(items):
        w, a = own[offs[i] : offs[i + 1]], own[offs[len(items) + i] : offs[len(items) + i + 1]]
        parts = -(-len(w) // STRIDE)
        for k in range(parts):
            p = w[len(w) * k // parts : len(w) * (k + 1) // parts]
            out.append((item, p, a if len(a) else p[-ANSWER:]))
    return vocabulary, out


def document_frequencies(documents: DataFrame, vocabulary: pa.Array) -> DataFrame:
    """(term, n): documents with each benchmark word by its place, and all documents under -1. One pass; a task sends one number a word."""
    shared = documents.sparkSession.sparkContext.broadcast(vocabulary)  # words of at most BLOCK items

    def count(batches):
        v = shared.value
        df, n = np.zeros(len(v), np.int64), 0
        for b in pieces(batches, most=SLICE):
            offs, own = terms(b.column(0), v)
            row = np.repeat(np.arange(len(offs) - 1), np.diff(offs))[own >= 0]
            key = row * len(v) + own[own >= 0]
            seen = np.zeros((len(offs) - 1) * len(v), bool) if (len(offs) - 1) * len(v) <= 1 << 24 else None
            if seen is not None:  # a bit map is faster than sorting
                seen[key] = True
                df += seen.reshape(-1, len(v)).sum(0)
            else:
                df += np.bincount(np.unique(key) % len(v), minlength=len(v))
            n += len(offs) - 1
        some = np.flatnonzero(df)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(some, -1)), pa.array(np.append(df[some], n))], names=["term", "n"])

    out = save(documents.select("text").mapInArrow(count, "term long, n long").groupBy("term").agg(F.sum("n").alias("n")))
    shared.destroy()
    return out


def inverse_frequencies(counted: DataFrame, n_words: int) -> np.ndarray:
    df, total = np.zeros(n_words, np.int64), 0
    for r in counted.toLocalIterator():
        if r["term"] < 0:
            total = r["n"]
        else:
            df[r["term"]] = r["n"]
    return np.log((total + 1.0) / (df + 1.0)) + 0.1


def folded(vocabulary: pa.Array, dims: int = DIMS) -> np.ndarray:
    return (hashes(vocabulary) % np.uint64(dims)).astype(np.int64)


def needed(n: int, share: float) -> int:
    """The least number of a passage's n words that covers the share."""
    return next(k for k in range(n + 1) if k / n >= share)


def postings(own: list, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """By word: start of its passages, and these; and how many looked-up words a window needs for each passage.

    A leak lacks at most `slack` words of a passage, so it has all but `slack` of any of them. Looked up are the
    passage's selective words, and the next rarest where these are no more than `slack`.
    """
    pairs, least = [], np.zeros(len(own), np.int64)
    for i, (_, w, _) in enumerate(own):
        slack = len(w) - min(needed(len(w), MIN_COVER), needed(len(w), MIN_COVER_ANSWER))
        use = max(slack + 1, int((idf[w] >= SELECTIVE).sum()))
        least[i] = use - slack
        pairs += [(x, i) for x in np.unique(w[np.argsort(-idf[w], kind="stable")[:use]]).tolist()]
    pairs.sort()
    term = np.array([t for t, _ in pairs], np.int64)
    return np.searchsorted(term, np.arange(len(idf) + 1)), np.array([p for _, p in pairs], np.int64), least


def sharing(own: np.ndarray, offs: np.ndarray, first: np.ndarray, many: np.ndarray, index: tuple) -> tuple[np.ndarray, np.ndarray]:
    """Pairs of a window (numbered through all rows, ascending) and a passage of which it has enough looked-up words.

    A window is two blocks of STRIDE words. A passage with a word several times may match as often: its window then
    needs the word as often too, so each word of the window counts one.
    """
    starts, lists, least = index
    n = starts[1:] - starts[:-1]
    at = np.flatnonzero(own >= 0)
    at = at[n[own[at]] > 0]
    row = np.searchsorted(offs, at, "right") - 1
    block = (at - offs[row]) // STRIDE
    word = own[at]
    # a word lies in the window that its block opens and in the one before
    window = np.concatenate([first[row] + np.minimum(block, many[row] - 1), first[row] + block - 1])
    good = np.concatenate([np.ones(len(at), bool), (block > 0) & (block < many[row])])
    word = np.concatenate([word, word])[good]
    window = window[good]
    found = []
    order = np.argsort(window, kind="stable")
    word, window = word[order], window[order]
    times = n[word]
    upto = np.cumsum(times)
    x = 0
    while x < len(word):  # some windows at once, so that their looked-up pairs take bounded memory
        y = max(x + 1, int(np.searchsorted(upto, (upto[x - 1] if x else 0) + EXPANDED, "right")))
        y = int(np.searchsorted(window, window[y - 1], "right"))
        t = times[x:y]
        where = np.repeat(starts[word[x:y]] - np.concatenate([[0], np.cumsum(t)])[:-1], t) + np.arange(t.sum())
        key, total = np.unique(np.repeat(window[x:y], t) * len(least) + lists[where], return_counts=True)
        found.append(key[total >= least[key % len(least)]])
        x = y
    key = np.concatenate(found) if found else np.zeros(0, np.int64)
    return key // len(least), key % len(least)


def common(h: np.ndarray, begin: np.ndarray, end: np.ndarray, passage: np.ndarray, held: np.ndarray, terms: int) -> np.ndarray:
    """Of each pair: words of the window that stand in the passage. `held` has passage * terms + word of all passages, sorted."""
    place = begin[:, None] + np.arange(WINDOW)
    word = np.where(place < end[:, None], h[np.minimum(place, len(h) - 1)], -1)
    key = np.where(word >= 0, passage[:, None] * terms + word, -1)
    at = np.minimum(np.searchsorted(held, key), len(held) - 1)
    return (held[at] == key).sum(1)


def randomised_svd(rows: DataFrame, rank: int, dims: int = DIMS, oversample: int = OVERSAMPLE, powers: int = POWERS, seed: int = 7, used: np.ndarray | None = None) -> np.ndarray:
    """Right singular directions (used dimensions x rank; without `used`, all dims) of the sparse matrix in rows (passage, dims array, weights array).

    Each pass computes A'(A Q) task by task; tasks send the groups of GROUP dimensions they touch,
    and these are summed in Spark. The driver holds used dimensions (sorted, at most DIMS) x (rank + oversample).
    """
    used = np.arange(dims) if used is None else used
    width, dims = rank + oversample, len(used)
    spark = rows.sparkSession
    q = np.random.default_rng(seed).standard_normal((dims, width), np.float32)

    def step(q):
        shared = spark.sparkContext.broadcast(q)

        def run(batches):
            acc, seen = np.zeros((dims, width), np.float32), np.zeros(dims, bool)
            for b in batches:
                for d, w in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    d, w = np.searchsorted(used, d), np.asarray(w, np.float32)
                    acc[d] += w[:, None] * (w @ shared.value[d])
                    seen[d] = True
            blocks = [k for k in range(0, dims, GROUP) if seen[k : k + GROUP].any()]
            yield pa.RecordBatch.from_arrays([pa.array(blocks, pa.int64()), pa.array([acc[k : k + GROUP].tobytes() for k in blocks], pa.binary())], names=["dim", "v"])

        def add(t: pa.Table) -> pa.Table:
            total = sum((np.frombuffer(x.as_buffer(), np.float32) for x in t.column("v")), np.float32(0))
            return pa.table({"dim": t.column("dim").slice(0, 1), "v": pa.array([total.tobytes()], pa.binary())})

        parts = rows.select("dims", "weights").mapInArrow(run, "dim long, v binary").groupBy("dim").applyInArrow(add, "dim long, v binary")
        out = np.zeros((dims, width), np.float32)
        for r in parts.toLocalIterator():
            out[r["dim"] : r["dim"] + GROUP] = np.frombuffer(r["v"], np.float32).reshape(-1, width)
        shared.destroy()
        trim()
        return out

    for _ in range(powers):
        q = np.linalg.qr(step(q))[0].astype(np.float32)
    y = step(q)
    small = q.T @ y  # = Q'A'AQ
    values, vectors = np.linalg.eigh((small + small.T) / 2)
    best = np.argsort(-values)[:rank]
    best = best[values[best] > 1e-6 * max(values.max(), 1e-12)]
    return (q @ vectors[:, best]).astype(np.float32)


def lcs(a: np.ndarray, b: np.ndarray) -> int:
    """Length of the longest common subsequence, bit-parallel over a."""
    return lcs_end(a, b)[0]


def lcs_end(a: np.ndarray, b: np.ndarray) -> tuple[int, int]:
    """Length of the longest common subsequence, and how long a prefix of b holds one."""
    masks: dict[int, int] = {}
    for i, x in enumerate(a.tolist()):
        masks[x] = masks.get(x, 0) | 1 << i
    v = full = (1 << len(a)) - 1
    most, end = 0, 0
    for k, x in enumerate(b.tolist()):
        if x in masks:
            u = v & masks[x]
            v = ((v + u) | (v - u)) & full
            n = len(a) - v.bit_count()
            if n > most:
                most, end = n, k + 1
    return most, end


def aligned(passage: np.ndarray, window: np.ndarray) -> tuple[int, np.ndarray]:
    """Length of the longest common subsequence, and the words of the window between its first and last word."""
    n, end = lcs_end(passage, window)
    _, size = lcs_end(passage[::-1], window[:end][::-1])
    return n, window[end - size : end]


def holds(window: np.ndarray, answer: np.ndarray) -> bool:
    n = len(answer)
    return n > 0 and any((window[k : k + n] == answer).all() for k in np.flatnonzero(window[: len(window) - n + 1] == answer[0]))


def blocks_of(bench: DataFrame, most: int) -> Iterator[list[tuple]]:
    """The items, block by block; a block has about `most`."""
    n = -(-bench.count() // most)
    number = F.pmod(F.xxhash64("item_id", "text", "answer"), F.lit(max(n, 1)))
    for k in range(n):
        rows = ((r["item_id"], r["text"] or "", r["answer"] or "") for r in bench.filter(number == k).collect())
        yield sorted(rows, key=lambda r: (r[0] is None, r[0] or 0, *r[1:]))  # each time in one order


def weights_of(own: list, place: np.ndarray, idf: np.ndarray) -> list[tuple]:
    """(passage, dims, weights): the rows of the TF-IDF matrix."""
    rows = []
    for i, (_, w, _) in enumerate(own):
        d, inv = np.unique(place[w], return_inverse=True)
        rows.append((i, d.tolist(), np.bincount(inv, weights=idf[w]).tolist()))
    return rows


MATRIX = "passage long, dims array<long>, weights array<double>"
SCHEMA = "doc_id long, item_id long, cosine double, cover double"


def leaks(documents: DataFrame, benchmark: DataFrame, rank: int = RANK, min_cosine: float | None = None, block: int = BLOCK) -> DataFrame:
    """(doc_id, item_id, cosine, cover): pairs of a document and an item that leaks into it.

    With min_cosine, a paraphrase without the answer is a leak too, if its stretch has this latent cosine with the passage.
    One latent space is fitted to the passages of the whole benchmark; the corpus is then searched for a block of items at a time.
    """
    spark = documents.sparkSession
    docs = pick(documents, doc_id="long", text="string")
    bench = pick(benchmark, item_id="long", text="string", answer="string")
    counted, matrix, used, n_passages = [], None, np.zeros(0, np.int64), 0
    for items in blocks_of(bench, block):
        vocabulary, own = passages(items)
        counted.append(document_frequencies(docs, vocabulary) if own else None)
        if own:
            place = folded(vocabulary)
            rows = save(spark.createDataFrame(weights_of(own, place, inverse_frequencies(counted[-1], len(vocabulary))), MATRIX))
            matrix = rows if matrix is None else matrix.union(rows)
            used, n_passages = np.union1d(used, place), n_passages + len(own)
    if matrix is None:
        return spark.createDataFrame([], SCHEMA)
    own = randomised_svd(matrix, min(rank, n_passages), used=used)
    directions = np.zeros((DIMS, own.shape[1]), np.float32)
    directions[used] = own
    out = None
    for items, count in zip(blocks_of(bench, block), counted, strict=True):
        if count is not None:
            found = search(spark, docs, passages(items), count, directions, min_cosine)
            out = found if out is None else out.union(found)
    return out.groupBy("doc_id", "item_id").agg(F.max("cosine").alias("cosine"), F.max("cover").alias("cover"))


def search(spark, docs: DataFrame, bench: tuple, counted: DataFrame, directions: np.ndarray, min_cosine: float | None) -> DataFrame:
    """The leaks of a block. Its broadcast holds the words and passages of at most about BLOCK items."""
    vocabulary, own = bench
    idf = inverse_frequencies(counted, len(vocabulary))
    place = folded(vocabulary)
    table = (directions[place] * idf[:, None]).astype(np.float32)  # words x rank
    latent = np.stack([np.asarray(w, np.float32) @ directions[d] for _, d, w in weights_of(own, place, idf)])
    norm = np.sqrt(np.square(latent).sum(1))
    held = np.unique(np.concatenate([i * len(vocabulary) + w.astype(np.int64) for i, (_, w, _) in enumerate(own)]))
    least = np.array([min(needed(len(w), MIN_COVER), needed(len(w), MIN_COVER_ANSWER)) for _, w, _ in own])
    shared = spark.sparkContext.broadcast((vocabulary, table, latent, norm, own, postings(own, idf), held, least))
    del table, latent, held
    trim()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary, table, latent, norm, own, index, held, least = shared.value
        for b in pieces(batches, most=SLICE):
            ids = b.column(b.schema.get_field_index("doc_id")).to_pylist()
            offs, h = terms(b.column(b.schema.get_field_index("text")), vocabulary)
            size = np.diff(offs)
            many = np.where(size > 0, np.maximum(1, -(-size // STRIDE) - 1), 0)
            first = np.concatenate([[0], np.cumsum(many)])
            window, passage = sharing(h, offs, first[:-1], many, index)
            row = np.searchsorted(first, window, "right") - 1
            begin = offs[row] + (window - first[row]) * STRIDE
            end = np.minimum(begin + WINDOW, offs[row + 1])
            found = []
            for at in range(0, len(window), 4096):
                x, y, j, r0 = (v[at : at + 4096] for v in (begin, end, passage, row))
                for k in np.flatnonzero(common(h, x, y, j, held, len(vocabulary)) >= least[j]):
                    item, p, answer = own[j[k]]
                    n, span = aligned(p, h[x[k] : y[k]])
                    cover = n / len(p)
                    if cover < MIN_COVER_ANSWER:
                        continue
                    vec = table[span[span >= 0]].sum(0)
                    cosine = vec @ latent[j[k]] / max(float(np.sqrt(np.square(vec).sum())) * norm[j[k]], 1e-9)
                    if cover >= MIN_COVER or (min_cosine is not None and cosine >= min_cosine and n >= MIN_COMMON) or holds(h[x[k] : y[k]], answer):
                        found.append((ids[r0[k]], item, float(cosine), cover))
            if found:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*found, strict=True), (pa.int64(), pa.int64(), pa.float64(), pa.float64()), strict=True)], names=["doc_id", "item_id", "cosine", "cover"])

    return docs.mapInArrow(run, SCHEMA)


def decontaminated(documents: DataFrame, benchmark: DataFrame, id: str = "doc_id", text: str = "text", min_cosine: float | None = MIN_COSINE) -> DataFrame:
    """The documents, with their columns, into which no item leaks. A row goes if its own text leaks, not for its id: of rows that share an id, the clean ones stay."""
    return without(documents, lambda rows: leaks(rows, benchmark, min_cosine=min_cosine), id, text)
