"""Toxicity: a linear-chain conditional random field that tags toxic tokens.

Labels are of documents, so tokens get weak labels first: word and prefix features
are chosen one by one, each the one that explains most toxic documents not
explained so far and hardly any other; tokens of toxic documents with a chosen
feature are toxic. On these tokens the field is trained (two states; hashed word
and affix features, start and transition weights) by gradient steps on the exact
log-likelihood, with a ridge on feature weights. Forward-backward marginals give offending offsets, and, by a
logistic function fitted on the training documents, the score of a document.

The training sample is bounded by TRAIN_DOCS and TRAIN_CHARS (rows with the
least hashes of their ids, whole texts). Scores are of whole texts of all rows.
Null or empty text: no tokens, the score is the logistic function's value at
zero. Missing classes in the labels: a constant score, the toxic share (0 if
there are no labels). Repeated rows are scored alike; labels that repeat an id
count by their largest value. Only id, text and label are read.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import coded, hashes, pick, pieces, trim, words

TRAIN_DOCS, TRAIN_CHARS = 5000, 25_000_000
#: Of these, the field is fitted on all toxic documents and the first FIT_CLEAN others.
FIT_CLEAN = 1000
DIMS = 1 << 17
PREFIXES = (3, 4, 5, 6)
#: A feature is chosen while it explains this many further toxic documents and this share of them, and its documents are toxic to this share.
MIN_GAIN, MIN_SHARE, MIN_PURITY = 3, 0.003, 0.9
BLOCK = 128
RIDGE = 0.05
SPAN_LIMIT = 0.5


@dataclass
class Model:
    weights: np.ndarray  # difference of the two states' emission, by hashed feature
    bias: float
    start: np.ndarray  # of both states
    move: np.ndarray  # 2 x 2
    link: np.ndarray  # logistic: intercept, and weights of the two aggregates
    constant: float | None = None


def normal(names: pa.Array) -> pa.Array:
    """Words in lower case without what is no letter or digit at their ends."""
    return pc.replace_substring_regex(pc.utf8_lower(names), r"^[^\p{L}\p{N}]+|[^\p{L}\p{N}]+$", "")


def features(names: pa.Array, dims: int = DIMS) -> np.ndarray:
    """Hashed feature indices of each distinct word: the word, its prefixes, its suffix, its shape."""
    names = names.cast(pa.string())
    n = normal(names)
    shape = pc.replace_substring_regex(pc.replace_substring_regex(names, r"\p{L}", "a"), r"\p{N}", "0")
    parts = [pc.binary_join_element_wise("w", n, "="), *[pc.binary_join_element_wise(f"p{k}", pc.utf8_slice_codeunits(n, 0, k), "=") for k in PREFIXES], pc.binary_join_element_wise("s", pc.utf8_slice_codeunits(n, -3), "="), pc.binary_join_element_wise("f", pc.utf8_slice_codeunits(shape, 0, 8), "=")]
    return np.stack([(hashes(p.cast(pa.string())) % np.uint64(dims)).astype(np.int32) for p in parts], 1) if len(n) else np.zeros((0, len(parts)), np.int32)


def emissions(model: Model, text: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    offs, flat = words(text)
    ids, names = coded(flat)
    own = model.weights[features(names, len(model.weights))].sum(1) + model.bias
    return offs, own[ids] if len(ids) else np.zeros(0)


def chains(offs: np.ndarray, em: np.ndarray, start: np.ndarray, move: np.ndarray, pairs: bool = False) -> tuple:
    """Marginals of state 1 and log-partition of each row; with pairs, also the expected number of each move, summed over all rows.

    Rows are cut into blocks of BLOCK tokens that run side by side. A first pass
    gets each block's transfer matrix, a short one chains the blocks of a row, and
    then forward and backward messages run within blocks.
    """
    size = np.diff(offs)
    nb = -(-size // BLOCK)
    first = np.concatenate([[0], np.cumsum(nb)])
    total = int(first[-1])
    if not total:
        return (np.zeros(0), np.zeros(len(size)), np.zeros((2, 2)))[: 2 + pairs]
    row = np.repeat(np.arange(len(size)), nb)
    inner = np.arange(total) - first[row]
    begin = offs[row] + inner * BLOCK
    length = np.minimum(BLOCK, offs[row + 1] - begin)
    order = np.argsort(-length, kind="stable")
    alive = np.searchsorted(-length[order], -np.arange(BLOCK), "left")  # blocks with more than t tokens
    (m00, m01), (m10, m11) = np.exp(move)
    e1 = np.exp(np.clip(em, -50, 50))
    b0 = begin[order]
    s0, s1 = np.exp(start)
    opens = (inner == 0)[order]
    # transfer of a block: txy from state x before it to state y at its end
    t = [np.ones(total), np.zeros(total), np.zeros(total), np.ones(total)]
    scale = np.zeros(total)
    for k in range(BLOCK):
        m = alive[k]
        if not m:
            break
        e = e1[b0[:m] + k]
        x00, x01, x10, x11 = (x[:m] for x in t)
        n00, n01, n10, n11 = x00 * m00 + x01 * m10, (x00 * m01 + x01 * m11) * e, x10 * m00 + x11 * m10, (x10 * m01 + x11 * m11) * e
        if k == 0:  # a row's first token follows no other: from either state, the start weights
            o = opens[:m]
            n00[o] = n10[o] = s0
            n01[o] = n11[o] = s1 * e[o]
        c = n00 + n01 + n10 + n11
        scale[:m] += np.log(c)
        for x, new in zip(t, (n00, n01, n10, n11), strict=True):
            x[:m] = new / c
    back = np.empty(total, np.int64)
    back[order] = np.arange(total)
    t = np.stack(t, 1)[back].reshape(total, 2, 2)
    scale = scale[back]
    entry = np.zeros((total, 2))
    exit_ = np.ones((total, 2))
    logz = np.zeros(len(size))
    most = int(nb.max())
    cur = np.tile([1.0, 0.0], (len(size), 1))
    for k in range(most):
        r = np.flatnonzero(nb > k)
        i = first[r] + k
        entry[i] = cur[r]
        nxt = np.einsum("rx,rxy->ry", cur[r], t[i])
        c = nxt.sum(1)
        cur[r] = nxt / c[:, None]
        logz[r] += np.log(c) + scale[i]
    cur = np.ones((len(size), 2))
    for k in range(most - 1, -1, -1):
        r = np.flatnonzero(nb > k)
        i = first[r] + k
        exit_[i] = cur[r]
        nxt = np.einsum("rxy,ry->rx", t[i], cur[r])
        cur[r] = nxt / nxt.sum(1)[:, None]
    # share of state 1 in the forward message, then with the backward message beside it
    fw = np.zeros(len(em))
    a0, a1 = entry[order].T.copy()
    for k in range(BLOCK):
        m = alive[k]
        if not m:
            break
        at = b0[:m] + k
        n0, n1 = a0[:m] * m00 + a1[:m] * m10, a0[:m] * m01 + a1[:m] * m11
        if k == 0:
            n0[opens[:m]], n1[opens[:m]] = s0, s1
        n1 *= e1[at]
        a1[:m] = n1 / (n0 + n1)
        a0[:m] = 1 - a1[:m]
        fw[at] = a1[:m]
    out, bw = np.zeros(len(em)), np.zeros(len(em) if pairs else 0)
    z0, z1 = exit_[order].T.copy()
    for k in range(BLOCK - 1, -1, -1):
        m = alive[k]
        if not m:
            continue
        at = b0[:m] + k
        up, down = fw[at] * z1[:m], (1 - fw[at]) * z0[:m]
        out[at] = up / (up + down)
        if pairs:
            bw[at] = z1[:m] / (z0[:m] + z1[:m])
        y1 = z1[:m] * e1[at]
        n0, n1 = z0[:m] * m00 + y1 * m01, z0[:m] * m10 + y1 * m11
        z1[:m] = n1 / (n0 + n1)
        z0[:m] = 1 - z1[:m]
    if not pairs:
        return out, logz
    inner = np.ones(len(em), bool)
    inner[offs[:-1][size > 0]] = False
    at = np.flatnonzero(inner)
    a1, y0, y1 = fw[at - 1], 1 - bw[at], bw[at] * e1[at]
    joint = np.stack([(1 - a1) * m00 * y0, (1 - a1) * m01 * y1, a1 * m10 * y0, a1 * m11 * y1])
    return out, logz, (joint / joint.sum(0)).sum(1).reshape(2, 2)


def gradient(model: Model, feats: np.ndarray, ids: np.ndarray, offs: np.ndarray, gold: np.ndarray) -> tuple[np.ndarray, float, np.ndarray, np.ndarray]:
    """Of the log-likelihood of the gold states, by feature weights, bias, start and moves: seen less expected counts."""
    em = (model.weights[feats].sum(1) + model.bias)[ids]
    p, _, expected = chains(offs, em, model.start, model.move, pairs=True)
    diff = np.bincount(ids, weights=gold - p, minlength=len(feats))
    first = offs[:-1][np.diff(offs) > 0]
    inner = np.ones(len(ids), bool)
    inner[first] = False
    at = np.flatnonzero(inner)
    seen = np.bincount(2 * gold[at - 1].astype(int) + gold[at], minlength=4).reshape(2, 2)
    start = float((gold[first] - p[first]).sum())
    return np.bincount(feats.ravel(), weights=np.repeat(diff, feats.shape[1]), minlength=len(model.weights)), float(diff.sum()), np.array([-start, start]), seen - expected


def parts_of(words_: set[str]) -> set[str]:
    return {f"={w}" for w in words_} | {w[:k] for w in words_ for k in PREFIXES if len(w) >= k}


def explained(texts: list[str], toxic: np.ndarray) -> set[str]:
    """Chosen features: whole words "=x" and prefixes "x". Counts of other documents are kept only for what toxic ones have often."""
    least = max(MIN_GAIN, MIN_SHARE * int(toxic.sum()))
    often: Counter = Counter()
    for own in distinct([texts[i] for i in np.flatnonzero(toxic)]):
        often.update(parts_of(own))
    docs: dict[str, set[int]] = {f: set() for f, n in often.items() if n >= least}
    del often
    clean: Counter = Counter()
    for i, own in enumerate(distinct(texts)):
        own = parts_of(own) & docs.keys()
        if toxic[i]:
            for f in own:
                docs[f].add(i)
        else:
            clean.update(own)
    cand = {f: v for f, v in docs.items() if len(v) >= MIN_PURITY * (len(v) + clean[f])}
    chosen: set[str] = set()
    left = set(np.flatnonzero(toxic).tolist())
    while cand:
        gain = {f: len(v & left) for f, v in cand.items()}
        cand = {f: v for f, v in cand.items() if gain[f] >= least}
        if not cand:
            break
        # of equal gain the purer, then the longer and so more specific one
        best = max(cand, key=lambda f: (gain[f] - 2 * clean[f], len(f.lstrip("=")), f))
        chosen.add(best)
        left -= cand.pop(best)
    return chosen


def train(rows: list[tuple[str, int]], dims: int = DIMS, rounds: int = 20, rate: float = 0.5) -> Model:
    toxic = np.array([y for _, y in rows], bool)
    zero = Model(np.zeros(dims, np.float32), 0.0, np.zeros(2), np.zeros((2, 2)), np.zeros(3), float(toxic.mean()) if len(rows) else 0.0)
    if not toxic.any() or toxic.all():
        return zero
    chosen = explained([t or "" for t, _ in rows], toxic)
    if not chosen:
        return zero
    fit = np.flatnonzero(toxic | (np.cumsum(~toxic) <= FIT_CLEAN))
    offs, flat = words(pa.array([rows[i][0] or "" for i in fit], pa.large_string()))
    ids, names = coded(flat)
    hit = np.array([f"={w}" in chosen or any(w[:k] in chosen for k in PREFIXES if len(w) >= k) for w in normal(names).to_pylist()], bool)
    gold = hit[ids] & np.repeat(toxic[fit], np.diff(offs))
    feats = features(names, dims)
    model = Model(np.zeros(dims), -2.0, np.zeros(2), np.zeros((2, 2)), np.zeros(3))
    g2 = {k: 1e-3 for k in ("bias", "start", "move")}
    w2 = np.full(dims, 1e-3)
    for _ in range(rounds):
        gw, gb, gs, gm = gradient(model, feats, ids, offs, gold)
        gw -= RIDGE * model.weights
        w2 += gw**2
        model.weights += rate * gw / np.sqrt(w2)
        g2["bias"] = g2["bias"] + gb**2
        model.bias += rate * gb / math.sqrt(g2["bias"])
        g2["move"] = g2["move"] + gm**2
        model.move = np.clip(model.move + 0.1 * gm / np.sqrt(g2["move"]), -3, 3)
        g2["start"] = g2["start"] + gs**2
        model.start = np.clip(model.start + 0.1 * gs / np.sqrt(g2["start"]), -3, 3)
    del feats, ids, gold, offs, w2
    model.weights = model.weights.astype(np.float32)
    found = []
    for at in range(0, len(rows), 500):
        o, em = emissions(model, pa.array([t or "" for t, _ in rows[at : at + 500]], pa.large_string()))
        found.append(aggregates(chains(o, em, model.start, model.move)[0], o))
    model.link = fitted(np.concatenate(found), toxic)
    trim()
    return model


def distinct(texts: list[str], step: int = 500) -> Iterator[set[str]]:
    """Distinct normal words of each text, some texts at a time."""
    for at in range(0, len(texts), step):
        offs, flat = words(pa.array(texts[at : at + step], pa.large_string()))
        ids, names = coded(flat)
        own = normal(names).to_pylist()
        for a, b in zip(offs[:-1], offs[1:], strict=True):
            yield {own[i] for i in np.unique(ids[a:b])} - {""}


def aggregates(p: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """Of each row: log-odds of its largest marginal, and log of one plus the sum of marginals."""
    most = np.zeros(len(offs) - 1)
    full = np.flatnonzero(np.diff(offs) > 0)
    if len(full):
        most[full] = np.maximum.reduceat(p, offs[full])
    most = np.clip(most, 1e-6, 1 - 1e-6)
    total = np.concatenate([[0.0], np.cumsum(np.where(p >= 0.05, p, 0.0))])
    return np.stack([np.log(most / (1 - most)), np.log1p(total[offs[1:]] - total[offs[:-1]])], 1)


def fitted(x: np.ndarray, y: np.ndarray, steps: int = 50) -> np.ndarray:
    """Logistic regression by ridge Newton steps."""
    x = np.concatenate([np.ones((len(x), 1)), x], 1)
    w = np.zeros(x.shape[1])
    for _ in range(steps):
        q = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        h = x.T @ (x * (q * (1 - q))[:, None]) + np.diag([1e-3, 0.05, 0.05])
        step = np.linalg.solve(h, x.T @ (y - q) - np.array([1e-3, 0.05, 0.05]) * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def training_rows(documents: DataFrame, labels: DataFrame, label: str, where=None, n_docs: int = TRAIN_DOCS, n_chars: int = TRAIN_CHARS) -> list[tuple[str, int]]:
    """The bounded sample: labelled documents in the order of their ids' hashes, but for those whose text no longer fits; one text an id."""
    y = pick(labels, **{"doc_id": "long", label: "int"}).filter(f"doc_id IS NOT NULL AND {label} IS NOT NULL").groupBy("doc_id").agg(F.max(label).alias("y"))
    if where is not None:
        y = y.filter(where("doc_id"))
    docs = pick(documents, doc_id="long", text="string")
    y = y.join(docs.select("doc_id"), "doc_id", "left_semi")
    y = y.orderBy(F.xxhash64("doc_id"), "doc_id").limit(n_docs).withColumnRenamed("doc_id", "labelled")
    rows = docs.join(F.broadcast(y), F.col("doc_id") == F.col("labelled")).select("doc_id", "text", "y", F.xxhash64("text").alias("h"), F.length("text").alias("n"))
    # the ids are bounded; lengths first, so that no more text than the bound reaches the driver
    one = rows.groupBy("doc_id").agg(F.min(F.struct("h", "n")).alias("x"), F.xxhash64("doc_id").alias("o")).select("o", "doc_id", "x.h", "x.n")
    used, chosen = 0, []
    for r in sorted(one.collect(), key=lambda r: (r["o"], r["doc_id"])):
        if used + (r["n"] or 0) <= n_chars:
            used += r["n"] or 0
            chosen.append((r["o"], r["doc_id"], r["h"]))
    if not chosen:
        return []
    of = documents.sparkSession.createDataFrame(chosen, "o long, id long, k long")
    kept = rows.join(F.broadcast(of), (F.col("doc_id") == F.col("id")) & (F.col("h") == F.col("k"))).groupBy("o", "id").agg(F.first("text").alias("text"), F.max("y").alias("y"))
    return [(r["text"], r["y"]) for r in sorted(kept.toLocalIterator(), key=lambda r: (r["o"], r["id"]))]


def scored(documents: DataFrame, model: Model, spans: bool = False) -> DataFrame:
    """doc_id, score, and with spans the offending ones: (start, end) code points of tokens with a marginal of at least SPAN_LIMIT."""
    shared = documents.sparkSession.sparkContext.broadcast(model)  # DIMS weights: a fixed size
    schema = "doc_id long, score double" + (", spans array<struct<s:int,e:int,p:double>>" if spans else "")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in pieces(batches):
            text = b.column(b.schema.get_field_index("text"))
            offs, em = emissions(m, text)
            if m.constant is not None:
                p, score = np.zeros(len(em)), np.full(len(text), m.constant)
            else:
                p, _ = chains(offs, em, m.start, m.move)
                score = 1 / (1 + np.exp(-np.clip(m.link[0] + aggregates(p, offs) @ m.link[1:], -30, 30)))
            cols = [b.column(b.schema.get_field_index("doc_id")), pa.array(score)]
            if spans:
                cols.append(pa.array([offending(t, p[a:z]) for t, a, z in zip(text.to_pylist(), offs[:-1], offs[1:], strict=True)], pa.list_(pa.struct([("s", pa.int32()), ("e", pa.int32()), ("p", pa.float64())]))))
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "score", "spans"][: len(cols)])

    return pick(documents, doc_id="long", text="string").mapInArrow(run, schema)


def offending(text: str, p: np.ndarray) -> list[dict]:
    import re

    if not (p >= SPAN_LIMIT).any():
        return []
    return [{"s": m.start(), "e": m.end(), "p": float(q)} for m, q in zip(re.finditer(r"[^\x20\x09-\x0D]+", text), p, strict=True) if q >= SPAN_LIMIT]


def train_on(documents: DataFrame, labels: DataFrame, where=None) -> Model:
    return train(training_rows(documents, labels, "toxic", where))
