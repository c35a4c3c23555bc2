"""Quality rules: base counts of a text, and cross-document line frequency by host.

Normalised lines are hashed; for each host the documents with a line are
counted; lines above the limits are removed from the text; a document that
keeps too small a share of its words is rejected.

Null text: no words, so the base rejects it; it counts as a document of its
host. Null host: a host of its own. Lines without a word count for nothing.
Repeated rows are documents of their own. A line at a limit stays. An empty
table gives an empty result; other columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import coded, pick, pieces, sums, words
from .line_dedup import drop_boilerplate

#: A line is over the limits in a host if this many of its documents, and more than this share of them, have it.
MIN_DOCS, MAX_SHARE = 2, 0.05
#: A document is depleted if it keeps less than this share of its words.
MIN_KEPT = 0.5
SYMBOLS = b"#*$%&|<>"
SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, n_kept_words long, cleaned string"


def repeated_words(ids: np.ndarray, offs: np.ndarray) -> np.ndarray:
    """For each row, the words that lie in a 3-word window found twice or more in the row."""
    n, size = len(ids), np.diff(offs)
    if n < 3:
        return np.zeros(len(size), np.int64)
    row = np.repeat(np.arange(len(size)), size)
    with np.errstate(over="ignore"):
        mult = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93], np.uint64)
        u = (ids + 1).astype(np.uint64)
        key = u[:-2] * mult[0] + u[1:-1] * mult[1] + u[2:] * mult[2] + row[:-2].astype(np.uint64) * mult[3]
    inside = row[:-2] == row[2:]
    at = np.flatnonzero(inside)
    order = at[np.argsort(key[at])]
    same = key[order[1:]] == key[order[:-1]]
    twice = np.zeros(n, bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = twice.copy()
    covered[1:] |= twice[:-1]
    covered[2:] |= twice[:-2]
    return sums(covered, offs)


def repeated_lines(text: pa.Array) -> np.ndarray:
    """For each row, the lines with a word that equal an earlier line."""
    split = pc.split_pattern(text, "\n")
    offs, flat = split.offsets.to_numpy().astype(np.int64), split.flatten()
    offs = offs - offs[0]
    ids, _ = coded(flat)
    full = pc.greater(pc.binary_length(pc.ascii_trim_whitespace(flat)), 0).to_numpy(zero_copy_only=False).astype(bool)
    row = np.repeat(np.arange(len(offs) - 1), np.diff(offs))
    n = sums(full, offs)
    key = np.unique((row * (len(flat) + 1) + ids)[full])
    return n - np.bincount(key // (len(flat) + 1), minlength=len(n))


def base_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    lookup = np.zeros(256, bool)
    lookup[list(SYMBOLS)] = True
    for b in pieces(batches):
        text = b.column(b.schema.get_field_index("text"))
        offs, flat = words(text)
        ids, _ = coded(flat)
        raw = [np.frombuffer(x, np.uint8) if x is not None else np.zeros(0, np.uint8) for x in [text.buffers()[2]]][0]
        at = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1]
        symbols = sums(lookup[raw[at[0] : at[-1]]], at - at[0])
        chars = sums(pc.utf8_length(flat).to_numpy(zero_copy_only=False), offs)
        cleaned = b.column(b.schema.get_field_index("cleaned"))
        changed = pc.is_valid(cleaned).to_numpy(zero_copy_only=False).astype(bool)
        left = np.diff(offs)
        left[changed] = np.diff(words(cleaned.filter(pa.array(changed)).cast(pa.large_string()))[0])
        cols = [np.diff(offs), chars, symbols, repeated_lines(text), repeated_words(ids, offs), left]
        yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index("doc_id"))] + [pa.array(c.astype(np.int64)) for c in cols] + [cleaned], names=[x.split()[0] for x in SCHEMA.split(", ")])


def quality(documents: DataFrame, min_docs: int = MIN_DOCS, max_share: float = MAX_SHARE, min_kept: float = MIN_KEPT) -> DataFrame:
    """doc_id, base counts, base_failed, n_lost_words, kept, and cleaned: the text without the lines over the limits, null where it has none of them."""
    docs = pick(documents, doc_id="long", source="string", text="string").withColumn("cleaned", F.col("text"))
    docs = drop_boilerplate(docs, "cleaned", "source", max_share, min_docs, counts=False)
    base = docs.select("doc_id", "text", F.when(F.col("cleaned") != F.col("text"), F.col("cleaned")).alias("cleaned")).mapInArrow(base_counts, SCHEMA)
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return base.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words",
        failed.alias("base_failed"), (F.col("n_words") - F.col("n_kept_words")).alias("n_lost_words"),
        (~failed & (F.col("n_kept_words") >= min_kept * F.col("n_words"))).alias("kept"), "cleaned",
    )


ORACLE_SQL = rf"""
WITH d AS (SELECT doc_id, source, coalesce(text, '') AS text FROM documents),
w AS (SELECT doc_id, ws, unnest(ws) AS w, generate_subscripts(ws, 1) AS i FROM (SELECT doc_id, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS ws FROM d)),
t AS (SELECT doc_id, i, w || chr(10) || lead(w, 1) OVER o || chr(10) || lead(w, 2) OVER o AS g FROM w WINDOW o AS (PARTITION BY doc_id ORDER BY i)),
g AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS n FROM t WHERE g IS NOT NULL) WHERE n > 1),
r AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM g, (SELECT unnest([0, 1, 2]) AS j) GROUP BY doc_id),
b AS (SELECT doc_id, count(*) AS n, sum(length(w)) AS chars FROM w GROUP BY doc_id),
l AS (SELECT doc_id, source, text, unnest(string_split(text, chr(10))) AS line FROM d),
f AS (SELECT doc_id, source, text, line, trim(regexp_replace(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+', ' ', 'g')) AS k, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS n FROM l WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
u AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n FROM f GROUP BY doc_id),
h AS (SELECT source, count(*) AS n FROM d GROUP BY source),
c AS (SELECT source, k, count(DISTINCT doc_id) AS n FROM f GROUP BY source, k),
o AS (SELECT c.source, k FROM c JOIN h ON c.source IS NOT DISTINCT FROM h.source WHERE c.n >= {MIN_DOCS} AND c.n > {MAX_SHARE} * h.n),
x AS (SELECT doc_id, sum(n) AS n FROM f JOIN o ON f.source IS NOT DISTINCT FROM o.source AND f.k = o.k GROUP BY doc_id),
a AS (SELECT d.doc_id, coalesce(b.n, 0)::BIGINT AS n_words, coalesce(b.chars, 0)::BIGINT AS word_chars,
        length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, coalesce(u.n, 0)::BIGINT AS n_dup_lines, coalesce(r.n, 0)::BIGINT AS n_repeat_words, coalesce(x.n, 0)::BIGINT AS n_lost_words
      FROM d LEFT JOIN b ON b.doc_id = d.doc_id LEFT JOIN u ON u.doc_id = d.doc_id LEFT JOIN r ON r.doc_id = d.doc_id LEFT JOIN x ON x.doc_id = d.doc_id),
z AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM a)
SELECT *, NOT base_failed AND n_words - n_lost_words >= {MIN_KEPT} * n_words AS kept FROM z
"""
