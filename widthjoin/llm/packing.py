"""Bounded-space online packing of documents into training sequences.

Each task keeps a fixed number of open windows. A document's ids are cut into
full sequences and a rest; the rest goes to the open window in which it leaves
the least room, and where it fits in none, the fullest window is closed and a
new one opened. At the end of a task its open windows are leftovers; groups of
tasks merge theirs, largest first, and close the fullest until as many are open
as a task keeps, so that each round of merging is no larger than the one before.

A sequence is padded to `size`, or not at all if its length is a power of two.
So a window that is full, or at a power of two when it is closed, costs nothing.

Null text: empty, which is the end id alone. Null ids and repeated rows are
documents of their own. Equal rooms: the window opened first. An empty table
gives no pieces. Only id and text are read.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import tokens
from .common import pick, pieces, save

SIZE, OPEN, END_ID = 2048, 64, 1
#: Tasks whose leftovers are merged by one task, in each round of merging.
MERGE = 32
#: A merged window filled to this share is not merged again.
NEARLY = 0.97
COLUMNS = (("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()))
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, task long, window long, offset long, used long, closed boolean"


class Packer:
    """Open windows of one task. A window is a list of pieces and the room that is left."""

    def __init__(self, size: int = SIZE, most: int = OPEN):
        self.size, self.most, self.open, self.made = size, most, {}, 0
        self.by_room: list[tuple[int, int]] = []  # (room, window), sorted

    def put(self, length: int, items: list) -> list | None:
        """Place items of a total length; a window that this closes, if any."""
        from bisect import bisect_left, insort

        done = None
        at = bisect_left(self.by_room, (length, -1))
        if at < len(self.by_room):
            room, w = self.by_room.pop(at)
            self.open[w] += items
        else:
            if len(self.open) >= self.most:
                done = self.open.pop(self.by_room.pop(0)[1])
            room, w, self.made = self.size, self.made, self.made + 1
            self.open[w] = list(items)
        if room == length:
            full = self.open.pop(w)
            return full if done is None else done + [None] + full
        insort(self.by_room, (room - length, w))
        return done


def rows_of(window: list, task: int, number: int, closed: bool) -> list[tuple]:
    used, at, out = sum(p[2] for p in window), 0, []
    for p in window:
        out.append((*p, task, number, at, used, closed))
        at += p[2]
    return out


def arrow(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [k for _, k in COLUMNS] + [pa.int64()] * 4 + [pa.bool_()]
    names = [x.split()[0] for x in SCHEMA.split(", ")]
    cols = list(zip(*rows, strict=True)) if rows else [[]] * len(names)
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=names)


def cut(doc_id, ids: np.ndarray, size: int) -> list[tuple]:
    """Pieces of a document: full ones first, then the rest."""
    raw, n = ids.astype("<u4"), len(ids)
    return [(doc_id, a, min(size, n - a), zlib.crc32(raw[a : a + size].tobytes()), n) for a in range(0, n, size)]


def pack_task(batches: Iterator[pa.RecordBatch], path: str, size: int = SIZE, most: int = OPEN, end_id: int = END_ID) -> Iterator[pa.RecordBatch]:
    task, packer, number, out = TaskContext.get().partitionId(), Packer(size, most), 0, []
    for b in pieces(batches):
        for doc_id, text in zip(b.column(b.schema.get_field_index("doc_id")).to_pylist(), b.column(b.schema.get_field_index("text")).to_pylist(), strict=True):
            for piece in cut(doc_id, np.array([*tokens.encode(path, text), end_id]), size):
                done = packer.put(piece[2], [piece])
                while done:
                    k = done.index(None) if None in done else len(done)
                    out += rows_of(done[:k], task, number, True)
                    done, number = done[k + 1 :], number + 1
            if len(out) > 20_000:
                yield arrow(out)
                out = []
    for _, w in packer.by_room:
        out += rows_of(packer.open[w], task, number, False)
        number += 1
    yield arrow(out)


def merge_group(t: pa.Table, size: int, nearly: float | None, turn: int, most: int) -> pa.Table:
    """Leftover windows of a group of tasks, by falling length, each into the fullest window with room.

    Windows filled to `nearly` are closed, and the fullest others, until at most `most` are open; None: all are closed.
    """
    windows: dict[tuple, list] = {}
    for r in sorted(t.to_pylist(), key=lambda r: (r["task"], r["window"], r["offset"])):
        windows.setdefault((r["task"], r["window"]), []).append(tuple(r[c] for c, _ in COLUMNS))
    packer, out = Packer(size, len(windows) + 1), []
    task, number = -1 - min(k[0] if k[0] >= 0 else -1 - k[0] for k in windows), turn << 24
    for w in sorted(windows.values(), key=lambda w: -sum(p[2] for p in w)):
        full = packer.put(sum(p[2] for p in w), w)
        if full:
            out += rows_of(full, task, number, True)
            number += 1
    for k, (room, w) in enumerate(packer.by_room):  # the fullest first
        over = len(packer.by_room) - k > most
        out += rows_of(packer.open[w], task, number, nearly is None or over or size - room >= nearly * size)
        number += 1
    return pa.Table.from_batches([arrow(out)])


def merger(size: int, nearly: float | None, turn: int, most: int):
    return lambda t: merge_group(t, size, nearly, turn, most)


def packed(documents: DataFrame, path: str | None = None, size: int = SIZE, most: int = OPEN, end_id: int = END_ID) -> DataFrame:
    """One row a piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset; and used, the sequence's length.

    Leftovers: rounds of merging, each over groups of MERGE tasks, with at most
    MERGE * most windows in a group; windows that are nearly full after a round are done.
    """
    path = path or tokens.vocabulary()
    docs = pick(documents, doc_id="long", text="string")
    first = save(docs.mapInArrow(lambda it: pack_task(it, path, size, most, end_id), SCHEMA))
    done, left = [first.filter("closed")], first.filter("NOT closed")
    own = F.when(F.col("task") < 0, -1 - F.col("task")).otherwise(F.col("task"))
    width, turn = MERGE, 1
    tasks = (first.agg(F.max("task")).first()[0] or 0) + 1
    while True:
        last = width >= tasks
        group = F.floor(own / width).alias("g")
        nearly = None if last else NEARLY
        merged = save(left.withColumn("g", group).groupBy("g").applyInArrow(merger(size, nearly, turn, most), SCHEMA))
        done.append(merged.filter("closed"))
        if last:
            break
        left, width, turn = merged.filter("NOT closed"), width * MERGE, turn + 1
    out = done[0]
    for d in done[1:]:
        out = out.union(d)
    # task and window number a sequence; first tasks are >= 0, merging ones below
    number = F.col("task") * F.lit(1 << 32) + F.col("window")
    return out.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", number.alias("sequence_id"), "offset", "used")


def padding(pieces_: DataFrame, size: int = SIZE) -> DataFrame:
    """Measure: sequences, tokens, padded tokens and their share."""
    s = pieces_.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    pad = F.when(F.col("n").bitwiseAND(F.col("n") - 1) == 0, 0).otherwise(size - F.col("n"))
    return s.agg(F.count(F.lit(1)).alias("sequences"), F.sum("n").alias("tokens"), F.sum(pad).alias("padding")).withColumn("share", F.col("padding") / F.col("tokens"))
