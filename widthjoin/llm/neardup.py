"""MinHash near-dedup: one-permutation hashing with optimal densification, banded buckets, star-shaped candidate edges.

A document's set is its distinct k-word shingles. Equal sets are one class with
one representative. Each representative's set is hashed once; each bin keeps its
least hash, empty bins borrow from a bin that a fixed random walk over the bins
finds first, each bin by a walk of its own (densification), and bands of bins are bucket keys. In each bucket
the first member is the centre of a star: members are compared with it on full
sets, so a bucket of n rows makes n - 1 pairs. Members that end up outside their
centre's component become centres themselves, for the members of other
components: their full sets meet inside the bucket, one centre with all members at
once, and a link joins its two components, so that only links that connect something
are made into rows. Nothing is capped, and a large group of copies costs one star.

Null or empty text: empty set, no links. Fewer words than k: the whole sequence
is the one shingle. Texts are told apart by their sets, not by their ids: rows
that repeat an id with another text are rows of their own. Rows without an id
take part; their component has the smallest id in it, null if it has none. An empty table gives an empty result; only id
and text are read, so other columns' names do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import coded, delete, hashes, mixed, pick, pieces, row_key, save, scratch, small, trim, unused, words

BINS, ROWS = 128, 4
#: Bins of a sketch that tells similarities well; rows of the blocks into which buckets are split, and hashes a row of a full block.
SKETCH, BLOCK_CENTRES, BLOCK_MEMBERS, BLOCK_SET = 1024, 512, 2048, 1024
SIGNED = "doc_id long, row_key long, n_shingles long, set_key binary, bands array<long>"
MULT = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53, 0x2545F4914F6CDD1D)


def shingle_sets(text: pa.Array, k: int) -> Iterator[np.ndarray]:
    """Sorted distinct 64-bit hashes of each row's shingles, words lower-cased in A-Z."""
    offs, flat = words(text, lower=True)
    ids, names = coded(flat)
    own = hashes(names)[ids] if len(ids) else np.zeros(0, np.uint64)
    n = len(own)
    with np.errstate(over="ignore"):
        whole = np.zeros(max(0, n - k + 1), np.uint64)
        for j in range(k if n >= k else 0):
            whole += own[j : n - k + 1 + j] * np.uint64(MULT[j % len(MULT)] + 2 * (j // len(MULT)))
        whole = mixed(whole)
        for a, b in zip(offs[:-1], offs[1:], strict=True):
            if b - a >= k:
                yield np.unique(whole[a : b - k + 1])
            elif b > a:
                short = sum((own[a + j] * np.uint64(MULT[j % len(MULT)]) for j in range(b - a)), np.uint64(b - a))
                yield mixed(np.array([short], np.uint64))
            else:
                yield np.zeros(0, np.uint64)


def walk(bins: int, steps: int = 64) -> np.ndarray:
    """For each bin, the fixed random bins that it tries in turn when it is empty."""
    at = np.arange(bins, dtype=np.uint64)[:, None] * np.uint64(1 << 20) + np.arange(steps, dtype=np.uint64)[None, :]
    return (mixed(at + np.uint64(0x51ED2701)) % np.uint64(bins)).astype(np.int64)


def densified(own: np.ndarray, bins: int, tries: np.ndarray) -> np.ndarray:
    """One-permutation sketch of a sorted non-empty hash set; bins must be a power of two."""
    shift = np.uint64(64 - bins.bit_length() + 1)
    starts = np.searchsorted(own, np.arange(bins, dtype=np.uint64) << shift)
    ends = np.append(starts[1:], len(own))
    full = ends > starts
    out = np.zeros(bins, np.uint64)
    out[full] = own[starts[full]]
    if not full.all():
        empty = np.flatnonzero(~full)
        found = full[tries[empty]]
        first = tries[empty, found.argmax(1)]
        lost = np.flatnonzero(~found.any(1))
        if len(lost):  # few bins are full: each empty bin goes on through all bins in an order of its own
            have = np.flatnonzero(full)
            rank = mixed((empty[lost].astype(np.uint64)[:, None] << np.uint64(32)) + have.astype(np.uint64)[None, :] + np.uint64(0x2F0B4C47))
            first[lost] = have[rank.argmin(1)]
        out[empty] = out[first]
    return out


def band_keys(own: np.ndarray, bins: int, rows: int, tries: np.ndarray) -> np.ndarray:
    bands = bins // rows
    lift = (np.arange(rows, dtype=np.uint64) * np.uint64(2) + np.uint64(1)) * np.uint64(MULT[0])
    with np.errstate(over="ignore"):
        d = mixed(densified(own, bins, tries)).reshape(bands, rows)
        return mixed((d * lift).sum(1, dtype=np.uint64) + mixed(np.arange(bands, dtype=np.uint64) + np.uint64(77))).view(np.int64)


def signatures(batches: Iterator[pa.RecordBatch], k: int, bins: int = BINS, rows: int = ROWS) -> Iterator[pa.RecordBatch]:
    import hashlib

    tries, names = walk(bins), [x.split()[0] for x in SIGNED.split(", ")]
    for b in pieces(batches):
        size, key, sig = [], [], []
        for s in shingle_sets(b.column(b.schema.get_field_index("text")), k):
            size.append(len(s))
            if not len(s):
                key.append(None)
                sig.append(None)
                continue
            key.append(hashlib.md5(s.tobytes()).digest())
            sig.append(band_keys(s, bins, rows, tries))
        yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index("doc_id")), b.column(b.schema.get_field_index("row_key")), pa.array(size, pa.int64()), pa.array(key, pa.binary()), pa.array(sig, pa.list_(pa.int64()))], names=names)


def full_sets(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    """(id, set) of rows of (text, id, set_key) whose text has that set."""
    import hashlib

    for b in pieces(batches):
        keys, ids, own = b.column(b.schema.get_field_index("set_key")).to_pylist(), [], []
        for i, s in enumerate(shingle_sets(b.column(b.schema.get_field_index("text")), k)):
            raw = s.tobytes()
            if hashlib.md5(raw).digest() == keys[i]:
                ids.append(i)
                own.append(raw)
        yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index("id")).take(pa.array(ids, pa.int64())), pa.array(own, pa.binary())], names=["doc_id", "set"])


def linked(batches: Iterator[pa.RecordBatch], num: int, den: int) -> Iterator[pa.RecordBatch]:
    """Pairs whose full sets have den * |intersection| >= num * |union|."""
    for b in batches:
        keep = []
        for x, y in zip(b.column(b.schema.get_field_index("set_a")), b.column(b.schema.get_field_index("set_b")), strict=True):
            x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
            if den * min(len(x), len(y)) < num * max(len(x), len(y)):
                keep.append(False)
                continue
            if len(x) > len(y):
                x, y = y, x
            at = np.searchsorted(y, x)
            at[at == len(y)] = 0
            both = int((y[at] == x).sum()) if len(y) else 0
            keep.append(den * both >= num * (len(x) + len(y) - both))
        yield b.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))
        del b
    trim()


def components(edges: DataFrame) -> DataFrame:
    """(node, component): the least node reachable. Alternates large-star and small-star steps; edges only, nothing is collected."""

    def print_of(e):
        r = e.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0)).alias("h")).first()
        return r["n"], r["h"]

    def star(e, large: bool):
        both = e.union(e.select("b", "a"))
        side = both if large else both.filter("b < a")
        least = side.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("u"), F.least("a", "m").alias("m"))
        j = side.join(least, F.col("a") == F.col("u"))
        if large:
            out = j.filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        else:
            out = j.select(F.col("b").alias("a"), F.col("m").alias("b")).union(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
        return out.filter("a <> b").distinct()

    path = scratch(edges.sparkSession)
    e = save(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).filter("a <> b").distinct(), path=path)
    before = print_of(e)
    while before[0]:
        spent, path = path, scratch(edges.sparkSession)
        e = save(star(star(e, True), False), path=path)
        now = print_of(e)
        delete(edges.sparkSession, spent)
        if now == before:
            break
        before = now
    return e.select(F.col("a").alias("node"), F.col("b").alias("component"))


def classes_of(documents: DataFrame, k: int, num: int, den: int, bins: int, rows: int) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows (SIGNED), classes of equal sets, and (node, component) of classes with links.

    A class has a number of its own, rep, and its least row: (id is null, id, row_key).
    """
    docs = pick(documents, doc_id="long", text="string").withColumn("row_key", row_key(F.col("doc_id"), F.col("text")))
    signed = save(docs.mapInArrow(lambda it: signatures(it, k, bins, rows), SIGNED))
    least = F.struct(F.isnull("doc_id").alias("no_id"), "doc_id", "row_key")
    classes = signed.filter("set_key IS NOT NULL").groupBy("set_key").agg(F.min(least).alias("least"), F.any_value("n_shingles").alias("n"), F.any_value("bands").alias("bands"))
    classes = save(classes.withColumn("rep", F.monotonically_increasing_id()))
    buckets = classes.select(F.explode("bands").alias("key"), "rep", "n")
    shared = buckets.groupBy("key").agg(F.min(F.struct("rep", "n")).alias("least"), F.count(F.lit(1)).alias("many")).filter("many > 1").select("key", F.col("least.rep").alias("centre"), F.col("least.n").alias("centre_n"))
    # a bucket key is on few rows of distinct sets; where near copies fill one, this inner join on its key is split by AQE
    members = save(buckets.join(shared.withColumnRenamed("key", "k2"), F.col("key") == F.col("k2")).select("key", "rep", "n", "centre", "centre_n"))
    pairs = members.filter("rep <> centre").filter(alike("n", "centre_n", num, den)).select(F.col("centre").alias("a"), F.col("rep").alias("b")).distinct()
    pairs = save(pairs)
    needed = members.select(F.col("rep").alias("r2")).distinct().join(classes, F.col("rep") == F.col("r2")).select(F.col("rep").alias("id"), "set_key", F.col("least.row_key").alias("of_row"))
    wanted = docs.join(small(save(needed)), F.col("row_key") == F.col("of_row")).select("text", "id", "set_key")
    if not signed.groupBy("row_key").agg(F.count(F.lit(1)).alias("times")).filter("times > 1").isEmpty():
        wanted = wanted.dropDuplicates(["id"])  # repeated rows: one of each
    sets = save(wanted.mapInArrow(lambda it: full_sets(it, k), "doc_id long, set binary"), "none")
    links = save(compare(pairs, sets, num, den))
    labels = save(components(links))
    links = further_links(members, links, labels, sets, num, den, bins, rows)
    labels = labels if links is None else save(components(links))
    return signed, classes, labels.union(labels.select("component", "component").distinct())  # the least nodes too


def near_duplicates(documents: DataFrame, k: int = 3, num: int = 85, den: int = 100, bins: int = BINS, rows: int = ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: one row a document. Linked: den * |intersection| >= num * |union|."""
    signed, classes, labels = classes_of(documents, k, num, den, bins, rows)
    own = classes.select("set_key", "rep", "least").join(labels, F.col("rep") == F.col("node"), "left")
    # of linked classes alone, the least id of each component
    first = own.filter("component IS NOT NULL").groupBy("component").agg(F.min("least").alias("first")).withColumnRenamed("component", "c2")
    ids = own.join(first, F.col("component") == F.col("c2"), "left").select(F.col("set_key").alias("k2"), F.coalesce("first", "least")["doc_id"].alias("least_id"))
    whole = signed.join(ids, F.col("set_key") == F.col("k2"), "left")
    component = F.least(F.coalesce("least_id", "doc_id"), "doc_id")
    return whole.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(F.col("doc_id") == component, F.lit(True)).alias("kept"))


def alike(m: str, n: str, num: int, den: int):
    """Whether sets of these sizes can be linked at all."""
    return (den * F.least(m, n)) >= (num * F.greatest(m, n))


def with_bands(batches: Iterator[pa.RecordBatch], bins: int, rows: int) -> Iterator[pa.RecordBatch]:
    """Each set and its band keys."""
    tries = walk(bins)
    for b in batches:
        own = b.column(b.schema.get_field_index("set"))
        keys = [band_keys(np.frombuffer(x.as_buffer(), np.uint64), bins, rows, tries).tobytes() for x in own]
        yield pa.RecordBatch.from_arrays([b.column(b.schema.get_field_index("doc_id")), own, pa.array(keys, pa.binary())], names=["of", "set", "bands"])
        del b, own, keys
    trim()


def block_links(rows: dict[str, list], key: int, num: int, den: int) -> Iterator[tuple[int, int]]:
    """Links between a block's centres and its members in other components, by full sets; those that join nothing new are left out."""
    bands = np.frombuffer(b"".join(rows["bands"]), np.int64).reshape(len(rows["rep"]), -1)
    rep, n, centre = (np.asarray(rows[k]) for k in ("rep", "n", "centre"))
    c = np.unique(rows["c"], return_inverse=True)[1]
    starts = np.concatenate([[0], np.cumsum(n)])
    codes = np.unique(np.frombuffer(b"".join(rows["set"]), np.uint64), return_inverse=True)[1].astype(np.int32)
    mark = np.zeros(int(codes.max()) + 1, np.uint8)
    for i in np.flatnonzero(centre):
        ok = np.flatnonzero((c != c[i]) & (den * np.minimum(n, n[i]) >= num * np.maximum(n, n[i])))
        ok = ok[bands[i, (bands[ok] == bands[i]).argmax(1)] == key]  # a pair is compared in the first of the buckets that it shares
        if not len(ok):
            continue
        mark[codes[starts[i] : starts[i + 1]]] = 1
        both = np.add.reduceat(mark[codes], starts[:-1], dtype=np.int64)[ok]
        mark[codes[starts[i] : starts[i + 1]]] = 0
        for j in ok[den * both >= num * (n[i] + n[ok] - both)]:
            if c[j] != c[i]:
                c[c == c[j]] = c[i]
                yield int(min(rep[i], rep[j])), int(max(rep[i], rep[j]))


def near_links(batches: Iterator[pa.RecordBatch], num: int, den: int) -> Iterator[pa.RecordBatch]:
    """Links (a, b) of rows with equal (key, ob, mb), one of them a centre, in different components.

    Rows come sorted by these keys; a group has at most about BLOCK_CENTRES centres and BLOCK_MEMBERS others, fewer of long texts.
    """

    def out(pairs):
        own = sorted(set(pairs))
        return pa.RecordBatch.from_arrays([pa.array([p[k] for p in own], pa.int64()) for k in (0, 1)], names=["a", "b"])

    kept, own, found = {}, None, []
    for b in batches:
        cols = {k: b.column(b.schema.get_field_index(k)).to_pylist() for k in ("key", "ob", "mb", "rep", "n", "c", "centre", "set", "bands")}
        ids = list(zip(cols.pop("key"), cols.pop("ob"), cols.pop("mb"), strict=True))
        starts = [0, *(i for i in range(1, len(ids)) if ids[i] != ids[i - 1]), len(ids)]
        for x, y in zip(starts[:-1], starts[1:], strict=True):
            if ids[x:] and ids[x] != own:
                if kept:
                    found += block_links(kept, own[0], num, den)
                kept, own = {k: [] for k in cols}, ids[x]
            for k, v in cols.items():
                kept[k] += v[x:y]
        if len(found) > 50_000:
            yield out(found)
            found = []
    if kept:
        found += block_links(kept, own[0], num, den)
    yield out(found)
    del kept, found
    trim()


def further_links(members: DataFrame, links: DataFrame, labels: DataFrame, sets: DataFrame, num: int, den: int, bins: int, rows: int) -> DataFrame | None:
    """Links that connect all that is linked, after those that the stars have missed; None if they have missed none.

    In a bucket where not all are in the centre's component, each member outside
    it is a centre too, for the members of other components, on full sets. Buckets
    are split by blocks of centres and of members.
    """
    label = lambda m: m.join(labels.withColumnRenamed("component", "c"), F.col("rep") == F.col("node"), "left").withColumn("c", F.coalesce("c", "rep")).drop("node")
    at_centre = labels.select(F.col("node").alias("cn"), F.col("component").alias("cc"))
    now = label(members).join(at_centre, F.col("centre") == F.col("cn"), "left").withColumn("cc", F.coalesce("cc", "centre"))
    now = now.withColumn("centre", F.col("c") != F.col("cc")).select("key", "rep", "n", "c", "centre")
    blocks = lambda many, hashes, most: F.ceil(F.greatest(F.col(many) / most, F.col(hashes) / (most * BLOCK_SET))).cast("int")
    outer = F.col("centre").cast("int")
    size = now.groupBy("key").agg(F.count(F.lit(1)).alias("many"), F.sum("n").alias("hashes"), F.sum(outer).alias("outs"), F.sum(outer * F.col("n")).alias("out_hashes")).filter("outs > 0 AND many > 2")
    size = size.select(F.col("key").alias("k2"), blocks("outs", "out_hashes", BLOCK_CENTRES).alias("obs"), blocks("many", "hashes", BLOCK_MEMBERS).alias("mbs"))
    open_ = save(now.join(size, F.col("key") == F.col("k2")).drop("k2"))
    wanted = save(open_.select(F.col("rep").alias("r2")).distinct())
    fine = sets.join(small(wanted), F.col("doc_id") == F.col("r2"), "left_semi").mapInArrow(lambda it: with_bands(it, bins, rows), "of long, set binary, bands binary")
    block = lambda of, salt: F.pmod(F.xxhash64("rep", F.lit(salt)), F.col(of)).cast("int")
    # a centre stands in one block of centres, against every block of members; a member in one block of members, against every block of centres
    as_centre = open_.filter("centre").withColumn("ob", block("obs", 1)).withColumn("mb", F.explode(F.sequence(F.lit(0), F.col("mbs") - 1)))
    as_member = open_.withColumn("centre", F.lit(False)).withColumn("mb", block("mbs", 2)).withColumn("ob", F.explode(F.sequence(F.lit(0), F.col("obs") - 1)))
    dealt = as_centre.unionByName(as_member).join(fine, F.col("rep") == F.col("of")).select("key", "ob", "mb", "rep", "n", "c", "centre", "set", "bands")
    dealt = dealt.repartition("key", "ob", "mb").sortWithinPartitions("key", "ob", "mb")
    found = save(dealt.mapInArrow(lambda it: near_links(it, num, den), "a long, b long").distinct())
    return None if found.isEmpty() else save(links.union(found))


def compare(pairs: DataFrame, sets: DataFrame, num: int, den: int) -> DataFrame:
    """The linked ones of (a, b), on full sets. A hot centre is a skewed inner join, which AQE splits."""
    a = sets.select(F.col("doc_id").alias("ia"), F.col("set").alias("set_a"))
    b = sets.select(F.col("doc_id").alias("ib"), F.col("set").alias("set_b"))
    both = pairs.join(b, F.col("b") == F.col("ib")).join(a, F.col("a") == F.col("ia"))
    return both.select("a", "b", "set_a", "set_b").mapInArrow(lambda it: linked(it, num, den), "a long, b long").distinct()


def deduplicated(documents: DataFrame, k: int = 5, num: int = 80, den: int = 100, id: str = "doc_id", text: str = "text", bins: int = BINS, rows: int = ROWS) -> DataFrame:
    """The documents that stay, with their columns: of each component the row with the least id (null last), and the least hash of its text.

    A row goes for its own text: another text of the same id stays. Of rows that repeat both id and text, one stays, whatever
    their other columns. Rows without words are linked with nothing and stay.
    """
    own = documents.select(F.col(f"`{id}`").cast("long").alias("doc_id"), F.col(f"`{text}`").cast("string").alias("text"))
    signed, classes, labels = classes_of(own, k, num, den, bins, rows)
    of = classes.select("set_key", "rep", "least").join(labels, F.col("rep") == F.col("node"), "left").withColumn("c", F.coalesce("component", "rep"))
    linked_ = of.filter("component IS NOT NULL").groupBy("component").agg(F.min("least").alias("first")).withColumnRenamed("component", "c2")
    winner = of.join(linked_, F.col("c") == F.col("c2"), "left").select(F.col("set_key").alias("k2"), F.coalesce("first", "least")["row_key"].alias("winner"))
    seen = signed.filter("set_key IS NOT NULL").groupBy("set_key", "row_key").agg(F.count(F.lit(1)).alias("times"))
    seen = save(seen.join(winner, F.col("set_key") == F.col("k2")).select("row_key", (F.col("row_key") != F.col("winner")).alias("goes"), "times").filter("goes OR times > 1"))
    key, name = row_key(F.col(f"`{id}`").cast("long"), F.col(f"`{text}`").cast("string")), unused("gone", documents)
    named = lambda of: small(seen.filter(of).select(F.col("row_key").alias(name)))
    left = documents.join(named("goes"), key == F.col(name), "left_anti")
    if seen.filter("NOT goes").isEmpty():
        return left
    mark = unused("row_key", documents)
    again = left.join(named("NOT goes"), key == F.col(name), "left_semi").withColumn(mark, key).dropDuplicates([mark]).drop(mark)
    return left.join(named("NOT goes"), key == F.col(name), "left_anti").unionByName(again)


ORACLE_SQL = r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents),
s AS (SELECT doc_id, list_distinct(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 3 THEN [array_to_string(ws, ' ')] ELSE list_transform(range(1, len(ws) - 1), lambda i: ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2]) END) AS g FROM w),
u AS (SELECT doc_id, unnest(g) AS x FROM s),
n AS (SELECT doc_id, len(g) AS n FROM s),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS i FROM u a JOIN u b ON a.x = b.x AND a.doc_id < b.doc_id GROUP BY ALL),
e AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * i >= 85 * (x.n + y.n - i)),
l AS (SELECT a, b FROM e UNION ALL SELECT b, a FROM e),
r(node, c) AS (SELECT doc_id, doc_id FROM documents UNION SELECT l.b, r.c FROM r JOIN l ON r.node = l.a WHERE l.b > r.c)
SELECT n.doc_id, n.n::BIGINT AS n_shingles, min(r.c) AS component_id, min(r.c) = n.doc_id AS kept FROM n JOIN r ON r.node = n.doc_id GROUP BY n.doc_id, n.n
"""
