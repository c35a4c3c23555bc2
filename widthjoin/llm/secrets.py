"""Secret scans in DataFrame functions alone: three patterns, and character Markov models.

Two first-order models of characters are trained from labelled strings, one of
random strings, one of ordinary identifiers. A long run of key characters is a
secret if the mean log-likelihood ratio of its character pairs is above a limit.

Null text: empty. A text without matches has counts 0 and empty span lists.
Overlapping spans of one kind do not occur (leftmost first); a model's span that
overlaps a pattern's span is dropped. Row by row, so ties, repeated rows and
clashing names do not matter; an empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .line_dedup import let

#: Fixed values of the base: patterns as Java regular expressions, in the order of kinds.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?)([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
#: Runs the models judge.
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=-"
MIN_LENGTH = 20
CANDIDATE = rf"[A-Za-z0-9+/_=-]{{{MIN_LENGTH},}}"
#: Mean log-likelihood ratio (nats a pair) above which a run is a secret.
MIN_RATIO = 0.6
#: Rows of the labelled samples: random strings, and documents whose words are the ordinary identifiers.
RANDOM_ROWS, SAMPLE_DOCS = 3000, 2000
SMOOTHING = 0.5
#: Matches are added up in blocks of this many, as an array that grows by one element is copied each time.
BLOCK = 256


def spans(text: str, pattern: str):
    """array<struct<s,e,v>> of the pattern's matches, leftmost first; code points, end exclusive.

    The gaps between matches and the matches alternate, so running sums of their lengths are positions.
    """
    t, p = F.col(f"`{text}`"), F.lit(pattern)
    none = F.array().cast("array<struct<s:int,e:int,v:string>>")
    found = F.regexp_extract_all(t, p, 0)
    # the last gap has no match behind it: filled up with null, then left out
    both = F.filter(F.zip_with(F.split(t, p, -1), found, lambda g, v: F.struct(F.length(g).alias("g"), v.alias("v"))), lambda x: x["v"].isNotNull())

    def step(a, x):
        start = a["at"] + x["g"]
        end = start + F.length(x["v"])
        return F.struct(end.alias("at"), F.concat(a["out"], F.array(F.struct(start.alias("s"), end.alias("e"), x["v"].alias("v")))).alias("out"))

    def block(a, x):  # where a block starts
        size = F.aggregate(x, F.lit(0), lambda n, y: n + y["g"] + F.length(y["v"]))
        return F.struct((a["at"] + size).alias("at"), F.concat(a["out"], F.array(F.struct(a["at"].alias("at"), x.alias("x")))).alias("out"))

    starts = F.array().cast("array<struct<at:int,x:array<struct<g:int,v:string>>>>")
    placed = F.aggregate(blocks(both), F.struct(F.lit(0).alias("at"), starts.alias("out")), block, lambda a: a["out"])
    own = F.transform(placed, lambda z: F.aggregate(z["x"], F.struct(z["at"].alias("at"), none.alias("out")), step, lambda a: a["out"]))
    return F.when(t.rlike(pattern), F.flatten(own)).otherwise(none)


def blocks(values):
    """An array's elements in arrays of at most BLOCK."""
    return let(values, lambda x: F.when(F.size(x) > 0, F.transform(F.sequence(F.lit(0), F.floor((F.size(x) - 1) / BLOCK).cast("int")), lambda k: F.slice(x, k * BLOCK + 1, F.lit(BLOCK)))).otherwise(F.filter(F.array(x), lambda y: F.size(y) > 0)))


def labelled_sample(documents: DataFrame, text: str = "text", id: str = "doc_id", n_random: int = RANDOM_ROWS, n_docs: int = SAMPLE_DOCS) -> DataFrame:
    """(value, is_random): digests written in several alphabets, and words, joined words and numbers. Bounded by its two parameters."""
    r = documents.sparkSession.range(n_random).select(F.sha2(F.concat(F.lit("random-"), F.col("id").cast("string")), 256).alias("h"))
    b64 = F.base64(F.unhex("h"))
    random = r.select(F.explode(F.array(b64, F.substring(F.translate(b64, "+/=", "xYz"), 1, 40), F.substring("h", 1, 40), F.substring(F.upper(F.translate(b64, "+/=", "Q7A")), 1, 24))).alias("value")).withColumn("is_random", F.lit(True))
    # ids alone are sorted; texts of the chosen ones follow, one an id
    ids = documents.select(F.col(f"`{id}`").alias("chosen")).dropna().distinct().orderBy(F.xxhash64("chosen"), "chosen").limit(n_docs)
    docs = documents.select(F.col(f"`{id}`").alias("i"), F.col(f"`{text}`").alias("t")).join(F.broadcast(ids), F.col("i") == F.col("chosen")).groupBy("i").agg(F.min("t").alias("t"))
    w = docs.select(F.explode(F.array_distinct(F.regexp_extract_all("t", F.lit("([A-Za-z]{4,})"), 1))).alias("w")).distinct()
    camel = F.concat("w", F.initcap(F.reverse("w")))
    ordinary = w.select(F.explode(F.array(F.col("w"), camel, F.concat_ws("_", "w", F.lower("w")), F.concat_ws("-", F.lower("w"), "w"))).alias("value"))
    numbers = documents.sparkSession.range(n_random).select(F.explode(F.array(F.lpad(F.pmod(F.xxhash64("id"), F.lit(10**16)).cast("string"), 16, "4"), F.date_add(F.lit("2000-01-01").cast("date"), F.col("id").cast("int")).cast("string"))).alias("value"))
    return random.unionByName(ordinary.unionByName(numbers).withColumn("is_random", F.lit(False)))


def train(sample: DataFrame) -> list[float]:
    """Log-likelihood ratios of character pairs, row by row over the alphabet. The driver gets at most 2 * 67^2 counts."""
    n = len(ALPHABET)
    at = lambda i: f"instr('{ALPHABET}', substr(value, {i}, 1))"
    pairs = sample.filter(F.length("value") >= 2).select(
        "is_random", F.explode(F.expr(f"transform(sequence(2, length(value)), i -> {at('i - 1')} * {n + 1} + {at('i')})")).alias("pair")
    )
    count: dict[bool, dict[int, int]] = {True: {}, False: {}}
    for r in pairs.groupBy("is_random", "pair").count().collect():
        count[r["is_random"]][r["pair"]] = r["count"]
    logs = {}
    for k, c in count.items():
        for a in range(n + 1):
            total = sum(c.get(a * (n + 1) + b, 0) for b in range(n + 1)) + SMOOTHING * (n + 1)
            for b in range(n + 1):
                logs[k, a, b] = math.log((c.get(a * (n + 1) + b, 0) + SMOOTHING) / total)
    return [round(logs[True, a, b] - logs[False, a, b], 6) for a in range(n + 1) for b in range(n + 1)]


def scan(documents: DataFrame, model: list[float], text: str = "text", id: str = "doc_id", min_ratio: float = MIN_RATIO) -> DataFrame:
    """doc_id, and the spans (start, end, value) of each kind: assign, access, hex, markov."""
    n = len(ALPHABET) + 1
    d = documents.select(F.col(f"`{id}`").alias("doc_id"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("t"))
    d = d.select("doc_id", spans("t", ASSIGN).alias("assign"), spans("t", ACCESS).alias("access"), spans("t", HEX).alias("hex"), spans("t", CANDIDATE).alias("runs"))
    value = F.filter("assign", lambda x: F.length(F.regexp_extract(x["v"], ASSIGN, 2)) >= 6)
    d = d.withColumn("assign", value).withColumn("base", F.concat("assign", "access", "hex"))
    table = F.split(F.lit(",".join(map(str, model))), ",").cast("array<double>")
    at = lambda v, i: F.instr(F.lit(ALPHABET), F.substring(v, i, F.lit(1)))

    def ratio(v):
        pair = lambda acc, i: acc + F.element_at(table, at(v, i - 1) * n + at(v, i) + 1)
        return F.aggregate(F.sequence(F.lit(2), F.length(v)), F.lit(0.0), pair) / (F.length(v) - 1)

    # spans of the base in order of their starts, in blocks with the range they cover
    def free(x, base):
        meets = lambda b: (b["s"] < x["e"]) & (x["s"] < b["e"])
        return ~F.exists(base, lambda k: meets(k) & F.exists(k["x"], meets))

    ranges = F.transform(blocks(F.array_sort(F.transform("base", lambda b: F.struct(b["s"].alias("s"), b["e"].alias("e"))))), lambda x: F.struct(x[0]["s"].alias("s"), F.array_max(F.transform(x, lambda b: b["e"])).alias("e"), x.alias("x")))
    markov = F.when(F.size("runs") == 0, F.col("runs")).otherwise(let(ranges, lambda base: F.filter("runs", lambda x: free(x, base) & (ratio(x["v"]) > min_ratio))))
    return d.select("doc_id", "assign", "access", "hex", markov.alias("markov"))


def digest(found: DataFrame) -> DataFrame:
    """The query's columns, from scan()'s spans."""
    kinds = ("assign", "access", "hex", "markov")

    def named(k):
        return F.transform(k, lambda x: F.struct(x["s"].alias("s"), F.lit(kinds.index(k)).alias("o"), F.concat_ws(":", F.lit(k), x["s"].cast("string"), x["e"].cast("string")).alias("n")))

    def listed(own):
        return F.array_join(F.transform(F.array_sort(F.concat(*map(named, own))), lambda x: x["n"]), ",")

    return found.select(
        "doc_id", *[F.size(k).cast("long").alias(f"n_{k}") for k in kinds[:3]],
        F.sha2(listed(kinds[:3]), 256).alias("base_sha256"), listed(kinds).alias("spans"), F.size("markov").cast("long").alias("n_markov"),
    )


def secrets_of(documents: DataFrame, spark: SparkSession | None = None) -> DataFrame:
    return digest(scan(documents, train(labelled_sample(documents))))
