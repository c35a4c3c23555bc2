"""Line dedup by site-relative frequency, in DataFrame functions alone.

Pages are grouped by host. For each line of a host, the pages that contain it
are divided by the host's pages; lines above the ratio are boilerplate and are
dropped from every page of that host.

Null text: null stays, it has no lines, but the page counts for its host.
Null host: a host of its own. Empty lines and lines of white space count for
nothing and are never dropped. Repeated rows are repeated pages. An empty table
gives an empty result. Other columns are passed through; helper columns have
names that are not in the table. A line at the ratio itself stays.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACES, ascii_lower, save, unused

#: Lines of more than this share of a host's pages are boilerplate, if they are repeated at all.
MAX_RATIO, MIN_PAGES = 0.05, 2
#: Boilerplate keys (8 bytes each) up to this number, of hosts up to that, are broadcast; beyond they are joined by salted hosts.
MAX_BROADCAST_KEYS, MAX_BROADCAST_HOSTS, SALTS = 2_000_000, 20_000, 32


def line_key(line):
    """Hash of a line, lower-cased in A-Z, with runs of white space as one space and none at the ends."""
    return F.xxhash64(F.trim(F.regexp_replace(ascii_lower(line), SPACES, " ")))


def has_word(line):
    return line.rlike(r"[^\x20\x09-\x0D]")


def boilerplate(pages: DataFrame, text: str = "text", host: str = "source", max_ratio: float = MAX_RATIO, min_pages: int = MIN_PAGES) -> DataFrame:
    """(host, line_key, n_pages, host_pages) of the lines to drop.

    A page's lines are made distinct in its own row, so that the only shuffles
    are two sums with map-side combine; a line shared by all pages is one row a task.
    """
    base = pages.select(F.col(f"`{host}`").alias("host"), F.col(f"`{text}`").alias("t"))
    totals = base.groupBy("host").agg(F.count(F.lit(1)).alias("host_pages"))
    keys = F.array_distinct(F.transform(F.filter(F.split("t", "\n"), has_word), line_key))
    lines = base.select("host", F.explode(keys).alias("line_key")).groupBy("host", "line_key").agg(F.count(F.lit(1)).alias("n_pages")).filter(F.col("n_pages") >= min_pages)
    return (
        lines.alias("l").join(totals.alias("h"), F.col("l.host").eqNullSafe(F.col("h.host")))
        .filter(F.col("n_pages") > max_ratio * F.col("host_pages"))
        .select("l.host", "line_key", "n_pages", "host_pages")
    )


def let(value, body):
    """body(value), the value worked out once."""
    return F.element_at(F.transform(F.array(value), body), 1)


def drop_boilerplate(pages: DataFrame, text: str = "text", host: str = "source", max_ratio: float = MAX_RATIO, min_pages: int = MIN_PAGES, counts: bool = True) -> DataFrame:
    """All pages with their columns, the text without boilerplate lines; with counts, n_lines and n_dropped (long) at the end, with "_" behind names that the table has.

    A host has fewer than (mean lines of its pages) / max_ratio boilerplate lines. Their keys are one array a host;
    hosts and keys are counted before a broadcast. A page first meets its host's keys as a set, and only pages with one are filtered line by line.
    """
    of, keys, salt, own = (unused(n, pages) for n in ("ld_host", "ld_keys", "ld_salt", "ld_text"))
    drops = save(boilerplate(pages, text, host, max_ratio, min_pages).groupBy("host").agg(F.array_sort(F.collect_list("line_key")).alias(keys)).withColumnRenamed("host", of))
    n = drops.agg(F.count(F.lit(1)).alias("hosts"), F.coalesce(F.sum(F.size(keys)), F.lit(0)).alias("keys")).first()
    same = F.col(f"`{host}`").eqNullSafe(F.col(of))
    if n["hosts"] <= MAX_BROADCAST_HOSTS and n["keys"] <= MAX_BROADCAST_KEYS:
        joined = pages.join(F.broadcast(drops), same, "left")
    else:
        mine = unused("ld_part", pages)
        salted = drops.withColumn(salt, F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        joined = pages.withColumn(mine, F.pmod(F.xxhash64(F.col(f"`{text}`")), F.lit(SALTS)).cast("int")).join(salted, same & (F.col(mine) == F.col(salt)), "left")
    lines = F.split(F.col(f"`{text}`"), "\n")
    found = F.array_intersect(F.transform(lines, line_key), F.col(keys))
    left = lambda hit: F.when(F.size(hit) > 0, F.filter(lines, lambda x: ~(has_word(x) & F.array_contains(hit, line_key(x))))).otherwise(lines)
    joined = joined.withColumn(own, F.when(F.col(keys).isNull(), F.when(F.col(f"`{text}`").isNotNull(), lines)).otherwise(let(found, left)))
    size = F.size(F.when(F.col(f"`{text}`").isNotNull(), lines))
    measures = {"n_lines": F.coalesce(size, F.lit(0)), "n_dropped": F.coalesce(size - F.size(own), F.lit(0))} if counts else {}
    return joined.select(
        *[(F.array_join(own, "\n") if c == text else F.col(f"`{c}`")).alias(c) for c in pages.columns],
        *[m.cast("long").alias(unused(c, pages)) for c, m in measures.items()],
    )


ORACLE_SQL = rf"""
WITH l AS (SELECT doc_id, source, text, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents),
k AS (SELECT doc_id, source, pos, line, trim(regexp_replace(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+', ' ', 'g')) AS key FROM l),
n AS (SELECT source, key, count(DISTINCT doc_id) AS n_pages FROM k WHERE key <> '' GROUP BY ALL),
h AS (SELECT source, count(*) AS host_pages FROM documents GROUP BY ALL),
d AS (SELECT n.source, key FROM n JOIN h ON n.source IS NOT DISTINCT FROM h.source WHERE n_pages >= {MIN_PAGES} AND n_pages > {MAX_RATIO} * host_pages),
r AS (SELECT k.doc_id, string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE d.key IS NULL) AS text, count(*) AS n_lines, count(d.key) AS n_dropped
      FROM k LEFT JOIN d ON k.source IS NOT DISTINCT FROM d.source AND k.key = d.key GROUP BY k.doc_id)
SELECT t.doc_id, CASE WHEN t.text IS NOT NULL THEN coalesce(r.text, '') END AS text, coalesce(n_lines, 0) AS n_lines, coalesce(n_dropped, 0) AS n_dropped FROM documents t LEFT JOIN r ON t.doc_id = r.doc_id
"""
