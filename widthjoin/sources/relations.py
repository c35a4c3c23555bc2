"""Relations of the given tables. Each has SQL text that Spark and DuckDB both read; where they differ, one text each."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: name -> SQL, with tables in braces; a pair is (Spark, DuckDB). Column order is variable order.
RELATIONS: dict[str, str | tuple[str, str]] = {
    "star_edges": "SELECT c_custkey AS a, CAST(0 AS BIGINT) AS b FROM {customer} UNION SELECT CAST(0 AS BIGINT) AS a, c_custkey AS b FROM {customer}",
    "cust_order": "SELECT DISTINCT o_custkey AS custkey, o_orderkey AS orderkey FROM {orders}",
    "order_supp": "SELECT DISTINCT l_orderkey AS orderkey, l_suppkey AS suppkey FROM {lineitem}",
    "supp_nation": "SELECT DISTINCT s_suppkey AS suppkey, CAST(s_nationkey AS BIGINT) AS nationkey FROM {supplier}",
    "nation_cust": "SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS nationkey, c_custkey AS custkey FROM {customer}",
    "order_part": "SELECT DISTINCT l_orderkey AS orderkey, l_partkey AS partkey FROM {lineitem}",
    "part_supp": "SELECT DISTINCT l_partkey AS partkey, l_suppkey AS suppkey FROM {lineitem}",
    "part_supp_r": "SELECT DISTINCT l_partkey AS partkey, l_suppkey AS suppkey FROM {lineitem} WHERE l_returnflag = 'R'",
    "part_supp_a": "SELECT DISTINCT l_partkey AS partkey, l_suppkey AS suppkey FROM {lineitem} WHERE l_returnflag = 'A'",
    "supp_order_a": "SELECT DISTINCT l_suppkey AS suppkey, l_orderkey AS orderkey FROM {lineitem} WHERE l_returnflag = 'A'",
    "order_part_n": "SELECT DISTINCT l_orderkey AS orderkey, l_partkey AS partkey FROM {lineitem} WHERE l_returnflag = 'N'",
    "user_key": ("SELECT DISTINCT user_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}", "SELECT DISTINCT user_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM {events}"),
    "user_key_buy": ("SELECT DISTINCT user_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events} WHERE event_type = 'purchase'", "SELECT DISTINCT user_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM {events} WHERE event_type = 'purchase'"),
    "doc_line": ("SELECT DISTINCT doc_id, line FROM (SELECT doc_id, explode(split(text, '\\n')) AS line FROM {documents}) WHERE trim(line) <> ''", "SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM {documents}) WHERE trim(line) <> ''"),
    "page_link": (
        "SELECT DISTINCT page_id, explode(regexp_extract_all(html, 'href=[\\\\x22\\\\x27]([^\\\\x22\\\\x27]*)[\\\\x22\\\\x27]', 1)) AS href FROM {pages}",
        "SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=[\\x22\\x27]([^\\x22\\x27]*)[\\x22\\x27]', 1)) AS href FROM {pages}",
    ),
    "conv_turn": "SELECT DISTINCT conv_id, turn FROM {conversations}",
    "turn_role": "SELECT DISTINCT turn, role FROM {conversations}",
    "role_conv": "SELECT DISTINCT role, conv_id FROM {conversations}",
    "line_ops": "SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s FROM {lineitem}",
    "line_psl": "SELECT DISTINCT l_partkey AS p, l_suppkey AS s, CAST(l_linenumber AS BIGINT) AS l FROM {lineitem}",
    "line_slo": "SELECT DISTINCT l_suppkey AS s, CAST(l_linenumber AS BIGINT) AS l, l_orderkey AS o FROM {lineitem}",
    "line_lop": "SELECT DISTINCT CAST(l_linenumber AS BIGINT) AS l, l_orderkey AS o, l_partkey AS p FROM {lineitem}",
    "nation_region": "SELECT DISTINCT CAST(n_nationkey AS BIGINT) AS nationkey, CAST(n_regionkey AS BIGINT) AS regionkey FROM {nation}",
    "region_key": "SELECT DISTINCT CAST(r_regionkey AS BIGINT) AS regionkey FROM {region}",
    "vec_bit": ("SELECT vec_id, CAST(2 * (i + 1) + CASE WHEN x > 0 THEN 1 ELSE 0 END AS BIGINT) AS bit FROM (SELECT vec_id, posexplode(slice(embedding, 1, 8)) AS (i, x) FROM {embeddings})", "SELECT vec_id, CAST(2 * i + CASE WHEN embedding[i] > 0 THEN 1 ELSE 0 END AS BIGINT) AS bit FROM {embeddings}, (SELECT unnest(range(1, 9)) AS i)"),
    "doc_lang": "SELECT DISTINCT d.doc_id, d.lang FROM {documents} d JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.quality = 1",
    "lang_source": "SELECT DISTINCT d.lang, d.source FROM {documents} d JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.quality = 1",
    "source_doc": "SELECT DISTINCT d.source, d.doc_id FROM {documents} d JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.quality = 1",
}
RELATIONS["part_supp_ra"] = f"{RELATIONS['part_supp_r']} INTERSECT {RELATIONS['part_supp_a']}"


def text_for(name: str, duckdb: bool = False) -> str:
    own = RELATIONS[name]
    own = own if isinstance(own, str) else own[duckdb]
    return re.sub(r"\{(\w+)\}", r"\1", own) if duckdb else own


def bind_atom(df: DataFrame, vars: dict[str, Column | str], where: Column | str | None = None) -> DataFrame:
    """A table as an atom's relation: {variable: column or SQL expression}, of the rows that meet the condition. Columns are in the order given."""
    own = df if where is None else df.filter(where)
    return own.select(*[(F.expr(c) if isinstance(c, str) else c).alias(v) for v, c in vars.items()])


def star(spark: SparkSession, n: int) -> DataFrame:
    """A hub 0 with n edges to it and n from it: the instance on which every single tree needs n^2 rows."""
    return star_of(spark.range(1, n + 1))


def star_of(keys: DataFrame) -> DataFrame:
    """The star whose leaves are the keys of a table's one column, none of them 0."""
    leaf = keys.select(F.col(keys.columns[0]).cast("bigint").alias("a"), F.lit(0).cast("bigint").alias("b"))
    return leaf.union(leaf.select("b", "a"))


def relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    own = text_for(name)
    tables = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in set(re.findall(r"\{(\w+)\}", own))}
    return spark.sql(own, **tables)
