"""Code relations derived from the given tables. Each is one SQL text that Spark and DuckDB both run."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

# Types in the order of their digits.
TYPES = ("STANDARD", "ECONOMY", "MEDIUM", "PROMO", "SMALL", "LARGE")
_DIGIT = "CASE p_type " + " ".join(f"WHEN '{t}' THEN '{k}'" for k, t in enumerate(TYPES, 1)) + " END"
_NEXT = "CASE p_type " + " ".join(f"WHEN '{t}' THEN '{TYPES[(k + 1) % 6]}'" for k, t in enumerate(TYPES)) + " END"

RELATIONS = {
    "part_code": f"""
SELECT p_partkey, CASE p_partkey % 3
         WHEN 0 THEN concat('P', substr(p_brand, 7), '-', {_DIGIT}, upper(substr(p_name, 1, 1)))
         WHEN 1 THEN concat('KX/', {_DIGIT}, lpad(CAST(p_size AS varchar(9)), 2, '0'), CASE WHEN p_size > 25 THEN 'U' ELSE '' END)
         ELSE concat('V.', upper(substr(p_name, 1, 1)), '-', substr(split_part(p_name, ' ', 2), 1, 2), {_DIGIT}) END AS code,
       CAST(p_partkey % 3 AS int) AS law, p_type, p_brand, p_size, split_part(p_name, ' ', 1) AS colour, split_part(p_name, ' ', 2) AS shape
FROM part""",
    "part_dirty": f"""
SELECT c.p_partkey, c.code, c.law, CASE WHEN c.p_partkey % 17 = 0 THEN NULL WHEN c.p_partkey % 23 = 0 THEN {_NEXT} ELSE c.p_type END AS p_type, c.p_type AS truth,
       c.p_brand, c.p_size, c.colour, c.shape
FROM part_code c""",
    "order_code": """
SELECT o_orderkey, CASE o_orderkey % 2
         WHEN 0 THEN concat(o_orderstatus, substr(CAST(year(o_orderdate) AS varchar(9)), 3, 2), '-', substr(o_orderpriority, 1, 1), CAST(month(o_orderdate) AS varchar(9)))
         ELSE concat('ORD.', substr(o_orderpriority, 1, 1), '/', o_orderstatus, CAST(o_custkey % 10 AS varchar(9)), CASE WHEN o_totalprice > 250000 THEN 'X' ELSE '' END) END AS code,
       CAST(o_orderkey % 2 AS int) AS law, o_orderstatus, o_orderpriority, CAST(year(o_orderdate) AS int) AS o_year, CAST(month(o_orderdate) AS int) AS o_month, o_totalprice > 250000 AS big
FROM orders""",
    "line_code": """
SELECT l_orderkey, l_linenumber, concat(l_returnflag, l_linestatus, '-', substr(CAST(year(l_shipdate) AS varchar(9)), 3, 2), '.', CAST(month(l_shipdate) AS varchar(9)), '/', CAST(l_linenumber AS varchar(9))) AS code,
       l_returnflag, l_linestatus, CAST(year(l_shipdate) AS int) AS ship_year, CAST(month(l_shipdate) AS int) AS ship_month
FROM lineitem""",
    "page_url": """
SELECT page_id, url AS code, regexp_extract(html, 'lang="([a-z]+)"', 1) AS lang, split_part(url, ':', 1) AS scheme,
       regexp_extract(url, 'example[.]([a-z]+)', 1) AS tld, CASE WHEN url LIKE '%utm_source%' THEN 'yes' ELSE 'no' END AS tracked
FROM pages""",
    "nation_code": "SELECT n_name AS code, n_regionkey FROM nation",
    "customer_code": "SELECT c_name AS code, CAST(c_nationkey AS varchar(9)) AS nation, c_mktsegment FROM customer",
    "supplier_code": "SELECT s_name AS code, CAST(s_nationkey AS varchar(9)) AS nation FROM supplier",
    "source_code": "SELECT d.source AS code, CAST(l.quality AS varchar(9)) AS quality FROM documents d JOIN labels l ON d.doc_id = l.doc_id",
    "event_code": """
SELECT event_id, ts, user_id, concat(upper(substr(event_type, 1, 2)), regexp_extract(props, '"k": ([0-9]+)', 1), '-', CAST(user_id % 10 AS varchar(9))) AS code,
       CASE WHEN event_id % 29 = 0 THEN concat(event_type, '?') ELSE event_type END AS event_type
FROM events""",
}

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def needed(text: str) -> list[str]:
    """Relations that a text names, each after those it is made of."""
    out: list[str] = []
    for name in RELATIONS:
        if re.search(rf"\b{name}\b", text):
            for x in [*needed(RELATIONS[name]), name]:
                if x not in out:
                    out.append(x)
    return out


def with_relations(text: str) -> str:
    """The text with the relations it names as common table expressions, for DuckDB and for Spark."""
    names = needed(text)
    if not names:
        return text
    head = ",\n".join(f"{n} AS ({RELATIONS[n]})" for n in names)
    body = text.strip()
    if body.upper().startswith("WITH RECURSIVE"):
        return f"WITH RECURSIVE {head},\n{body[14:]}"
    if body.upper().startswith("WITH "):
        return f"WITH {head},\n{body[5:]}"
    return f"WITH {head}\n{body}"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def sql(spark: SparkSession, sf_dir: str, text: str, **frames: DataFrame) -> DataFrame:
    """Runs a text over the tables and relations it names; frames add further tables.

    Tables are passed as parameters, so nothing is registered in the session.
    """
    full = with_relations(text)
    args = dict(frames)
    for t in (*TABLES, *frames):
        if t in frames or re.search(rf"(?:FROM|JOIN)\s+{t}\b", full):
            full = re.sub(rf"((?:FROM|JOIN)\s+){t}\b(?!\s*(?:AS\s*)?\()", rf"\1{{{t}}}", full)
            if t not in args:
                args[t] = table(spark, sf_dir, t)
    return spark.sql(full, **{k: v for k, v in args.items() if f"{{{k}}}" in full})


def relation(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return sql(spark, sf_dir, f"SELECT * FROM {name}")
