"""Queries of the operators around the methods: scans, joins, aggregates, windows, sets, functions, streams' batch twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.sql import AlignColumns, cost_udf, spread_agg
from ..operators.align import block_by, dedupe, learn_tree, signature
from ..operators.baselines import fd_measures
from ..operators.claims import unpivot_counts
from ..operators.clean import code_keys, predictions
from ..operators.metric import CharMetric
from ..operators.rules import Thresholds, discover, rule_map
from ..operators.pattern import matches
from ..sources.codes import relation, table
from ..streaming import stream
from .catalog import PART_ATTRS, law_keys, query, same_sql, tree_of

# ------------------------------------------------------------------ scans, projections, filters

same_sql("codes_part", "SELECT p_partkey, code, law FROM part_code")
same_sql("codes_orders", "SELECT o_orderkey, code, law, o_year, o_month, big FROM order_code")
same_sql("codes_lineitem", "SELECT code, count(*) AS n FROM line_code GROUP BY code")
same_sql("codes_pages", "SELECT page_id, code, lang, scheme, tld, tracked FROM page_url")


@query("scan_part_codes", "SELECT p_partkey, p_brand FROM part WHERE p_size BETWEEN 10 AND 20")
def scan_part_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two columns read, the range pushed to the Parquet reader."""
    return table(spark, sf_dir, "part").where(F.col("p_size").between(10, 20)).select("p_partkey", "p_brand")


_LAW2_RE = "^V[.][BCHLNORS]-[a-z][a-z][1-6]$"


@query("filter_match", f"SELECT p_partkey, code FROM part_code WHERE regexp_matches(code, '{_LAW2_RE}')")
def filter_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_code").select("p_partkey", "code")
    return df.where(matches(F.col("code"), _LAW2_RE))


@query("filter_nonnull", "SELECT p_partkey, code, p_type FROM part_dirty WHERE p_type IS NOT NULL AND length(code) BETWEEN 6 AND 7 AND p_brand IN ('Brand#1', 'Brand#12')")
def filter_nonnull(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_dirty")
    return df.where(F.col("p_type").isNotNull() & F.length("code").between(6, 7) & F.col("p_brand").isin("Brand#1", "Brand#12")).select("p_partkey", "code", "p_type")


# ------------------------------------------------------------------ joins


@query("join_codes_members", "SELECT c.p_partkey, c.code, m.law, m.n FROM part_code c JOIN (SELECT code, law, count(*) AS n FROM part_code GROUP BY code, law) m ON c.code = m.code")
def join_codes_members(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tuples with the law node that holds their code; a sort-merge join, as members may be large."""
    df = relation(spark, sf_dir, "part_code")
    tree = tree_of(df)
    keys = law_keys(df)
    members = tree.members(only=tree.all.join(keys, ["rep", "card"], "left_semi")).join(keys, ["rep", "card"]).select("code", "law")
    sized = members.join(dedupe(df).withColumnRenamed("weight", "n"), "code")
    return df.select("p_partkey", "code").join(sized.hint("merge"), "code").select("p_partkey", "code", "law", "n")


@query("join_shuffle_hash", "SELECT o.o_orderkey, c.c_mktsegment FROM orders o JOIN customer c ON o.o_custkey = c.c_custkey")
def join_shuffle_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    return o.join(c.hint("shuffle_hash"), o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "c_mktsegment")


same_sql("pairs_nation", "SELECT x.n_name AS a, y.n_name AS b FROM nation x JOIN nation y ON x.n_name < y.n_name")


@query("join_pattern", "SELECT c.code, p.law FROM (SELECT DISTINCT code FROM part_code) c JOIN (VALUES (0, '^P[0-9]{1,2}-[1-6][A-Z]$'), (1, '^KX/[1-6][0-9]{2}U?$'), (2, '^V[.][A-Z]-[a-z]{2}[1-6]$')) p(law, re) ON regexp_matches(c.code, p.re)")
def join_pattern(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Codes joined with the patterns of the learned law nodes that they match."""
    df = relation(spark, sf_dir, "part_code")
    laws = tree_of(df).nodes.join(law_keys(df), ["rep", "card"]).select("law", "regex")  # three rows
    return df.select("code").distinct().join(F.broadcast(laws), F.rlike("code", F.col("regex"))).select("code", "law")


@query("pairs_len_band", "WITH c AS (SELECT DISTINCT code, length(code) AS n FROM order_code) SELECT x.n AS a_len, y.n AS b_len, count(*) AS pairs FROM c x JOIN c y ON x.code < y.code AND abs(x.n - y.n) <= 1 GROUP BY 1, 2")
def pairs_len_band(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidate pairs whose length difference a cost limit allows: an equi join on length buckets, not a theta join."""
    c = relation(spark, sf_dir, "order_code").select("code").distinct().withColumn("n", F.length("code").cast("long"))
    a = c.select(F.col("code").alias("a"), F.col("n").alias("a_len"), F.floor(F.col("n") / 2).alias("slot"))
    b = c.select(F.col("code").alias("b"), F.col("n").alias("b_len"), F.explode(F.array(*[F.floor(F.col("n") / 2) + k for k in (-1, 0, 1)])).alias("slot"))
    return a.join(b, "slot").where((F.col("a") < F.col("b")) & (F.abs(F.col("a_len") - F.col("b_len")) <= 1)).groupBy("a_len", "b_len").agg(F.count("*").alias("pairs"))


same_sql("semi_codes", "SELECT DISTINCT c.code FROM part_code c WHERE EXISTS (SELECT 1 FROM part_dirty d WHERE d.code = c.code AND d.p_type IS NULL)")
same_sql("anti_codes", "SELECT DISTINCT c.code FROM part_code c WHERE NOT EXISTS (SELECT 1 FROM part_dirty d WHERE d.code = c.code AND d.p_type IS NULL)")

# versions of a rule: each event sees the latest one made before it
_VERSIONS = [(1, "2024-01-01 00:00:00"), (2, "2024-01-10 12:00:00"), (3, "2024-01-21 06:00:00")]
_VERSION_ROWS = ", ".join(f"({v}, TIMESTAMP '{t}')" for v, t in _VERSIONS)


@query("asof_rule_version", f"SELECT e.event_id, v.version FROM events e ASOF JOIN (SELECT * FROM (VALUES {_VERSION_ROWS}) t(version, since)) v ON e.ts >= v.since")
def asof_rule_version(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As-of join against a short version history: the ends of validity come from a window over the history."""
    v = spark.createDataFrame(_VERSIONS, "version int, since string").withColumn("since", F.to_timestamp("since"))
    v = v.withColumn("until", F.lead("since").over(W.orderBy("since")))  # as long as the history of one catalog
    e = table(spark, sf_dir, "events").select("event_id", "ts")
    return e.join(F.broadcast(v), (F.col("ts") >= F.col("since")) & (F.col("until").isNull() | (F.col("ts") < F.col("until")))).select("event_id", "version")


@query("asof_by_union", "SELECT e.event_id, (SELECT max(p.ts) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'error' AND p.ts < e.ts) AS last_error FROM events e WHERE e.event_type = 'click'")
def asof_by_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    """As-of join of two large sides: one sort by key and time, the last value carried forward."""
    e = table(spark, sf_dir, "events").where("event_type in ('click', 'error')")
    stamped = e.withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    order = W.partitionBy("user_id").orderBy("us").rangeBetween(W.unboundedPreceding, -1)
    seen = stamped.withColumn("last_error", F.max(F.when(F.col("event_type") == "error", F.col("ts"))).over(order))
    return seen.where("event_type = 'click'").select("event_id", "last_error")


@query("interval_events", f"WITH v AS (SELECT version, since, lead(since) OVER (ORDER BY since) AS until FROM (VALUES {_VERSION_ROWS}) t(version, since)) SELECT v.version, e.event_type, count(*) AS n FROM events e JOIN v ON e.ts >= v.since AND (v.until IS NULL OR e.ts < v.until) GROUP BY 1, 2")
def interval_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events inside each version's validity."""
    v = spark.createDataFrame(_VERSIONS, "version int, since string").withColumn("since", F.to_timestamp("since")).withColumn("until", F.lead("since").over(W.orderBy("since")))
    e = table(spark, sf_dir, "events")
    return e.join(F.broadcast(v), (F.col("ts") >= F.col("since")) & (F.col("until").isNull() | (F.col("ts") < F.col("until")))).groupBy("version", "event_type").agg(F.count("*").alias("n"))


@query("outer_rules_diff", "SELECT coalesce(a.code, b.code) AS code, a.n AS n_old, b.n AS n_new FROM (SELECT code, count(*) AS n FROM part_code WHERE p_size <= 30 GROUP BY code) a FULL JOIN (SELECT code, count(*) AS n FROM part_code WHERE p_size > 20 GROUP BY code) b ON a.code = b.code")
def outer_rules_diff(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_code")
    n = lambda cond, name: df.where(cond).groupBy("code").agg(F.count("*").alias(name))
    return n("p_size <= 30", "n_old").join(n("p_size > 20", "n_new"), "code", "full")


# ------------------------------------------------------------------ aggregates

same_sql("diversity_part", "SELECT law, count(DISTINCT p_type) AS types, count(DISTINCT p_brand) AS brands, count(DISTINCT code) AS codes FROM part_code GROUP BY law")
same_sql("rollup_rules", "SELECT law, p_type, count(*) AS n, count(DISTINCT code) AS codes FROM part_code GROUP BY ROLLUP (law, p_type)")
same_sql("cube_codes", "SELECT law, colour, count(*) AS n FROM part_code GROUP BY CUBE (law, colour)")
same_sql("gsets_codes", "SELECT law, p_type, colour, count(*) AS n FROM part_code GROUP BY GROUPING SETS ((law, p_type), (law, colour), ())")


@query("diversity_approx_part")
def diversity_approx_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cheap pre-filter of diversity."""
    return relation(spark, sf_dir, "part_code").groupBy("law").agg(*[F.approx_count_distinct(a, 0.02).alias(a) for a in PART_ATTRS])


@query("unpivot_part", " UNION ALL ".join(f"SELECT code, '{a}' AS attr, CAST({a} AS varchar(40)) AS value, count(*) AS n FROM part_dirty WHERE {a} IS NOT NULL GROUP BY 1, 3" for a in PART_ATTRS))
def unpivot_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return unpivot_counts(relation(spark, sf_dir, "part_dirty"), "code", PART_ATTRS)


_TYPES = ("STANDARD", "ECONOMY", "MEDIUM", "PROMO", "SMALL", "LARGE")


@query("pivot_claims", "SELECT substr(code, 7, 1) AS key, " + ", ".join(f"count(*) FILTER (WHERE p_type = '{t}') AS {t.lower()}" for t in _TYPES) + " FROM part_dirty WHERE law = 2 GROUP BY 1")
def pivot_claims(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_dirty").where("law = 2")
    wide = df.groupBy(F.substring("code", 7, 1).alias("key")).pivot("p_type", list(_TYPES)).count().na.fill(0)
    return wide.select("key", *[F.col(t).alias(t.lower()) for t in _TYPES])


@query("class_masks", "SELECT law, length(code) AS n, bit_or(CASE WHEN code LIKE '%U' THEN 1 ELSE 0 END) AS any_suffix, bool_or(contains(code, '/')) AS any_slash, min(code) AS first, max(code) AS last, arg_max(code, p_partkey) AS newest, arg_min(code, p_partkey) AS oldest FROM part_code GROUP BY 1, 2")
def class_masks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return relation(spark, sf_dir, "part_code").groupBy("law", F.length("code").cast("long").alias("n")).agg(
        F.bit_or(F.when(F.col("code").endswith("U"), 1).otherwise(0)).alias("any_suffix"), F.bool_or(F.contains("code", F.lit("/"))).alias("any_slash"), F.min("code").alias("first"), F.max("code").alias("last"),
        F.max_by("code", "p_partkey").alias("newest"), F.min_by("code", "p_partkey").alias("oldest"),
    )


@query("listed_codes", "SELECT law, colour, string_agg(DISTINCT code, ',' ORDER BY code) AS codes FROM part_code WHERE law = 2 GROUP BY 1, 2")
def listed_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct codes per group as one text."""
    df = relation(spark, sf_dir, "part_code").where("law = 2")
    return df.groupBy("law", "colour").agg(F.array_join(F.array_sort(F.collect_set("code")), ",").alias("codes"))


# ------------------------------------------------------------------ windows, sorting, sets, subqueries

same_sql(
    "rank_values",
    "SELECT key, value, n, CAST(row_number() OVER w AS bigint) AS rn, CAST(rank() OVER w2 AS bigint) AS rk, CAST(dense_rank() OVER w2 AS bigint) AS dr, CAST(ntile(3) OVER w AS bigint) AS nt, round(percent_rank() OVER w2, 6) AS pr "
    "FROM (SELECT substr(code, 1, 1) AS key, p_brand AS value, count(*) AS n FROM part_code GROUP BY 1, 2) c WINDOW w AS (PARTITION BY key ORDER BY n DESC, value), w2 AS (PARTITION BY key ORDER BY n DESC)",
)


@query("lag_costs")
def lag_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fuse costs in order with the step from the one before: large steps are where laws meet."""
    nodes = tree_of(relation(spark, sf_dir, "part_code")).nodes
    order = W.partitionBy("block").orderBy("cost_u", "rep", "card")
    whole = order.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    return nodes.select(
        "rep", "card", "cost_u", (F.col("cost_u") - F.lag("cost_u").over(order)).alias("step"), F.lead("cost_u").over(order).alias("next_cost"),
        F.first_value("cost_u").over(whole).alias("first_cost"), F.last_value("cost_u").over(whole).alias("last_cost"), F.nth_value("cost_u", 3).over(whole).alias("third_cost"),
    )


same_sql("analytic_values", "SELECT p_partkey, lag(p_size) OVER w AS prev_size, lead(p_size, 2) OVER w AS next2, first_value(p_size) OVER w AS first_size, nth_value(p_size, 2) OVER (PARTITION BY law ORDER BY p_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_size FROM part_code WINDOW w AS (PARTITION BY law ORDER BY p_partkey)")
same_sql("running_support", "SELECT p_partkey, law, count(*) OVER (PARTITION BY law, p_type ORDER BY p_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS running, CAST(sum(p_size) OVER (PARTITION BY law ORDER BY p_partkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS bigint) AS last3 FROM part_code")
same_sql("range_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL '1' DAY PRECEDING AND CURRENT ROW) AS in_day FROM events")
same_sql("topk_pairs", "SELECT x.n_name AS a, y.n_name AS b, CAST(levenshtein(x.n_name, y.n_name) AS bigint) AS d FROM nation x JOIN nation y ON x.n_name < y.n_name ORDER BY d, a, b LIMIT 10")


@query("topk_rules", "SELECT * FROM (SELECT law, colour, n, row_number() OVER (PARTITION BY law ORDER BY n DESC, colour) AS rn FROM (SELECT law, colour, count(*) AS n FROM part_code GROUP BY 1, 2) c) r WHERE rn <= 3")
def topk_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Top three per group; the row_number filter becomes a group limit below the shuffle."""
    c = relation(spark, sf_dir, "part_code").groupBy("law", "colour").agg(F.count("*").alias("n"))
    return c.withColumn("rn", F.row_number().over(W.partitionBy("law").orderBy(F.desc("n"), "colour"))).where("rn <= 3").withColumn("rn", F.col("rn").cast("long"))


_SETS = "SELECT code FROM part_code WHERE p_size <= 30 {op} SELECT code FROM part_code WHERE p_size > 20"
for _name, _op in (("setop_union", "UNION"), ("setop_union_all", "UNION ALL"), ("setop_intersect", "INTERSECT"), ("setop_intersect_all", "INTERSECT ALL"), ("setop_except", "EXCEPT"), ("setop_except_all", "EXCEPT ALL")):
    same_sql(_name, _SETS.format(op=_op))

same_sql("subquery_scalar", "SELECT p_partkey, p_size FROM part WHERE p_size > (SELECT avg(p_size) FROM part)")
same_sql("subquery_in", "SELECT p_partkey FROM part_code WHERE code IN (SELECT code FROM part_dirty WHERE p_type IS NULL)")


@query("subquery_nn", "SELECT x.n_name AS code, min(levenshtein(x.n_name, y.n_name)) AS nearest FROM nation x JOIN nation y ON y.n_regionkey = x.n_regionkey AND y.n_nationkey <> x.n_nationkey GROUP BY 1")
def subquery_nn(spark: SparkSession, sf_dir: str) -> DataFrame:
    x, y = table(spark, sf_dir, "nation").alias("x"), table(spark, sf_dir, "nation").alias("y")
    near = x.join(y, (F.col("x.n_regionkey") == F.col("y.n_regionkey")) & (F.col("x.n_nationkey") != F.col("y.n_nationkey")))
    return near.groupBy(F.col("x.n_name").alias("code")).agg(F.min(F.levenshtein("x.n_name", "y.n_name")).cast("long").alias("nearest"))


@query("tree_path", "SELECT count(*) AS members, count(DISTINCT code) AS codes FROM (SELECT DISTINCT code FROM part_code) c")
def tree_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From the root to the leaves by a recursive common table expression; every code is reached once."""
    tree = tree_of(relation(spark, sf_dir, "part_code"))
    text = (
        "WITH RECURSIVE down(rep, card) MAX RECURSION LEVEL 100000 AS (SELECT rep, card FROM {roots} UNION ALL SELECT p.rep, p.card FROM down d JOIN {path} p ON p.up_rep = d.rep AND p.up_card = d.card) "
        "SELECT count(*) AS members, count(DISTINCT rep) AS codes FROM down WHERE card = 1"
    )
    return spark.sql(text, roots=tree.roots().select("rep", "card"), path=tree.path())


# ------------------------------------------------------------------ functions

same_sql(
    "char_profile",
    "SELECT code, CAST(length(code) AS bigint) AS n, reverse(code) AS back, translate(code, '0123456789', '##########') AS masked, ascii(code) AS first_code, lpad(code, 10, '*') AS padded, CAST(instr(code, '-') AS bigint) AS dash, lower(code) AS low, substr(code, 2, 3) AS mid FROM part_code",
)


@query("signature_profile", "SELECT regexp_replace(regexp_replace(regexp_replace(code, '[A-Za-z]+', 'A', 'g'), '[0-9]+', '9', 'g'), '[^A9]+', '-', 'g') AS block, count(*) AS codes FROM (SELECT DISTINCT code FROM part_code) c GROUP BY 1")
def signature_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks by class signature."""
    return block_by(dedupe(relation(spark, sf_dir, "part_code")), "signature").groupBy("block").agg(F.count("*").alias("codes"))


@query("block_prefix_part", "SELECT substr(code, 1, 2) AS block, count(*) AS codes, CAST(sum(n) AS bigint) AS tuples FROM (SELECT code, count(*) AS n FROM part_code GROUP BY code) c GROUP BY 1")
def block_prefix_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return block_by(dedupe(relation(spark, sf_dir, "part_code")), "prefix").groupBy("block").agg(F.count("*").alias("codes"), F.sum("weight").alias("tuples"))


@query("block_minhash_part")
def block_minhash_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks by smallest bigram hash, a tree in each."""
    codes = block_by(dedupe(relation(spark, sf_dir, "part_code")), "minhash")
    from ..operators.align import learn_tree

    return learn_tree(codes).roots().select("block", "rep", "card", "weight", "pattern")


@query("positions_part", "SELECT pos, ch, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT {i} AS pos, substr(code, {i}, 1) AS ch FROM part_code WHERE length(code) >= {i}" for i in range(1, 8)) + ") x GROUP BY 1, 2")
def positions_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_code")
    return df.select(F.posexplode(F.split("code", "")).alias("p", "ch")).groupBy((F.col("p") + 1).alias("pos"), "ch").agg(F.count("*").alias("n"))


@query("array_functions_part", "SELECT p_partkey, len(list_filter(string_split(code, ''), lambda c: c BETWEEN '0' AND '9')) AS digits, array_to_string(list_sort(list_distinct(string_split(code, ''))), '') AS letters, list_contains(string_split(code, ''), 'K') AS has_k FROM part_code")
def array_functions_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    chars = F.split("code", "")
    return relation(spark, sf_dir, "part_code").select(
        "p_partkey", F.size(F.filter(chars, lambda c: c.between("0", "9"))).cast("long").alias("digits"), F.array_join(F.array_sort(F.array_distinct(chars)), "").alias("letters"), F.exists(chars, lambda c: c == "K").alias("has_k")
    )


@query("json_events", """SELECT event_id, CAST(json_extract_string(props, '$.k') AS int) AS k FROM events WHERE event_type = 'error'""")
def json_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").where("event_type = 'error'").select("event_id", F.from_json("props", "k int")["k"].alias("k"))


@query("map_functions_part", "SELECT law, string_agg(p_type || ':' || n, ',' ORDER BY p_type) AS counts FROM (SELECT law, p_type, count(*) AS n FROM part_code GROUP BY 1, 2) c GROUP BY law")
def map_functions_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts as a map per law, read back through its keys."""
    m = relation(spark, sf_dir, "part_code").groupBy("law", "p_type").agg(F.count("*").alias("n")).groupBy("law").agg(F.map_from_entries(F.collect_list(F.struct("p_type", "n"))).alias("m"))
    return m.select("law", F.array_join(F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat_ws(":", k, F.element_at("m", k))), ",").alias("counts"))


same_sql("math_functions", "SELECT p_partkey, greatest(p_size, 25) AS g, least(p_size, 25) AS l, abs(p_size - 25) AS d, round(log2(p_size), 6) AS lg, round(p_retailprice, 1) AS price FROM part")
same_sql("date_functions", "SELECT o_orderkey, CAST(year(o_orderdate) AS int) AS y, CAST(month(o_orderdate) AS int) AS m, CAST(date_trunc('month', o_orderdate) AS timestamp) AS first_day FROM orders")


@query(
    "doc_ids",
    "SELECT doc_id, len(regexp_extract_all(text, '[A-Za-z0-9._]+@[A-Za-z0-9]+[.][a-z]+')) AS mails, len(regexp_extract_all(text, '[0-9]{16}')) AS digit_runs, len(regexp_extract_all(text, '[0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}')) AS addresses FROM documents WHERE regexp_matches(text, '[0-9@]')",
)
def doc_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Identifiers inside prose."""
    d = table(spark, sf_dir, "documents").where(F.col("text").rlike("[0-9@]"))
    n = lambda r: F.size(F.regexp_extract_all("text", F.lit(r), F.lit(0))).cast("long")
    return d.select("doc_id", n("[A-Za-z0-9._]+@[A-Za-z0-9]+[.][a-z]+").alias("mails"), n("[0-9]{16}").alias("digit_runs"), n("[0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}").alias("addresses"))


same_sql("sample_mod", "SELECT law, count(*) AS n FROM part_code WHERE p_partkey % 10 = 3 GROUP BY law")


@query("udf_align", "SELECT a.n_name AS a, b.n_name AS b, CAST(levenshtein(a.n_name, b.n_name) AS double) AS cost FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_name < b.n_name")
def udf_align(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "nation")
    pairs = n.select(F.col("n_name").alias("a"), "n_regionkey").join(n.select(F.col("n_name").alias("b"), "n_regionkey"), "n_regionkey").where("a < b")
    return pairs.select("a", "b", cost_udf(CharMetric.unit())("a", "b").alias("cost"))


@query("udaf_spread", "SELECT length(n_name) AS n, CAST(CASE WHEN count(DISTINCT right(n_name, 1)) > 1 THEN 0.5 ELSE 0.0 END AS double) AS spread FROM nation GROUP BY 1")
def udaf_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = table(spark, sf_dir, "nation")
    return n.select(F.length("n_name").cast("long").alias("n"), F.right("n_name", F.lit(1)).alias("ch")).groupBy("n").agg(spread_agg(CharMetric.classes())("ch").alias("spread"))


@query("udtf_align", "SELECT n_name AS code, CAST(p AS int) AS pos, CASE WHEN p < 8 THEN substr(n_name, p, 1) WHEN p = 8 THEN CASE WHEN length(n_name) = 9 THEN substr(n_name, 8, 1) END ELSE right(n_name, 1) END AS ch FROM nation, (SELECT unnest(range(1, 10)) AS p) q")
def udtf_align(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row per column of every name in the pattern of all names."""
    f = F.udtf(AlignColumns, returnType="pos int, ch string")
    spark.udtf.register("align_columns_q", f)
    names = table(spark, sf_dir, "nation").select(F.col("n_name").alias("code"))
    return spark.sql("SELECT t.code, a.pos, a.ch FROM {names} t, LATERAL align_columns_q(t.code, 'NATION_[12]{{0-9}}') a", names=names)


# ------------------------------------------------------------------ streams' batch twins

_EXPECTED = "SELECT e.*, m.value AS expected, coalesce(m.value <> e.event_type, FALSE) AS violates FROM event_code e LEFT JOIN (SELECT key, value FROM (SELECT key, value, row_number() OVER (PARTITION BY key ORDER BY n DESC, value) AS rn FROM (SELECT substr(code, 1, 2) AS key, event_type AS value, count(*) AS n FROM event_code GROUP BY 1, 2) c) r WHERE rn = 1) m ON substr(e.code, 1, 2) = m.key"


def event_rules(events: DataFrame) -> DataFrame:
    """(key, value): the event type that the rules foresee for each distinct code.

    A tree per first letter, the rules at its root, and a vote of them; noise of a few percent stays below their confidence.
    """
    tree = learn_tree(block_by(dedupe(events), "prefix", length=1))
    own = discover(events, "code", ["event_type"], tree, Thresholds(10, 0.9, 1, 5)).join(tree.roots().select("block", "rep", "card"), ["block", "rep", "card"], "left_semi")
    keys = code_keys(events.select("code"), own, tree)
    return predictions(keys, own, rule_map(events, "code", own, tree, ["event_type"])).select(F.col("code").alias("key"), F.col("predicted").alias("value"))


def flagged_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = relation(spark, sf_dir, "event_code")
    return stream.flagged(e, event_rules(e), F.col("code"), "event_type")


@query("stream_violations", f"SELECT time_bucket(INTERVAL '1 hour', ts) AS w_start, count(*) AS events, count(*) FILTER (WHERE violates) AS violations FROM ({_EXPECTED}) x GROUP BY 1")
def stream_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Batch twin of the streaming count of rule violations per hour."""
    return stream.violation_counts(flagged_events(spark, sf_dir))


@query("sliding_violations", f"SELECT w_start, count(*) AS events, count(*) FILTER (WHERE violates) AS violations FROM (SELECT x.*, time_bucket(INTERVAL '6 hours', ts) - k * INTERVAL '6 hours' AS w_start FROM ({_EXPECTED}) x, (VALUES (0), (1)) s(k)) y GROUP BY 1")
def sliding_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stream.violation_counts(flagged_events(spark, sf_dir), "12 hours", "6 hours")


@query(
    "session_events",
    f"WITH v AS (SELECT user_id, ts FROM ({_EXPECTED}) x WHERE violates), g AS (SELECT *, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL '2 hours' THEN 0 ELSE 1 END AS brk FROM v), s AS (SELECT *, sum(brk) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT user_id, min(ts) AS w_start, max(ts) + INTERVAL '2 hours' AS w_end, count(*) AS violations FROM s GROUP BY user_id, sid",
)
def session_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return stream.violation_sessions(flagged_events(spark, sf_dir))


@query("fd_events", "SELECT CAST(sum(m) AS bigint) AS support, round(sum(m) / CAST(sum(t) AS double), 6) AS confidence, (SELECT count(DISTINCT event_type) FROM event_code) AS diversity, max(m) AS inner_support, CAST(sum(t) AS bigint) AS claims FROM (SELECT key, max(n) AS m, sum(n) AS t FROM (SELECT code AS key, event_type, count(*) AS n FROM event_code GROUP BY 1, 2) c GROUP BY key) k")
def fd_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole-code dependency on a dirty stream's table."""
    return fd_measures(relation(spark, sf_dir, "event_code"), "code", "event_type").withColumn("confidence", F.round("confidence", 6))


@query("top_rules_part")
def top_rules_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The ten best-supported rules of each attribute."""
    df = relation(spark, sf_dir, "part_code")
    found = discover(df, "code", PART_ATTRS, tree_of(df))
    order = W.partitionBy("attr").orderBy(F.desc("support"), "rep", "card", "col_ix")
    return found.withColumn("rn", F.row_number().over(order)).where("rn <= 10").select("attr", "rn", "pattern", "col_ix", "support", "confidence")


__all__ = ["signature"]
