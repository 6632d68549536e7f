"""Registered queries of the methods, and their DuckDB SQL. relational.py has those of the operators around."""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.sql import cost_udf, spread_native
from ..operators import align, baselines, clean, rules
from ..operators.align import Tree, block_by, compare_searches, dedupe, learn_tree
from ..operators.claims import largest_count, measures, node_claims, satisfies, unpivot_counts
from ..operators.metric import CharMetric
from ..operators.pattern import degap, render, to_regex
from ..operators.rules import Thresholds, discover
from ..operators.tree import pair_fuse
from ..sources.codes import relation, sql, with_relations
from ..sources.synth import DEFAULTS, coded_strings
from .experiments import CLUSTERS, LENGTHS, NUMBERS, VARIATIONS
from .scratch import Scratch

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}

PART_ATTRS = ["p_type", "p_brand", "p_size", "colour", "shape"]
ORDER_ATTRS = ["o_orderstatus", "o_orderpriority", "o_year"]
PAGE_ATTRS = ["lang", "scheme", "tld", "tracked"]
#: What a node-level query tells of a rule.
FIGURES = ["col_ix", "attr", "support", "confidence", "diversity", "inner_support"]


def query(name: str, oracle: str | None = None):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = with_relations(oracle)
        return f

    return put


def same_sql(name: str, text: str) -> None:
    """One text for both engines."""
    QUERIES[name] = lambda spark, sf_dir: sql(spark, sf_dir, text)
    ORACLES[name] = with_relations(text)


# ------------------------------------------------------------------ shared pieces


def tree_of(df: DataFrame, **options) -> Tree:
    return learn_tree(dedupe(df), **options)


def law_keys(df: DataFrame) -> DataFrame:
    """Key (rep, card) that the node of exactly one law's codes has."""
    return df.groupBy("law").agg(F.min("code").alias("rep"), F.count_distinct("code").alias("card"))


def law_rules(df: DataFrame, attrs: list[str], laws: tuple[int, ...], t: Thresholds = Thresholds(), positions: int = 1, **options) -> DataFrame:
    found = discover(df, "code", attrs, tree_of(df, **options), t, positions=positions)
    return found.join(law_keys(df).where(F.col("law").isin(*laws)), ["rep", "card"]).select("law", *FIGURES).withColumn("confidence", F.round("confidence", 6))


def root_rules(df: DataFrame, attrs: list[str], t: Thresholds, **options) -> DataFrame:
    tree = tree_of(df, **options)
    return discover(df, "code", attrs, tree, t).join(tree.roots().select("rep", "card"), ["rep", "card"]).select(*FIGURES).withColumn("confidence", F.round("confidence", 6))


def measured(claims: str, by: str) -> str:
    """SQL of the four measures over claims (by..., key, value, n)."""
    eq = " AND ".join(f"a.{c.strip()} = b.{c.strip()}" for c in by.split(","))
    cols = ", ".join(f"a.{c.strip()}" for c in by.split(","))
    return f"""
kv AS (SELECT {by}, key, value, CAST(sum(n) AS bigint) AS n FROM ({claims}) c WHERE key IS NOT NULL AND key <> '' AND value IS NOT NULL GROUP BY {by}, key, value),
tops AS (SELECT {by}, key, max(n) AS most, sum(n) AS total FROM kv GROUP BY {by}, key),
sums AS (SELECT {by}, CAST(sum(most) AS bigint) AS support, CAST(sum(total) AS bigint) AS claims, max(most) AS inner_support FROM tops GROUP BY {by}),
kinds AS (SELECT {by}, count(DISTINCT value) AS diversity FROM kv GROUP BY {by}),
found AS (SELECT {cols}, a.support, round(a.support / CAST(a.claims AS double), 6) AS confidence, b.diversity, a.inner_support, a.claims FROM sums a JOIN kinds b ON {eq})"""


def law_claims(rel: str, attrs: list[str], places: int, where: str = "TRUE") -> str:
    """SQL of (law, col_ix, attr, key, value, n) by fixed positions from the left."""
    return " UNION ALL ".join(
        f"SELECT law, {i} AS col_ix, '{a}' AS attr, substr(code, {i}, 1) AS key, CAST({a} AS varchar(40)) AS value, count(*) AS n FROM {rel} WHERE {where} GROUP BY 1, 2, 3, 4, 5" for a in attrs for i in range(1, places + 1)
    )


def passing(t: Thresholds) -> str:
    return f"support >= {t.support} AND confidence >= {t.confidence} AND diversity >= {t.diversity} AND inner_support >= {t.inner_support}"


PAPER = Thresholds()
LOOSE = Thresholds(10, 0.9, 2, 5)

# ------------------------------------------------------------------ rules on planted laws


@query("rules_part", "WITH " + measured(law_claims("part_code", ["p_type", "colour"], 7, "law > 0"), "law, col_ix, attr") + f" SELECT law, {', '.join(FIGURES)} FROM found WHERE {passing(PAPER)}")
def rules_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Type and colour rules at the nodes of laws 1 and 2."""
    return law_rules(relation(spark, sf_dir, "part_code"), PART_ATTRS, (1, 2)).where("attr in ('p_type', 'colour')")


_LAW0 = " UNION ALL ".join(f"SELECT {7 - k} AS col_ix, '{a}' AS attr, substr(code, length(code) - {k - 1}, 1) AS key, {a} AS value, count(*) AS n FROM part_code WHERE law = 0 GROUP BY 1, 2, 3, 4" for a in ("p_type", "colour") for k in (1, 2))


@query("rules_part_law0", "WITH " + measured(_LAW0, "col_ix, attr") + f" SELECT 0 AS law, {', '.join(FIGURES)} FROM found WHERE {passing(PAPER)}")
def rules_part_law0(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The law with a column that may be a gap."""
    return law_rules(relation(spark, sf_dir, "part_code"), PART_ATTRS, (0,)).where("attr in ('p_type', 'colour') and col_ix > 4")


@query(
    "rules_pages",
    """SELECT attr, support, CAST(1 AS double) AS confidence, diversity, inner_support FROM (
  SELECT 'tld' AS attr, CAST(count(*) AS bigint) AS support, count(DISTINCT tld) AS diversity, (SELECT max(n) FROM (SELECT count(*) AS n FROM page_url GROUP BY tld) x) AS inner_support FROM page_url
  UNION ALL
  SELECT 'lang', CAST(count(*) AS bigint), count(DISTINCT lang), (SELECT max(n) FROM (SELECT count(*) AS n FROM page_url GROUP BY lang) x) FROM page_url) y""",
)
def rules_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Best root column for the language and for the domain ending, at looser diversity."""
    found = root_rules(relation(spark, sf_dir, "page_url"), PAGE_ATTRS, LOOSE).where("attr in ('tld', 'lang') and confidence = 1.0")
    best = found.groupBy("attr").agg(F.max_by(F.struct("support", "confidence", "diversity", "inner_support"), F.struct("support", "inner_support")).alias("b"))
    return best.select("attr", "b.support", "b.confidence", "b.diversity", "b.inner_support")


# every column of the three laws' templates; a brand of one digit leaves column 3 of law 0 empty
_KEYS = {
    0: ("substr(code, 1, 1)", "substr(code, 2, 1)", "CASE WHEN length(code) = 6 THEN substr(code, 3, 1) END", "substr(code, length(code) - 2, 1)", "substr(code, length(code) - 1, 1)", "substr(code, length(code), 1)"),
    1: tuple(f"substr(code, {i}, 1)" for i in range(1, 8)),
    2: tuple(f"substr(code, {i}, 1)" for i in range(1, 8)),
}
_EVERY = " UNION ALL ".join(
    f"SELECT {law} AS law, {i} AS col_ix, '{a}' AS attr, {key} AS key, CAST({a} AS varchar(40)) AS value, count(*) AS n FROM part_code WHERE law = {law} GROUP BY 4, 5"
    for law, keys in _KEYS.items() for a in PART_ATTRS for i, key in enumerate(keys, 1)
)
# The columns that the laws write one attribute's value in.
PLANTED = ((0, 5, "p_type"), (0, 6, "colour"), (1, 4, "p_type"), (2, 3, "colour"), (2, 7, "p_type"))


@query("rules_laws_part", "WITH " + measured(_EVERY, "law, col_ix, attr") + f" SELECT law, {', '.join(FIGURES)} FROM found WHERE {passing(PAPER)}")
def rules_laws_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All rules at the nodes of all three laws: every column, every attribute."""
    return law_rules(relation(spark, sf_dir, "part_code"), PART_ATTRS, (0, 1, 2))


_DECLARED = ", ".join(f"({law}, {i}, '{a}')" for law, i, a in PLANTED)


@query(
    "rule_validity_part",
    "WITH " + measured(_EVERY, "law, col_ix, attr") + f""", good AS (SELECT law, col_ix, attr FROM found WHERE {passing(PAPER)}), planted AS (SELECT * FROM (VALUES {_DECLARED}) t(law, col_ix, attr)),
both_ AS (SELECT count(*) AS n FROM good g JOIN planted p ON g.law = p.law AND g.col_ix = p.col_ix AND g.attr = p.attr)
SELECT (SELECT count(*) FROM good) AS found, (SELECT count(*) FROM planted) AS declared, round(n / CAST((SELECT count(*) FROM good) AS double), 6) AS precision, round(n / CAST((SELECT count(*) FROM planted) AS double), 6) AS recall FROM both_""",
)
def rule_validity_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules found at the law nodes against those that the laws were written with."""
    truth = spark.createDataFrame(PLANTED, "law int, col_ix int, attr string")
    return clean.score_rules(rules_laws_part(spark, sf_dir), truth, ["law", "col_ix", "attr"])


_ORDER = (
    "SELECT 0 AS law, 5 AS col_ix, 'o_orderpriority' AS attr, substr(code, 5, 1) AS key, o_orderpriority AS value, count(*) AS n FROM order_code WHERE law = 0 GROUP BY 4, 5 UNION ALL "
    "SELECT 0, 3, 'o_year', substr(code, 3, 1), CAST(o_year AS varchar(9)), count(*) FROM order_code WHERE law = 0 GROUP BY 4, 5 UNION ALL "
    "SELECT 1, 5, 'o_orderpriority', substr(code, 5, 1), o_orderpriority, count(*) FROM order_code WHERE law = 1 GROUP BY 4, 5"
)


@query("rules_orders", "WITH " + measured(_ORDER, "law, col_ix, attr") + f" SELECT law, {', '.join(FIGURES)} FROM found WHERE {passing(PAPER)}")
def rules_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Priority and year at the law nodes of the orders."""
    return law_rules(relation(spark, sf_dir, "order_code"), ORDER_ATTRS, (0, 1))


@query(
    "rules_nation",
    "WITH " + measured("SELECT 9 AS col_ix, 'n_regionkey' AS attr, right(code, 1) AS key, CAST(n_regionkey AS varchar(9)) AS value, count(*) AS n FROM nation_code GROUP BY 3, 4", "col_ix, attr")
    + f" SELECT {', '.join(FIGURES)} FROM found",
)
def rules_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Root rule of nation names with ties resolved early."""
    return root_rules(relation(spark, sf_dir, "nation_code"), ["n_regionkey"], Thresholds(10, 0.9, 5, 2), tie="gap_early")


def _none(name: str, rel: str, attrs: list[str]) -> None:
    @query(name, "SELECT CAST(0 AS bigint) AS n_rules")
    def control(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = relation(spark, sf_dir, rel)
        return discover(df, "code", attrs, tree_of(df), PAPER).agg(F.count("*").alias("n_rules"))


# Without a planted law nothing may be found; names of customers are fixed-width numbers.
_none("rules_source_none", "source_code", ["quality"])
_none("rules_supplier_none", "supplier_code", ["nation"])


@query("rules_customer_none", "SELECT CAST(0 AS bigint) AS n_rules")
def rules_customer_none(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Blocks of a thousand neighbouring names, as one block would grow with the table."""
    df = relation(spark, sf_dir, "customer_code")
    tree = learn_tree(block_by(dedupe(df), "prefix", length=15))
    return discover(df, "code", ["nation", "c_mktsegment"], tree, PAPER).agg(F.count("*").alias("n_rules"))


_SWEEP = (Thresholds(10, 0.9, 5, 5), Thresholds(5, 0.7, 3, 3), Thresholds(3, 0.5, 2, 2), Thresholds(1, 0.2, 1, 1))


@query(
    "threshold_sweep_part",
    "WITH " + measured(law_claims("part_code", ["p_type", "colour", "shape"], 7, "law = 2"), "law, col_ix, attr")
    + " SELECT * FROM (" + " UNION ALL ".join(f"SELECT {k} AS step, count(*) AS n_rules FROM found WHERE {passing(t)}" for k, t in enumerate(_SWEEP)) + ") s",
)
def threshold_sweep_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules at the node of law 2 under ever lower thresholds."""
    df = relation(spark, sf_dir, "part_code")
    tree = tree_of(df)
    every = discover(df, "code", ["p_type", "colour", "shape"], tree, _SWEEP[-1], prune=()).join(law_keys(df).where("law = 2"), ["rep", "card"]).select(*FIGURES, "claims")
    marks = every.select(*[t.passed().alias(f"s{k}") for k, t in enumerate(_SWEEP)]).agg(*[F.count_if(f"s{k}").alias(f"s{k}") for k in range(len(_SWEEP))])
    return marks.select(F.explode(F.array(*[F.struct(F.lit(k).alias("step"), F.col(f"s{k}").alias("n_rules")) for k in range(len(_SWEEP))])).alias("x")).select("x.*")


def _law2_claims(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_code")
    tree = tree_of(df)
    node = law_keys(df).where("law = 2").select("rep", "card")
    return node_claims(aligned_rows(spark, tree, node), unpivot_counts(df, "code", ["p_type", "colour"]))


_LAW2 = "WITH " + measured(law_claims("part_code", ["p_type", "colour"], 7, "law = 2"), "law, col_ix, attr")
for _name, _col in (("support_part", "support"), ("confidence_part", "confidence"), ("diversity_part", "diversity"), ("inner_part", "inner_support")):

    @query(_name, f"{_LAW2} SELECT col_ix, attr, {_col} FROM found")
    def one_measure(spark: SparkSession, sf_dir: str, col: str = _col) -> DataFrame:
        found = measures(_law2_claims(spark, sf_dir), ["col_ix", "attr"])
        return found.select("col_ix", "attr", (F.round(col, 6) if col == "confidence" else F.col(col)).alias(col))


@query("satisfied_part", "WITH " + measured(law_claims("part_code", ["p_type", "colour"], 7, "law = 2"), "law, col_ix, attr") + " SELECT col_ix, attr, support = claims AS satisfied FROM found")
def satisfied_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which columns of law 2 satisfy the dependency without exception."""
    return satisfies(_law2_claims(spark, sf_dir), ["col_ix", "attr"])


@query("measures_part", f"{_LAW2} SELECT col_ix, attr, support, confidence, diversity, inner_support, claims FROM found")
def measures_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures(_law2_claims(spark, sf_dir), ["col_ix", "attr"]).withColumn("confidence", F.round("confidence", 6))


@query("eta_example", "SELECT CAST(max(n) AS bigint) AS eta FROM (SELECT count(*) AS n FROM order_code GROUP BY code) x")
def eta_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of the most frequent code."""
    return largest_count(relation(spark, sf_dir, "order_code").select(F.col("code").alias("key")))


# ------------------------------------------------------------------ alignment


def aligned_rows(spark: SparkSession, tree: Tree, key: DataFrame) -> DataFrame:
    return tree.members(only=tree.all.join(key, ["rep", "card"], "left_semi")).join(key, ["rep", "card"])


@query("align_nation", "SELECT n_name AS code, CASE WHEN length(n_name) = 8 THEN concat(substr(n_name, 1, 7), '_', substr(n_name, 8, 1)) ELSE n_name END AS aligned FROM nation")
def align_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    tree = tree_of(relation(spark, sf_dir, "nation_code"), tie="gap_early")
    # the names hold an underscore of their own, so the gap is shown by the same sign as in the expected text
    return aligned_rows(spark, tree, tree.roots().select("rep", "card")).select("code", render(F.col("aligned")).alias("aligned"))


@query("degap_part", "SELECT CAST(0 AS bigint) AS mismatches")
def degap_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Over all nodes, aligned codes without their gaps are the codes."""
    tree = tree_of(relation(spark, sf_dir, "part_code"))
    return tree.members(min_card=2).agg(F.count_if(degap(F.col("aligned")) != F.col("code")).alias("mismatches"))


# The worked example's codes and attribute values.
T1 = [("SL410", 2010, "14 inch"), ("T520i", 2012, "15 inch"), ("T560", 2016, "15 inch"), ("New S1 2016", 2016, "12 inch"), ("New S1 2017", 2017, "13 inch")]


@query("example_t1", "SELECT * FROM (VALUES ('SL410', 'SL410_', '{ST}[L]{45}{126}0[i]'), ('T520i', 'T_520i', '{ST}[L]{45}{126}0[i]'), ('T560', 'T_560_', '{ST}[L]{45}{126}0[i]')) t(code, aligned, pattern)")
def example_t1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The example's three codes of one law, found as a node among all five."""
    tree = tree_of(spark.createDataFrame(T1, "code string, year int, screen string"))
    rows = aligned_rows(spark, tree, tree.nodes.where("card = 3").select("rep", "card"))
    return rows.join(tree.nodes.select("rep", "card", "pattern"), ["rep", "card"]).select("code", render(F.col("aligned")).alias("aligned"), "pattern")


_STARS = """WITH c AS (SELECT DISTINCT law, code FROM part_code), p AS (SELECT law, min(code) AS pivot FROM c GROUP BY law),
s AS (SELECT c.law, c.code AS b, CAST(levenshtein(p.pivot, c.code) AS double) AS cost FROM c JOIN p ON c.law = p.law AND c.code > p.pivot)
SELECT x.b AS a, y.b AS b, abs(x.cost - y.cost) AS lb, x.cost + y.cost AS ub FROM s x JOIN s y ON x.law = y.law AND x.b < y.b"""


@query("star_example", _STARS)
def star_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bounds of all other pairs from the star of each law's smallest code, as a self-join of the star's edges."""
    codes = relation(spark, sf_dir, "part_code").select("law", "code").distinct()
    edges = codes.join(codes.groupBy("law").agg(F.min("code").alias("pivot")), "law").where("code > pivot")
    s = edges.select("pivot", F.col("code").alias("t"), cost_udf(CharMetric.unit())("pivot", "code").alias("cost"))
    x, y = s.select("pivot", F.col("t").alias("a"), F.col("cost").alias("ca")), s.select("pivot", F.col("t").alias("b"), F.col("cost").alias("cb"))
    return x.join(y, "pivot").where("a < b").select("a", "b", F.abs(F.col("ca") - F.col("cb")).alias("lb"), (F.col("ca") + F.col("cb")).alias("ub"))


def _t1_node():
    fused = pair_fuse([c for c, *_ in T1[:3]], CharMetric.classes())
    return fused.nodes[-1].template


# the law's codes have seven columns, each of single characters or of runs of letters and digits
_PATTERN = "WITH chars AS (" + " UNION ".join(f"SELECT {i} AS i, substr(code, {i}, 1) AS c FROM part_code WHERE law = 2" for i in range(1, 8)) + r"""),
runs AS (SELECT i, c, ascii(c) - row_number() OVER (PARTITION BY i ORDER BY c) AS run FROM chars),
spans AS (SELECT i, min(c) AS lo, CASE WHEN count(*) > 2 THEN concat(min(c), '-', max(c)) ELSE string_agg(c, '' ORDER BY c) END AS span FROM runs GROUP BY i, run),
shown AS (SELECT i, string_agg(span, '' ORDER BY lo) AS spans FROM spans GROUP BY i),
cols AS (SELECT i, count(*) AS n, string_agg(c, '' ORDER BY c) AS all_ FROM chars GROUP BY i)
SELECT string_agg(CASE WHEN n > 1 THEN concat('{', spans, '}') WHEN all_ = '-' THEN '\-' ELSE all_ END, '' ORDER BY cols.i) AS pattern,
concat('^', string_agg(CASE WHEN n > 1 THEN concat('([', all_, '])') WHEN all_ IN ('-', '.') THEN concat('(\', all_, ')') ELSE concat('(', all_, ')') END, '' ORDER BY cols.i), '$') AS regex
FROM cols JOIN shown ON cols.i = shown.i"""


@query("pattern_example", _PATTERN)
def pattern_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pattern and regex of the node of law 2."""
    df = relation(spark, sf_dir, "part_code")
    return tree_of(df).nodes.join(law_keys(df).where("law = 2"), ["rep", "card"]).select("pattern", "regex")


# Codes that the worked example's pattern is tried on.
_TRIED = ("TL510i", "SL410", "T560", "X520", "T5600", "S4", "TL520")


@query("unseen_match", "SELECT code, regexp_matches(code, '^[ST]L?[45][126]0i?$') AS matches FROM (VALUES " + ", ".join(f"('{c}')" for c in _TRIED) + ") t(code)")
def unseen_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A pattern also matches codes that it was not learned from."""
    from ..operators.pattern import matches

    return spark.createDataFrame([(c,) for c in _TRIED], "code string").select("code", matches(F.col("code"), to_regex(_t1_node().cols, capture=False)).alias("matches"))


def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = relation(spark, sf_dir, "nation_code")
    return n.select(F.col("code").alias("a")).join(n.select(F.col("code").alias("b")), F.col("a") < F.col("b"))


@query("lev_pairs", "SELECT x.n_name AS a, y.n_name AS b, CAST(levenshtein(x.n_name, y.n_name) AS double) AS cost FROM nation x JOIN nation y ON x.n_name < y.n_name")
def lev_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Under the unit metric the kernel's cost is edit distance."""
    return _pairs(spark, sf_dir).withColumn("cost", cost_udf(CharMetric.unit())("a", "b"))


_DIGITS = "CASE WHEN length(x.n_name) = length(y.n_name) THEN 0.5 * (" + " + ".join(f"CASE WHEN substr(x.n_name, {k}, 1) <> substr(y.n_name, {k}, 1) THEN 1 ELSE 0 END" for k in (8, 9)) + ") ELSE 1.0 + CASE WHEN (length(x.n_name) = 8 AND (substr(y.n_name, 8, 1) = right(x.n_name, 1) OR right(y.n_name, 1) = right(x.n_name, 1))) OR (length(y.n_name) = 8 AND (substr(x.n_name, 8, 1) = right(y.n_name, 1) OR right(x.n_name, 1) = right(y.n_name, 1))) THEN 0 ELSE 0.5 END END"


@query("cost_pairs_nation", f"SELECT x.n_name AS a, y.n_name AS b, CAST({_DIGITS} AS double) AS cost FROM nation x JOIN nation y ON x.n_name < y.n_name")
def cost_pairs_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Class metric on all pairs of names."""
    return _pairs(spark, sf_dir).withColumn("cost", cost_udf(CharMetric.classes())("a", "b"))


@query("align_hof_nation", f"SELECT x.n_name AS a, y.n_name AS b, CAST({_DIGITS} AS double) AS cost FROM nation x JOIN nation y ON x.n_name < y.n_name")
def align_hof_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same recurrence in built-in higher-order functions only; for small inputs and as a cross-check."""
    kind = lambda c: F.when(c.rlike("[0-9]"), 0).when(c.rlike(r"\p{L}"), 1).otherwise(2)
    a, b = F.split("a", ""), F.split("b", "")

    def next_row(row, x):
        walked = F.aggregate(
            F.sequence(F.lit(1), F.size(b)), F.array(F.element_at(row, 1) + 1.0),
            lambda new, j: F.concat(new, F.array(F.least(
                F.element_at(row, j + 1) + 1.0, F.element_at(new, -1) + 1.0,
                F.element_at(row, j) + F.when(x == F.element_at(b, j), 0.0).when(kind(x) == kind(F.element_at(b, j)), 0.5).otherwise(1.5),
            ))),
        )
        return walked

    start = F.transform(F.sequence(F.lit(0), F.size(b)), lambda k: k.cast("double"))
    return _pairs(spark, sf_dir).withColumn("cost", F.element_at(F.aggregate(a, start, next_row), -1))


@query("first_pair_nation", "SELECT x.n_name AS a, y.n_name AS b, CAST(levenshtein(x.n_name, y.n_name) AS double) AS cost FROM nation x JOIN nation y ON x.n_name < y.n_name ORDER BY cost, a, b LIMIT 1")
def first_pair_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The first fuse under the unit metric."""
    tree = tree_of(relation(spark, sf_dir, "nation_code"), metric=CharMetric.unit(), algorithm="pair")
    return tree.nodes.orderBy("round").limit(1).select(F.col("left_rep").alias("a"), F.col("right_rep").alias("b"), (F.col("cost_u") / 2).alias("cost"))


@query("length_bounds_part", "SELECT CAST(max(length(code)) AS bigint) AS lo, CAST(sum(length(code)) AS bigint) AS hi FROM (SELECT DISTINCT code FROM part_code) x")
def length_bounds_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return align.length_bounds(dedupe(relation(spark, sf_dir, "part_code")))


_COLS2 = "SELECT i AS col_ix, CASE WHEN count(DISTINCT CASE WHEN ch BETWEEN '0' AND '9' THEN 0 WHEN lower(ch) BETWEEN 'a' AND 'z' THEN 1 ELSE 2 END) > 1 THEN 1.5 WHEN count(DISTINCT ch) > 1 THEN 0.5 ELSE 0.0 END AS spread FROM (" + " UNION ALL ".join(f"SELECT {i} AS i, substr(code, {i}, 1) AS ch FROM part_code WHERE law = 2" for i in range(1, 8)) + ") x GROUP BY i"


@query("spread_columns_part", f"SELECT col_ix, CAST(spread AS double) AS spread FROM ({_COLS2}) y")
def spread_columns_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Column spreads of the node of law 2, by built-in aggregates."""
    df = relation(spark, sf_dir, "part_code")
    rows = aligned_rows(spark, tree_of(df), law_keys(df).where("law = 2").select("rep", "card"))
    return rows.select(F.posexplode("aligned").alias("pos", "ch")).groupBy((F.col("pos") + 1).alias("col_ix")).agg(spread_native(F.col("ch")).alias("spread"))


@query("metric_check", "SELECT count(DISTINCT ch) + 1 AS symbols, CAST(0 AS bigint) AS violations FROM (SELECT unnest(string_split(code, '')) AS ch FROM (SELECT code FROM part_code UNION SELECT code FROM order_code UNION SELECT code FROM page_url) c) x")
def metric_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triangle inequality over all characters of the codes and the gap, as a join of the distance table with itself."""
    m = CharMetric.classes()
    codes = [relation(spark, sf_dir, r).select("code").distinct() for r in ("part_code", "order_code", "page_url")]
    chars = reduce(DataFrame.unionByName, codes).select(F.explode(F.split("code", "")).alias("ch")).where("ch <> ''").distinct()
    symbols = Scratch(spark, "symbols").save(chars.unionByName(spark.createDataFrame([("",)], "ch string")), "all")  # the gap is the empty text
    distance = F.udf(lambda a, b: m.distance(a or None, b or None), "int")
    d = symbols.select(F.col("ch").alias("a")).crossJoin(symbols.select(F.col("ch").alias("b"))).withColumn("d", distance("a", "b"))  # as large as the alphabet, squared
    x, y = d.toDF("a", "c", "ac"), d.toDF("c", "b", "cb")
    return x.join(y, "c").join(d.toDF("a", "b", "ab"), ["a", "b"]).agg(F.count_distinct("a").alias("symbols"), F.count_if(F.col("ab") > F.col("ac") + F.col("cb")).alias("violations"))


# ------------------------------------------------------------------ trees and their cost


@query("tree_size_part", "SELECT count(DISTINCT code) - 1 AS nodes, count(DISTINCT code) AS root_card, count(*) AS root_weight FROM part_code")
def tree_size_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tree_of(relation(spark, sf_dir, "part_code")).nodes.agg(F.count("*").alias("nodes"), F.max("card").alias("root_card"), F.max("weight").alias("root_weight"))


def differing(a: Tree, b: Tree) -> DataFrame:
    """Nodes that only one of two trees has."""
    cols = ["block", "rep", "card", "cost_u", "pattern"]
    x, y = a.nodes.select(*cols), b.nodes.select(*cols)
    return x.exceptAll(y).unionByName(y.exceptAll(x))


@query("same_tree_bounded", "SELECT CAST(0 AS bigint) AS differing")
def same_tree_bounded(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pruned searches build the baseline's tree."""
    df = relation(spark, sf_dir, "part_code")
    base = tree_of(df, algorithm="pair")
    star, inherit, profile = (differing(base, tree_of(df, **o)) for o in ({"profile": "star", "lower": "zero"}, {"lower": "zero"}, {}))
    return star.unionByName(inherit).unionByName(profile).agg(F.count("*").alias("differing"))


@query("same_tree_rounds", "SELECT CAST(0 AS bigint) AS differing")
def same_tree_rounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """So does round-parallel fusing with intervals, here until 256 templates are left for one worker."""
    df = relation(spark, sf_dir, "part_code")
    return differing(tree_of(df, algorithm="pair"), tree_of(df, algorithm="rounds", finish=256)).agg(F.count("*").alias("differing"))


@query("bounded_not_more", "SELECT TRUE AS star_not_more, TRUE AS inherit_not_more, TRUE AS profile_not_more")
def bounded_not_more(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_code")
    n = lambda name, **o: tree_of(df, **o).counters.select(F.col("fuse_evals").alias(name))
    one = n("pair", algorithm="pair").crossJoin(n("star", profile="star", lower="zero")).crossJoin(n("inherit", lower="zero")).crossJoin(n("profile"))  # one row each
    return one.select((F.col("star") <= F.col("pair")).alias("star_not_more"), (F.col("inherit") <= F.col("star")).alias("inherit_not_more"), (F.col("profile") <= F.col("inherit")).alias("profile_not_more"))


def _counts(name: str, rel: str) -> None:
    @query(name)
    def counts(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Evaluations and refines of the baseline and both pruned searches on one relation, side by side."""
        return compare_searches(dedupe(relation(spark, sf_dir, rel))).drop("wall_ms", "refine_hist", "block")


def _shares(name: str, rel: str) -> None:
    @query(name)
    def shares(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Share of the baseline's evaluations that each search makes, and its time in milliseconds, the median of three runs."""
        found = compare_searches(dedupe(relation(spark, sf_dir, rel)), repeats=3)
        base = found.where("method = 'pair'").select(F.col("fuse_evals").alias("base"))
        return found.crossJoin(F.broadcast(base)).select("method", "n", F.round(F.col("fuse_evals") / F.col("base"), 6).alias("evals_share"), "wall_ms")  # base is one row


def _evals_pair(name: str, rel: str) -> None:
    @query(name, f"SELECT (count(DISTINCT code) - 1) * (count(DISTINCT code) - 1) AS fuse_evals FROM {rel}")
    def evals_pair(spark: SparkSession, sf_dir: str) -> DataFrame:
        """The baseline's evaluations follow from the number of distinct codes."""
        return tree_of(relation(spark, sf_dir, rel), algorithm="pair").counters.select("fuse_evals")


for _name, _rel in (("part", "part_code"), ("pages", "page_url"), ("orders", "order_code")):
    _counts(f"counts_{_name}", _rel)
    _shares(f"shares_{_name}", _rel)
    _evals_pair(f"evals_pair_{_name}", _rel)


@query("refine_hist_part")
def refine_hist_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How often a selection took so many refines, with inherited bounds."""
    return tree_of(relation(spark, sf_dir, "part_code"), lower="zero").counters.select(F.explode("refine_hist").alias("refines", "selections"))


@query("independence_pages", "SELECT TRUE AS same_tree, TRUE AS not_more_refines_in_worst")
def independence_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Looking only at dependent pairs changes no node and shortens the worst selection."""
    df = relation(spark, sf_dir, "page_url")
    with ThreadPoolExecutor(2) as both:  # each search is one task, so they run side by side
        on, off = both.map(lambda independence: tree_of(df, lower="zero", independence=independence), (True, False))
    worst = lambda t, name: t.counters.select(F.array_max(F.map_keys("refine_hist")).alias(name))
    return differing(on, off).agg((F.count("*") == 0).alias("same_tree")).crossJoin(worst(on, "x")).crossJoin(worst(off, "y")).select("same_tree", (F.col("x") <= F.col("y")).alias("not_more_refines_in_worst"))


def law_chains(df: DataFrame) -> Tree:
    """One growing template for the codes of each law: the laws' first characters differ."""
    return learn_tree(block_by(dedupe(df), "prefix", length=1), algorithm="chain")


def chain_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_code")
    tree = law_chains(df)
    rows = aligned_rows(spark, tree, tree.roots().select("rep", "card").join(law_keys(df), ["rep", "card"]).select("rep", "card"))
    own = rows.join(law_keys(df), ["rep", "card"]).groupBy("law")
    return own.agg(F.max("card").alias("root_card"), F.count_if(degap(F.col("aligned")) != F.col("code")).alias("mismatches"))


def chain_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_code")
    tree = law_chains(df)
    roots = tree.roots().select("rep", "card").join(law_keys(df), ["rep", "card"])
    return discover(df, "code", ["p_type", "colour"], tree, PAPER).join(roots, ["rep", "card"]).select("law", *FIGURES).withColumn("confidence", F.round("confidence", 6))


@query("chain_part", "SELECT count(DISTINCT code) AS root_card, CAST(0 AS bigint) AS mismatches FROM part_code WHERE law = 2")
def chain_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One growing template over the codes of one law."""
    return chain_sizes(spark, sf_dir).where("law = 2").drop("law")


@query("chain_laws_part", "SELECT law, count(DISTINCT code) AS root_card, CAST(0 AS bigint) AS mismatches FROM part_code GROUP BY law")
def chain_laws_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The growing templates of all laws."""
    return chain_sizes(spark, sf_dir)


@query("chain_rules_part", "WITH " + measured(law_claims("part_code", ["p_type", "colour"], 7, "law = 2"), "law, col_ix, attr") + f" SELECT {', '.join(FIGURES)} FROM found WHERE {passing(PAPER)}")
def chain_rules_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Alignment without clustering: rules at the chain's root."""
    return chain_rules(spark, sf_dir).where("law = 2").drop("law")


@query("chain_rules_laws_part", "WITH " + measured(law_claims("part_code", ["p_type", "colour"], 7, "law > 0"), "law, col_ix, attr") + f" SELECT law, {', '.join(FIGURES)} FROM found WHERE {passing(PAPER)}")
def chain_rules_laws_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same at the chains of both laws whose columns count from the left."""
    return chain_rules(spark, sf_dir).where("law > 0")


@query("chain_rules_part_law0", "WITH " + measured(_LAW0, "col_ix, attr") + f" SELECT 0 AS law, {', '.join(FIGURES)} FROM found WHERE {passing(PAPER)}")
def chain_rules_part_law0(spark: SparkSession, sf_dir: str) -> DataFrame:
    """And of the law with a column that may be a gap."""
    return chain_rules(spark, sf_dir).where("law = 0 and col_ix > 4")


@query("prune_sound_part", "SELECT CAST(0 AS bigint) AS differing")
def prune_sound_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No prune loses or adds a rule."""
    df = relation(spark, sf_dir, "part_code")
    tree, key = tree_of(df), ["rep", "card", "col_ix", "attr", "support"]
    on, off = discover(df, "code", PART_ATTRS, tree).select(*key), discover(df, "code", PART_ATTRS, tree, prune=()).select(*key)
    return on.exceptAll(off).unionByName(off.exceptAll(on)).agg(F.count("*").alias("differing"))


@query("lift_vs_explode", "SELECT CAST(0 AS bigint) AS differing")
def lift_vs_explode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Claims merged up the tree and claims counted per node give the same rules."""
    df = relation(spark, sf_dir, "part_code")
    tree, key = tree_of(df), ["rep", "card", "col_ix", "attr", "support", "confidence", "diversity", "inner_support", "claims"]
    a, b = (discover(df, "code", PART_ATTRS, tree, strategy=s).select(*key) for s in ("lift", "explode"))
    return a.exceptAll(b).unionByName(b.exceptAll(a)).agg(F.count("*").alias("differing"))


@query("rule_counts_part")
def rule_counts_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rules over the whole tree by attribute, all and those not implied by the parent."""
    df = relation(spark, sf_dir, "part_code")
    tree = tree_of(df)
    found = discover(df, "code", PART_ATTRS, tree)
    few = rules.drop_implied(found, tree).groupBy("attr").agg(F.count("*").alias("not_implied"))
    return found.groupBy("attr").agg(F.count("*").alias("n_rules")).join(few, "attr", "left").na.fill(0)


# ------------------------------------------------------------------ maps, cleaning


_MAJORITY = """
WITH c AS (SELECT substr(code, 7, 1) AS key, p_type AS value, count(*) AS n FROM part_code WHERE law = 2 GROUP BY 1, 2),
r AS (SELECT *, row_number() OVER (PARTITION BY key ORDER BY n DESC, value) AS rn, coalesce(lead(n) OVER (PARTITION BY key ORDER BY n DESC, value), 0) AS runner_up FROM c)
SELECT key, value, n, runner_up FROM r WHERE rn = 1"""


@query("majority_part", _MAJORITY)
def majority_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_code")
    tree = tree_of(df)
    own = discover(df, "code", ["p_type"], tree).join(law_keys(df).where("law = 2").select("rep", "card"), ["rep", "card"], "left_semi")
    return rules.rule_map(df, "code", own, tree, ["p_type"]).select("key", "value", "n", "runner_up")


@query("rule_map_nation", "SELECT right(n_name, 1) AS key, CAST(n_regionkey AS varchar(9)) AS value, count(*) AS n, CAST(0 AS bigint) AS runner_up FROM nation GROUP BY 1, 2")
def rule_map_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "nation_code")
    tree = tree_of(df, tie="gap_early")
    own = discover(df, "code", ["n_regionkey"], tree, Thresholds(10, 0.9, 5, 2)).join(tree.roots().select("rep", "card"), ["rep", "card"], "left_semi")
    return rules.rule_map(df, "code", own, tree, ["n_regionkey"]).select("key", "value", "n", "runner_up")


@query("two_positions_part", "WITH " + measured("SELECT '5,6' AS col_ix, 'shape' AS attr, substr(code, 5, 2) AS key, shape AS value, count(*) AS n FROM part_code WHERE law = 2 GROUP BY 3, 4", "col_ix, attr") + f" SELECT {', '.join(FIGURES)} FROM found")
def two_positions_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two columns together decide the shape at the node of law 2."""
    return pair_rules(spark, sf_dir).where("law = 2 and attr = 'shape' and col_ix = '5,6'").drop("law")


def pair_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two-column rules of the law nodes, learned on all part codes."""
    return law_rules(relation(spark, sf_dir, "part_code"), ["p_brand", "p_size", "shape"], (0, 1, 2), positions=2)


# brand digits, size digits and shape letters; a brand of one digit has a gap at column 3, which is no claim
_PLANTED = (
    "SELECT 0 AS law, '2,3' AS col_ix, 'p_brand' AS attr, substr(code, 2, 2) AS key, p_brand AS value, count(*) AS n FROM part_code WHERE law = 0 AND substr(code, 3, 1) <> '-' GROUP BY 4, 5 UNION ALL "
    "SELECT 1, '5,6', 'p_size', substr(code, 5, 2), CAST(p_size AS varchar(9)), count(*) FROM part_code WHERE law = 1 GROUP BY 4, 5 UNION ALL "
    "SELECT 2, '5,6', 'shape', substr(code, 5, 2), shape, count(*) FROM part_code WHERE law = 2 GROUP BY 4, 5"
)


@query("two_positions_laws_part", "WITH " + measured(_PLANTED, "law, col_ix, attr") + f" SELECT law, {', '.join(FIGURES)} FROM found WHERE {passing(PAPER)}")
def two_positions_laws_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The planted two-column rules of all three laws."""
    planted = "law = 0 and attr = 'p_brand' and col_ix = '2,3' or law = 1 and attr = 'p_size' and col_ix = '5,6' or law = 2 and attr = 'shape' and col_ix = '5,6'"
    return pair_rules(spark, sf_dir).where(planted)


def cleaned(df: DataFrame, attr: str = "p_type", laws: bool = True) -> tuple[Tree, DataFrame, DataFrame]:
    """Tree, rules at the law nodes and predictions learned from a dirty relation."""
    tree = tree_of(df)
    own = discover(df, "code", [attr], tree)
    if laws:
        own = own.join(law_keys(df).select("rep", "card"), ["rep", "card"], "left_semi")
    maps = rules.rule_map(df, "code", own, tree, [attr])
    return tree, own, clean.predictions(clean.code_keys(df.select("code"), own, tree), own, maps)


@query("impute_part", "SELECT p_partkey, truth AS p_type_filled FROM part_dirty WHERE p_type IS NULL")
def impute_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hidden types come back from the code."""
    df = relation(spark, sf_dir, "part_dirty")
    return clean.impute(df, "code", "p_type", cleaned(df)[2]).where("p_type is null").select("p_partkey", "p_type_filled")


@query("repair_part", "SELECT p_partkey, p_type, truth AS p_type_expected FROM part_dirty WHERE p_type IS NOT NULL AND p_type <> truth")
def repair_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Wrong types contradict the code."""
    df = relation(spark, sf_dir, "part_dirty")
    return clean.violations(df, "code", "p_type", cleaned(df)[2]).select("p_partkey", "p_type", "p_type_expected")


@query(
    "clean_score_part",
    "SELECT count(*) FILTER (WHERE p_type IS NULL) AS filled, count(*) FILTER (WHERE p_type IS NULL) AS filled_right, CAST(1 AS double) AS missing_recall, count(*) FILTER (WHERE p_type <> truth) AS changed, count(*) FILTER (WHERE p_type <> truth) AS changed_right, CAST(1 AS double) AS wrong_recall FROM part_dirty",
)
def clean_score_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = relation(spark, sf_dir, "part_dirty")
    return clean.score_cleaning(clean.repair(df, "code", "p_type", cleaned(df)[2]), "p_type", "p_type_repaired", "truth")


@query("example_impute", "SELECT 'T560' AS code, '15 inch' AS screen_filled")
def example_impute(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The motivating example: the screen of one code follows from another's by the first digit."""
    rows = [(c, None if c == "T560" else s) for c, _, s in T1[:3]]
    df = spark.createDataFrame(rows, "code string, screen string")
    tree = tree_of(df)
    own = discover(df, "code", ["screen"], tree, Thresholds(2, 0.9, 2, 1)).where("card = 3 and col_ix = 3")
    predicted = clean.predictions(clean.code_keys(df, own, tree), own, rules.rule_map(df, "code", own, tree, ["screen"]))
    return clean.impute(df, "code", "screen", predicted).where("screen is null").select("code", "screen_filled")


@query("feedback_nation", "SELECT 0 AS setting, 'n_regionkey' AS attr, CAST(15 AS bigint) AS explained, FALSE AS chosen UNION ALL SELECT 1, 'n_regionkey', CAST(count(*) AS bigint), TRUE FROM nation")
def feedback_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which tie rule aligns nation names better, judged by the region it lets one column decide."""
    settings = [{"tie": "gap_late"}, {"tie": "gap_early"}]
    best, _, scores = rules.choose_alignment(relation(spark, sf_dir, "nation_code"), "code", ["n_regionkey"], settings, Thresholds(10, 0.9, 5, 2))
    return scores.withColumn("chosen", F.col("setting") == settings.index(best))


# ------------------------------------------------------------------ comparators


def _whole(rel: str, lhs: str, rhs: str, cond: str | None = None) -> str:
    by = "condition" if cond else "grp"
    head = f"CAST({cond} AS varchar(9)) AS condition" if cond else "1 AS grp"
    return "WITH " + measured(f"SELECT {head}, CAST({lhs} AS varchar(40)) AS key, CAST({rhs} AS varchar(40)) AS value, count(*) AS n FROM {rel} GROUP BY 1, 2, 3", by) + f" SELECT {'condition, ' if cond else ''}support, confidence, diversity, inner_support, claims FROM found"


@query("fd_part", _whole("part_code", "code", "p_type"))
def fd_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.fd_measures(relation(spark, sf_dir, "part_code"), "code", "p_type").withColumn("confidence", F.round("confidence", 6))


@query("cfd_part", _whole("part_code", "p_brand", "p_type", "law"))
def cfd_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.cfd_measures(relation(spark, sf_dir, "part_code"), "law", "p_brand", "p_type").withColumn("confidence", F.round("confidence", 6))


@query("lookup_part", "WITH u AS (SELECT code AS k, min(p_type) AS v FROM part_dirty WHERE p_type IS NOT NULL GROUP BY code HAVING min(p_type) = max(p_type)) SELECT p_partkey, coalesce(p_type, v) AS p_type_filled FROM part_dirty d LEFT JOIN u ON d.code = u.k")
def lookup_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Editing by reference: the code's own other tuples as reference data."""
    df = relation(spark, sf_dir, "part_dirty")
    return baselines.lookup_fill(df, df.where("p_type is not null").select("code", "p_type"), "code", "p_type").select("p_partkey", "p_type_filled")


def _raw(places: int, end: bool) -> str:
    at = (lambda i: f"substr(code, length(code) - {i - 1}, 1)") if end else (lambda i: f"substr(code, {i}, 1)")
    text = " UNION ALL ".join(f"SELECT {i} AS pos, '{a}' AS attr, {at(i)} AS key, {a} AS value, count(*) AS n FROM part_code WHERE length(code) >= {i} GROUP BY 1, 2, 3, 4" for a in ("p_type", "colour") for i in range(1, places + 1))
    return "WITH " + measured(text, "pos, attr") + " SELECT pos, attr, support, confidence, diversity, inner_support, claims FROM found"


for _name, _end in (("raw_pos_part", False), ("raw_pos_end_part", True)):

    @query(_name, _raw(7, _end))
    def raw(spark: SparkSession, sf_dir: str, end: bool = _end) -> DataFrame:
        return baselines.raw_position_measures(relation(spark, sf_dir, "part_code"), "code", ["p_type", "colour"], from_end=end).withColumn("confidence", F.round("confidence", 6))


# ------------------------------------------------------------------ statistics and cluster measures


def _stats(name: str, rel: str, brand: str, attributes: int) -> None:
    text = f"SELECT count(DISTINCT {brand}) AS brands, count(*) AS records, {attributes} AS attributes, count(DISTINCT code) AS codes, round(avg(length(code)), 6) AS mean_length, CAST(max(length(code)) AS bigint) AS max_length FROM {rel}"

    @query(name, text)
    def stats(spark: SparkSession, sf_dir: str) -> DataFrame:
        return relation(spark, sf_dir, rel).agg(
            F.count_distinct(brand).alias("brands"), F.count("*").alias("records"), F.lit(attributes).alias("attributes"), F.count_distinct("code").alias("codes"),
            F.round(F.avg(F.length("code")), 6).alias("mean_length"), F.max(F.length("code")).cast("long").alias("max_length"),
        )


_stats("stats_part", "part_code", "p_brand", 5)
_stats("stats_pages", "page_url", "tld", 4)
_stats("stats_orders", "order_code", "o_orderstatus", 5)


@query("purity_part", "SELECT CAST(1 AS double) AS purity, CAST(1 AS double) AS pair_precision, CAST(1 AS double) AS pair_recall")
def purity_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters at the law nodes against the laws."""
    df = relation(spark, sf_dir, "part_code")
    tree, keys = tree_of(df), law_keys(df).select("rep", "card")
    clusters = aligned_rows(spark, tree, keys).select("code", F.concat_ws("#", "rep", "card").alias("cluster"))
    return clean.score_clusters(clusters, df.select("code", F.col("law").alias("truth")).distinct())


@query("purity_blind_part", "SELECT CAST(1 AS double) AS purity")
def purity_blind_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters at a cut that only the tree's own costs choose, against the laws."""
    df = relation(spark, sf_dir, "part_code")
    tree = tree_of(df)
    flat = tree.cut(max_cost=tree.largest_step())
    clusters = tree.members(only=flat).select("code", F.concat_ws("#", "rep", "card").alias("cluster"))
    return clean.score_clusters(clusters, df.select("code", F.col("law").alias("truth")).distinct()).select("purity")


@query("cut_part", "SELECT law, count(DISTINCT code) AS card FROM part_code GROUP BY law")
def cut_part(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A cut by cost gives the three laws as flat clusters."""
    df = relation(spark, sf_dir, "part_code")
    cut = tree_of(df).cut(max_cost=2.5)
    return cut.join(df.groupBy("law").agg(F.min("code").alias("rep")), "rep").select("law", "card")


# ------------------------------------------------------------------ generated codes

# numbers below 1000 are for unit tests; clusters and variation are reported for the baseline and inherited bounds only
ALL_SEARCHES = tuple(align.SEARCHES)
SIZES = {
    "synth_len": ("l", LENGTHS, ALL_SEARCHES), "synth_n": ("N", (50, 100, 200, *NUMBERS), ALL_SEARCHES),
    "synth_cn": ("CN", CLUSTERS, ("pair", "bounded_inherit", "bounded_profile")), "synth_var": ("sigma", VARIATIONS, ("pair", "bounded_inherit", "bounded_profile")),
}


def synthetic(spark: SparkSession, searches: tuple[str, ...] = ALL_SEARCHES, **options) -> DataFrame:
    """Counters of the searches on generated codes."""
    return compare_searches(dedupe(coded_strings(spark, **(DEFAULTS | options))), searches=searches).select("method", "n", "fuse_evals", "refines")


for _group, (_option, _values, _searches) in SIZES.items():
    for _v in _values:

        @query(f"{_group}_{str(_v).replace('.', '')}")
        def generated(spark: SparkSession, sf_dir: str, option: str = _option, v=_v, searches: tuple[str, ...] = _searches) -> DataFrame:
            keyed = {"sf_dir": sf_dir} if option == "CN" else {}  # clusters: of the orders' records
            return synthetic(spark, searches, **{option: v}, **keyed)


# ------------------------------------------------------------------ application at volume


@query("apply_lineitem", "SELECT substr(code, 1, 1) AS key, l_returnflag AS predicted, count(*) AS tuples, count(*) AS agreeing FROM line_code GROUP BY 1, 2")
def apply_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A rule learned on the distinct codes, applied to all lines: keys and predictions per code, then one join of the lines."""
    df = relation(spark, sf_dir, "line_code")
    tree = tree_of(df)
    own = discover(df, "code", ["l_returnflag"], tree, Thresholds(10, 0.9, 2, 5)).where("col_ix = 1").join(tree.roots().select("rep", "card"), ["rep", "card"], "left_semi")
    keys = clean.code_keys(df.select("code"), own, tree)
    predicted = clean.predictions(keys, own, rules.rule_map(df, "code", own, tree, ["l_returnflag"]))
    per_code = keys.select("code", "key").join(predicted.select("code", "predicted"), "code")
    return df.select("code", "l_returnflag").join(per_code, "code").groupBy("key", "predicted").agg(F.count("*").alias("tuples"), F.count_if(F.col("predicted") == F.col("l_returnflag")).alias("agreeing"))


def entry(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All rules of the part codes with their patterns."""
    df = relation(spark, sf_dir, "part_code")
    return discover(df, "code", PART_ATTRS, tree_of(df)).select("pattern", "rep", "card", *FIGURES, "claims", "tuples")


__all__ = ["ORACLES", "QUERIES", "entry", "query", "same_sql", "tree_of"]
