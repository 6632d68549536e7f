"""Using rules: fill missing attribute values, flag and repair contradicting ones, score both."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .align import Tree
from .kernel import Template
from .metric import CharMetric
from .pattern import key_of


def code_keys(codes: DataFrame, rules: DataFrame, tree: Tree, members: DataFrame | None = None) -> DataFrame:
    """(code, block, rep, card, col_ix, attr, key) of every rule that applies to a code.

    Members of a rule's node bring their alignment with them. Other codes meet the templates of which they may have
    the length and the first character in an equi join, then those whose regex they match, and are laid out in the
    template's columns.
    """
    known = members if members is not None else tree.members(only=rules.select("block", "rep", "card"))
    own = known.join(rules.select("block", "rep", "card", "col_ix", "attr"), ["block", "rep", "card"]).withColumn("key", F.expr("aligned[col_ix - 1]")).where("key is not null")
    own = own.join(codes.select("code").distinct(), "code", "left_semi").select("code", "block", "rep", "card", "col_ix", "attr", "key")
    other = codes.select("code").distinct().join(tree.all.where("card = 1").select(F.col("rep").alias("code")), "code", "left_anti")
    nodes = tree.all.join(rules.select("block", "rep", "card").distinct(), ["block", "rep", "card"], "left_semi").select(
        "block", "rep", "card", "regex", "cols", "n_cols", F.size(F.filter("cols", lambda c: ~F.exists(c, lambda x: x.isNull()))).alias("least")
    )
    # a code's first character is of a column that only columns with gaps stand before
    lead = F.aggregate("cols", F.struct(F.array().cast("array<string>").alias("c"), F.lit(True).alias("on")), _lead, lambda s: F.array_distinct(s["c"]))
    spread = nodes.withColumn("size", F.explode(F.sequence(F.greatest(F.lit(1), F.col("least")), F.col("n_cols")))).withColumn("lead", F.explode(lead))
    hits = other.join(spread, (F.length("code") == F.col("size")) & (F.substring("code", 1, 1) == F.col("lead"))).where(F.rlike("code", F.col("regex")))
    wanted = hits.join(rules.select("block", "rep", "card", "col_ix", "attr"), ["block", "rep", "card"])
    metric, tie = tree.metric, tree.tie

    @F.pandas_udf("string")
    def laid(code: pd.Series, rep: pd.Series, card: pd.Series, cols: pd.Series, i: pd.Series) -> pd.Series:
        return pd.Series([key_of(c, _template(r, int(k), x, metric), int(at), metric, tie=tie) for c, r, k, x, at in zip(code, rep, card, cols, i)], dtype=object)

    new = wanted.withColumn("key", laid("code", "rep", "card", "cols", "col_ix")).where("key is not null").select("code", "block", "rep", "card", "col_ix", "attr", "key")
    return own.unionByName(new)


def _lead(state: Column, col: Column) -> Column:
    """Adds a column's characters as long as all columns before may be gaps."""
    real = F.filter(col, lambda x: x.isNotNull())
    return F.struct(F.when(state["on"], F.concat(state["c"], real)).otherwise(state["c"]).alias("c"), (state["on"] & F.exists(col, lambda x: x.isNull())).alias("on"))


def _template(rep: str, card: int, cols, metric: CharMetric) -> Template:
    sets = [frozenset(c) for c in cols]
    return Template(rep, card, sets, 0, np.array([metric.pack(c) for c in sets], np.int64) if metric.packed else None)


def predictions(keys: DataFrame, rules: DataFrame, rule_map: DataFrame, resolve: str = "vote") -> DataFrame:
    """(code, attr, predicted, rule): one value per code and attribute.

    'vote' sums confidence times support over the rules that agree; 'best' takes the rule with the highest
    confidence, then support. Ties go to the smaller value.
    """
    at = ["block", "rep", "card", "col_ix", "attr"]
    cast = keys.join(rules.select(*at, "pattern", "confidence", "support"), at).join(rule_map.select(*at, "key", "value"), [*at, "key"])
    cast = cast.withColumn("rule", F.concat_ws("@", "pattern", "col_ix"))
    if resolve == "best":
        order = W.partitionBy("code", "attr").orderBy(F.desc("confidence"), F.desc("support"), "value", "rule")
        return cast.withColumn("at", F.row_number().over(order)).where("at = 1").select("code", "attr", F.col("value").alias("predicted"), "rule")
    votes = cast.groupBy("code", "attr", "value").agg(F.sum(F.col("confidence") * F.col("support")).alias("vote"), F.min("rule").alias("rule"))
    order = W.partitionBy("code", "attr").orderBy(F.desc("vote"), "value")
    return votes.withColumn("at", F.row_number().over(order)).where("at = 1").select("code", "attr", F.col("value").alias("predicted"), "rule")


def _with(df: DataFrame, code: str, attr: str, predicted: DataFrame) -> DataFrame:
    own = predicted.where(F.col("attr") == attr).select(F.col("code").alias("__code"), F.col("predicted").alias("__predicted"), F.col("rule").alias("__rule"))
    return df.join(own, df[code] == F.col("__code"), "left").drop("__code")


def impute(df: DataFrame, code: str, attr: str, predicted: DataFrame) -> DataFrame:
    """Adds <attr>_filled and, where it was filled, <attr>_rule."""
    fill = F.coalesce(F.col(attr).cast("string"), F.col("__predicted"))
    rule = F.when(F.col(attr).isNull(), F.col("__rule"))
    return _with(df, code, attr, predicted).withColumn(f"{attr}_filled", fill).withColumn(f"{attr}_rule", rule).drop("__predicted", "__rule")


def violations(df: DataFrame, code: str, attr: str, predicted: DataFrame) -> DataFrame:
    """Rows whose value contradicts the rules, with the expected value."""
    rows = _with(df, code, attr, predicted).where(F.col("__predicted") != F.col(attr).cast("string"))
    return rows.withColumnRenamed("__predicted", f"{attr}_expected").withColumnRenamed("__rule", f"{attr}_rule")


def repair(df: DataFrame, code: str, attr: str, predicted: DataFrame) -> DataFrame:
    """Adds <attr>_repaired: the rules' value where there is one, the row's own elsewhere."""
    return _with(df, code, attr, predicted).withColumn(f"{attr}_repaired", F.coalesce("__predicted", F.col(attr).cast("string"))).drop("__predicted", "__rule")


def score_cleaning(rows: DataFrame, before: str, after: str, truth: str) -> DataFrame:
    """filled, filled_right, missing_recall, changed, changed_right, wrong_recall."""
    was, now, true = F.col(before), F.col(after), F.col(truth)
    hidden, wrong = was.isNull(), was.isNotNull() & (was != true)
    changed = was.isNotNull() & now.isNotNull() & (now != was)
    n = lambda c: F.count_if(F.coalesce(c, F.lit(False)))
    return rows.agg(
        n(hidden & now.isNotNull()).alias("filled"), n(hidden & (now == true)).alias("filled_right"), F.round(n(hidden & (now == true)) / n(hidden), 6).alias("missing_recall"),
        n(changed).alias("changed"), n(changed & (now == true)).alias("changed_right"), F.round(n(wrong & (now == true)) / n(wrong), 6).alias("wrong_recall"),
    )


def score_clusters(clusters: DataFrame, truth: DataFrame) -> DataFrame:
    """purity, pair_precision and pair_recall of (code, cluster) against (code, truth); from the contingency table only."""
    table = clusters.join(truth, "code").groupBy("cluster", "truth").agg(F.count("*").alias("n"))
    pairs = lambda c: F.sum(c * (c - 1) / 2)
    hit = table.agg(pairs(F.col("n")).alias("both"), F.sum("n").alias("all"))
    by = lambda c, name: table.groupBy(c).agg(F.sum("n").alias("s"), F.max("n").alias("m")).agg(pairs(F.col("s")).alias(name), F.sum("m").alias(f"{name}_top"))
    one = hit.crossJoin(by("cluster", "c")).crossJoin(by("truth", "t"))  # one row each
    ratio = lambda a, b: F.round(F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(F.lit(1.0)), 6)
    return one.select(ratio("c_top", "all").alias("purity"), ratio("both", "c").alias("pair_precision"), ratio("both", "t").alias("pair_recall"))


def score_rules(rules: DataFrame, truth: DataFrame, on: list[str]) -> DataFrame:
    """Precision and recall of found rules against declared ones."""
    a, b = rules.select(*on).distinct(), truth.select(*on).distinct()
    both = a.join(b, on, "left_semi").agg(F.count("*").alias("both"))
    one = both.crossJoin(a.agg(F.count("*").alias("found"))).crossJoin(b.agg(F.count("*").alias("declared")))  # one row each
    return one.select("found", "declared", F.round(F.col("both") / F.col("found"), 6).alias("precision"), F.round(F.col("both") / F.col("declared"), 6).alias("recall"))
