"""Position rules: which template column decides which attribute, on every node of a tree."""

from __future__ import annotations

from dataclasses import dataclass

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .align import Tree
from .claims import GAP_KEY, measures, node_claims, pair_claims, unpivot_counts

RULES = "block string, rep string, card long, pattern string, col_ix int, attr string, support long, confidence double, diversity long, inner_support long, claims long, tuples long"


@dataclass(frozen=True)
class Thresholds:
    # The four thresholds of the experiments.
    support: int = 10
    confidence: float = 0.9
    diversity: int = 5
    inner_support: int = 5

    def passed(self, denominator: str = "claims"):
        conf = F.col("support") / F.col("claims" if denominator == "claims" else "tuples")
        return (F.col("support") >= self.support) & (conf >= self.confidence) & (F.col("diversity") >= self.diversity) & (F.col("inner_support") >= self.inner_support)


def discover(
    df: DataFrame, code: str, attrs: list[str], tree: Tree, thresholds: Thresholds = Thresholds(), denominator: str = "claims",
    gap_as_key: bool = False, positions: int = 1, strategy: str = "lift", prune: tuple[str, ...] = ("weight", "confidence", "diversity"),
) -> DataFrame:
    """All (node, column, attribute) that pass the thresholds; columns of RULES.

    'lift' merges claims up each tree, smaller side into larger, one task per block; 'explode' joins every
    node's members with the counts and aggregates. positions=2 keys by column pairs (explode only).
    prune: 'weight' skips nodes of too few tuples, 'confidence' a column whose source columns all failed on
    confidence, 'diversity' attributes with too few values anywhere. None of them loses a rule.
    """
    counts = unpivot_counts(df, code, attrs)
    if "diversity" in prune:
        wide = counts.groupBy("attr").agg(F.count_distinct("value").alias("d")).where(F.col("d") >= thresholds.diversity)
        counts = counts.join(F.broadcast(wide.select("attr")), "attr")  # one row an attribute
    low = thresholds.support if "weight" in prune else 1
    if positions == 1 and strategy == "lift":
        return _lift(tree, counts, thresholds, denominator, gap_as_key, low, "confidence" in prune)
    members = tree.members(min_weight=low)
    claims = node_claims(members, counts, gap_as_key) if positions == 1 else pair_claims(members, counts)
    found = measures(claims, ["block", "rep", "card", "col_ix", "attr"])
    named = found.join(tree.all.select("block", "rep", "card", "pattern", F.col("weight").alias("tuples")), ["block", "rep", "card"])
    share = F.col("support") / F.col("claims" if denominator == "claims" else "tuples")
    return named.withColumn("confidence", share).where(thresholds.passed(denominator)).select(*[c.split(" ")[0] for c in RULES.split(", ")])


class _Column:
    """Claims of one (column, attribute): counts by key and value, with the figures kept up to date."""

    __slots__ = ("keys", "tops", "values", "support", "claims", "inner", "size")

    def __init__(self):
        self.keys: dict[str, dict[str, int]] = {}
        self.tops: dict[str, int] = {}
        self.values: set[str] = set()
        self.support = self.claims = self.inner = self.size = 0

    def add(self, key: str, value: str, n: int) -> None:
        own = self.keys.setdefault(key, {})
        had = own.get(value, 0)
        now = own[value] = had + n
        top = self.tops.get(key, 0)
        if now > top:
            self.support += now - top
            self.tops[key] = now
            self.inner = max(self.inner, now)
        self.size += not had
        self.values.add(value)
        self.claims += n

    def absorb(self, other: _Column) -> _Column:
        if other.size > self.size:
            return other.absorb(self)
        for key, own in other.keys.items():
            for value, n in own.items():
                self.add(key, value, n)
        return self


def _lift(tree: Tree, counts: DataFrame, t: Thresholds, denominator: str, gap_as_key: bool, low: int, skip: bool) -> DataFrame:
    nodes = tree.all.select("block", "rep", "card", "weight", "n_cols", "left_rep", "left_card", "right_rep", "right_card", "left_map", "right_map", "pattern", "round")
    leaves = nodes.where("card = 1").select(F.col("block").alias("of_block"), F.col("rep").alias("code"))
    per_code = counts.join(leaves, "code").select("of_block", "code", "attr", "value", "n")
    names = [c.split(" ")[0] for c in RULES.split(", ")]

    def climb(nodes: pd.DataFrame, claims: pd.DataFrame) -> pd.DataFrame:
        by_code: dict[str, list] = {}
        for c, a, v, n in claims[["code", "attr", "value", "n"]].itertuples(index=False):
            by_code.setdefault(c, []).append((a, v, n))
        live: dict[tuple, list[dict[str, _Column]]] = {}
        failed: dict[tuple, list[set[str]]] = {}
        out = []

        def judge(x, cols: list[dict[str, _Column]], sources: list[list[set[str]]]) -> list[set[str]]:
            """Adds the rules of a node; gives, for each column, the attributes that failed on confidence."""
            bads = []
            for k, of in enumerate(cols, 1):
                bad: set[str] = set()
                src = sources[k - 1]
                for a, c in of.items():
                    if skip and src and all(a in s for s in src):
                        bad.add(a)
                        continue
                    below = x.weight if denominator == "tuples" else c.claims
                    if c.support < t.confidence * below:
                        bad.add(a)
                    elif x.weight >= low and c.support >= t.support and len(c.values) >= t.diversity and c.inner >= t.inner_support:
                        out.append((x.block, x.rep, x.card, x.pattern, k, a, c.support, c.support / below, len(c.values), c.inner, c.claims, x.weight))
                bads.append(bad)
            return bads

        leaves = {x.rep: x for x in nodes[nodes["card"] == 1].itertuples(index=False)}

        def take(rep: str, card: int) -> tuple[list[dict[str, _Column]], list[set[str]]]:
            """Claims of a part; those of a code are made when its first node needs them, so few are held at a time."""
            if card > 1:
                return live.pop((rep, card)), failed.pop((rep, card))
            cols = []
            for ch in rep:
                of: dict[str, _Column] = {}
                for a, v, n in by_code.get(rep, ()):
                    of.setdefault(a, _Column()).add(ch, v, n)
                cols.append(of)
            return cols, judge(leaves.pop(rep), cols, [[] for _ in cols])

        for x in nodes[nodes["card"] > 1].sort_values(["round", "card"]).itertuples(index=False):
            parts = [(*take(r, int(c)), m) for r, c, m in ((x.left_rep, x.left_card, x.left_map), (x.right_rep, x.right_card, x.right_map))]
            cols, sources = [], []
            for k in range(int(x.n_cols)):
                of, src = {}, []
                for got, bad, m in parts:
                    j = int(m[k])
                    if j:
                        src.append(bad[j - 1])
                        for a, c in got[j - 1].items():
                            of[a] = c if a not in of else of[a].absorb(c)
                cols.append(of), sources.append(src)
            live[x.rep, x.card], failed[x.rep, x.card] = cols, judge(x, cols, sources)
        for rep in list(leaves):  # codes that no node holds
            take(rep, 1)
        return pd.DataFrame(out, columns=names)

    if gap_as_key:  # gap keys belong to whole sub-templates; the aggregate form counts them directly
        claims = node_claims(tree.members(min_weight=low), counts, True)
        found = measures(claims, ["block", "rep", "card", "col_ix", "attr"]).join(tree.all.select("block", "rep", "card", "pattern", F.col("weight").alias("tuples")), ["block", "rep", "card"])
        share = F.col("support") / F.col("claims" if denominator == "claims" else "tuples")
        return found.withColumn("confidence", share).where(t.passed(denominator)).select(*names)
    return nodes.groupBy("block").cogroup(per_code.groupBy("of_block")).applyInPandas(climb, RULES)


def drop_implied(rules: DataFrame, tree: Tree) -> DataFrame:
    """Leaves out a rule if the parent's column that it was mapped to has the same attribute's rule."""
    n = tree.nodes
    maps = None
    for s in ("left", "right"):
        one = n.select("block", "rep", "card", F.col(f"{s}_rep").alias("c_rep"), F.col(f"{s}_card").alias("c_card"), F.posexplode(f"{s}_map").alias("pos", "c_ix")).where("c_ix > 0")
        maps = one if maps is None else maps.unionByName(one)
    above = rules.select("block", "rep", "card", (F.col("col_ix") - 1).alias("pos"), "attr").join(maps, ["block", "rep", "card", "pos"])
    above = above.select("block", F.col("c_rep").alias("rep"), F.col("c_card").alias("card"), F.col("c_ix").alias("col_ix"), "attr")
    return rules.join(above, ["block", "rep", "card", "col_ix", "attr"], "left_anti")


def rule_map(df: DataFrame, code: str, rules: DataFrame, tree: Tree, attrs: list[str], members: DataFrame | None = None) -> DataFrame:
    """(block, rep, card, col_ix, attr, key, value, n, runner_up): the most frequent value of each key; ties to the smaller value."""
    picked = rules.select("block", "rep", "card").distinct()
    members = tree.members(only=picked) if members is None else members.join(picked, ["block", "rep", "card"])
    claims = node_claims(members, unpivot_counts(df, code, attrs)).join(rules.select("block", "rep", "card", "col_ix", "attr"), ["block", "rep", "card", "col_ix", "attr"])
    return majority(claims, ["block", "rep", "card", "col_ix", "attr"])


def majority(claims: DataFrame, by: list[str]) -> DataFrame:
    """The most frequent value per key, its count, and the next one's count (0 if there is none)."""
    order = W.partitionBy(*by, "key").orderBy(F.desc("n"), "value")
    ranked = claims.groupBy(*by, "key", "value").agg(F.sum("n").alias("n")).withColumn("at", F.row_number().over(order)).withColumn("runner_up", F.coalesce(F.lead("n").over(order), F.lit(0)))
    return ranked.where("at = 1").select(*by, "key", "value", "n", "runner_up")


def choose_alignment(df: DataFrame, code: str, attrs: list[str], settings: list[dict], thresholds: Thresholds = Thresholds()) -> tuple[dict, Tree, DataFrame]:
    """Lets attributes speak on the alignment: of several settings (metric, tie, ...), the one whose rules explain most.

    A setting scores, summed over attributes, the most tuples that one node's rule explains. Returns the best
    setting (ties to the earlier one), its tree, and (setting, attr, explained) of all.
    """
    from .align import dedupe, learn_tree

    codes, trees, scores = dedupe(df, code), [], None
    for k, s in enumerate(settings):
        tree = learn_tree(codes, **s)
        trees.append(tree)
        one = discover(df, code, attrs, tree, thresholds).groupBy("attr").agg(F.max("support").alias("explained")).select(F.lit(k).alias("setting"), "attr", "explained")
        scores = one if scores is None else scores.unionByName(one)
    totals = {r["setting"]: r["n"] for r in scores.groupBy("setting").agg(F.sum("explained").alias("n")).collect()}  # a row a setting
    best = max(range(len(settings)), key=lambda k: (totals.get(k, 0), -k))
    return settings[best], trees[best], scores


def rules_json(rules: DataFrame) -> DataFrame:
    """Every rule as one line of JSON, column rule."""
    return rules.select(F.to_json(F.struct(*rules.columns)).alias("rule"))


__all__ = ["GAP_KEY", "RULES", "Thresholds", "choose_alignment", "discover", "drop_implied", "majority", "rule_map", "rules_json"]
