"""Trees as DataFrames: dedupe, block, learn, members, cuts; and exact alignment of very small sets."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache
from itertools import product

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..plans.scratch import Scratch
from . import tree as T
from .metric import GAP, CharMetric
from .pattern import to_display, to_regex

NODES = (
    "block string, rep string, card long, weight long, cost_u int, n_cols int, cols array<array<string>>, left_rep string, left_card long, "
    "right_rep string, right_card long, left_map array<int>, right_map array<int>, pattern string, regex string, round int, "
    "counters map<string,long>, refine_hist map<int,long>"
)
#: Codes that one block may have for a tree on one worker, which holds two half words a pair (0.8 GB). Of larger blocks the cheapest
#: fuses are made first (near.py); blocks that are larger even so are fused in rounds.
MAX_BLOCK = 14_000


def dedupe(df: DataFrame, code: str = "code") -> DataFrame:
    """Distinct codes with their tuple counts; null and empty codes are left out. One shuffle with partial sums."""
    return df.where((F.col(code) != "") & F.col(code).isNotNull()).groupBy(F.col(code).alias("code")).agg(F.count("*").alias("weight"))


def signature(code: Column) -> Column:
    """Code with runs of digits, letters and other characters reduced to one sign each."""
    # a letter sign first, as signs of the other classes must not be read again as letters
    return F.regexp_replace(F.regexp_replace(F.regexp_replace(code, r"\p{L}+", "A"), r"[0-9]+", "9"), r"[^A9]+", "-")


def block_by(codes: DataFrame, how: str = "none", length: int = 2) -> DataFrame:
    """Adds block: all in one, by class signature, by prefix, or by the smallest hash of the code's bigrams."""
    code = F.col("code")
    if how == "none":
        key = F.lit("all")
    elif how == "signature":
        key = signature(code)
    elif how == "prefix":
        key = F.substring(code, 1, length)
    elif how == "minhash":
        grams = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(code) - 1)), lambda i: F.xxhash64(F.substring(code, i, F.lit(2))))
        key = F.array_min(grams).cast("string")
    else:
        raise ValueError(how)
    return codes.withColumn("block", key)


def _rows(block: str, fused: T.Fused) -> Iterator[tuple]:
    for k, x in enumerate(fused.nodes):
        t, last = x.template, k == len(fused.nodes) - 1
        left, right = x.left or (None, None), x.right or (None, None)
        yield (
            block, t.rep, t.card, t.weight, t.spread, len(t), [sorted(c, key=lambda ch: (ch is GAP, ch or "")) for c in t.cols], *left, *right,
            x.left_map, x.right_map, to_display(t.cols), to_regex(t.cols), x.round, list(fused.counters.items()) if last else None, list(fused.refine_hist.items()) if last else None,
        )


class Tree:
    """A learned tree: one row per node, leaves included, keyed by (block, rep, card)."""

    def __init__(self, all_nodes: DataFrame, metric: CharMetric, tie: str):
        self.all, self.metric, self.tie = all_nodes, metric, tie

    @property
    def nodes(self) -> DataFrame:
        """Fused nodes only."""
        return self.all.where("card > 1").drop("counters", "refine_hist")

    @property
    def counters(self) -> DataFrame:
        """One row a block: n, fuse_evals, fuse_done, refines, tightenings, rounds, wall_ms, and the histogram of refines."""
        names = ("n", "fuse_evals", "fuse_done", "refines", "tightenings", "rounds", "wall_ms")
        return self.all.where("counters is not null").select("block", *[F.col("counters")[k].alias(k) for k in names], "refine_hist")

    def roots(self) -> DataFrame:
        """Nodes that no other node holds; one a block unless a cost limit stopped the fusing."""
        held = self.nodes.select("block", F.explode(F.array(F.struct("left_rep", "left_card"), F.struct(F.col("right_rep").alias("left_rep"), F.col("right_card").alias("left_card")))).alias("x"))
        return self.all.join(held.select("block", F.col("x.left_rep").alias("rep"), F.col("x.left_card").alias("card")), ["block", "rep", "card"], "left_anti")

    def members(self, min_card: int = 1, min_weight: int = 1, only: DataFrame | None = None) -> DataFrame:
        """(block, rep, card, code, aligned) of every node of at least so many codes and tuples; maps are composed per block.

        only: nodes (block, rep, card) to expand; no other is. A chain-like tree of n codes has n^2/2 rows without it.
        """
        kept = ["block", "rep", "card", "weight", "n_cols", "left_rep", "left_card", "right_rep", "right_card", "left_map", "right_map"]

        def spread_out(pdf: pd.DataFrame) -> pd.DataFrame:
            nodes = {(r.rep, r.card): r for r in pdf.itertuples()}
            out = []
            for key, node in nodes.items():
                if not node.wanted or node.card < min_card or node.weight < min_weight:
                    continue
                stack = [(key, list(range(1, node.n_cols + 1)))]
                while stack:
                    (rep, card), at = stack.pop()
                    x = nodes[rep, card]
                    if card == 1:
                        out.append((x.block, *key, rep, [rep[k - 1] if k else None for k in at]))
                    else:
                        stack.append(((x.left_rep, int(x.left_card)), [int(x.left_map[k - 1]) if k else 0 for k in at]))
                        stack.append(((x.right_rep, int(x.right_card)), [int(x.right_map[k - 1]) if k else 0 for k in at]))
            return pd.DataFrame(out, columns=["block", "rep", "card", "code", "aligned"])

        key = ["block", "rep", "card"]
        marked = self.all.select(*kept).withColumn("wanted", F.lit(True)) if only is None else self.all.select(*kept).join(only.select(*key).distinct().withColumn("found", F.lit(True)), key, "left").withColumn("wanted", F.col("found").isNotNull()).drop("found")
        return marked.groupBy("block").applyInPandas(spread_out, "block string, rep string, card long, code string, aligned array<string>")

    def path(self) -> DataFrame:
        """(block, rep, card, up_rep, up_card): every node's parent."""
        n = self.nodes
        side = lambda s: n.select("block", F.col(f"{s}_rep").alias("rep"), F.col(f"{s}_card").alias("card"), F.col("rep").alias("up_rep"), F.col("card").alias("up_card"))
        return side("left").unionByName(side("right"))

    def cut(self, max_cost: float | None = None, max_cost_per_col: float | None = None, min_card: int | None = None) -> DataFrame:
        """Flat clusters: the largest nodes within the limits, none inside another."""
        ok = F.lit(True)
        if max_cost is not None:
            ok = ok & (F.col("cost_u") <= 2 * max_cost)
        if max_cost_per_col is not None:
            ok = ok & (F.col("cost_u") <= 2 * max_cost_per_col * F.col("n_cols"))
        marked = self.all.drop("counters", "refine_hist").withColumn("ok", ok)
        # costs never fall towards the root; for a limit per column, a node counts if it is the topmost that fits
        up = self.path().join(marked.select("block", F.col("rep").alias("up_rep"), F.col("card").alias("up_card"), F.col("ok").alias("up_ok")), ["block", "up_rep", "up_card"])
        flat = marked.where("ok").join(up.where("up_ok").select("block", "rep", "card"), ["block", "rep", "card"], "left_anti").drop("ok")
        return flat.where(F.col("card") >= min_card) if min_card else flat

    def largest_step(self) -> float:
        """The cost below the largest step between neighbouring fuse costs of any block: a cut that needs no knowledge of clusters."""
        order = W.partitionBy("block").orderBy("cost_u")
        steps = self.nodes.select("block", "cost_u").distinct().withColumn("step", F.lead("cost_u").over(order) - F.col("cost_u"))
        best = steps.agg(F.max_by("cost_u", F.struct("step", -F.col("cost_u")))).first()[0]
        return (best or 0) / 2


def learn_tree(
    codes: DataFrame, metric: CharMetric | None = None, algorithm: str = "bounded", profile: str = "star+inherit", independence: bool = True,
    tie: str = "gap_late", lower: str = "profile", max_cost: float | None = None, max_block: int = MAX_BLOCK, finish: int | None = None,
) -> Tree:
    """Learns one tree per block; blocks are the unit of work, and the result is kept in the shared folder.

    algorithm: 'pair', 'chain', 'bounded' (with profile 'star' or 'star+inherit') or 'rounds'. With 'bounded', blocks of
    more than max_block codes are fused from their least costs up where that leaves at most max_block templates, and in
    rounds otherwise; both give the same tree. So are, with no search of its own asked for, blocks of more than near.FROM; a search
    that was asked for (profile, independence, lower) is never replaced by these. finish: templates of a block that a worker may take over from the rounds.
    """
    metric = metric or CharMetric.classes()
    if "block" not in codes.columns:
        codes = block_by(codes)
    if "weight" not in codes.columns:
        codes = codes.withColumn("weight", F.lit(1).cast("long"))
    scratch = Scratch(codes.sparkSession, "tree")
    limit = None if max_cost is None else int(2 * max_cost)
    from .rounds import FINISH, round_fuse

    in_rounds = lambda some: round_fuse(some, metric, tie, limit, scratch, FINISH if finish is None else finish)
    if algorithm == "rounds":
        return Tree(in_rounds(codes), metric, tie)
    large = near = None
    from .near import FROM, MOST, fuse_large, has_least

    if algorithm == "bounded" and metric.kind == "diameter":
        codes = scratch.save(codes.select("block", "code", "weight"), "codes")
        over = codes.groupBy("block").agg(F.count("*").alias("n")).where(F.col("n") > max_block)
        if not over.isEmpty():
            if (profile, independence, lower) != ("star+inherit", True, "profile"):
                raise ValueError(f"a block has more than {max_block} codes; the search asked for holds intervals of all its pairs, and no other one takes its place")
            over = scratch.save(over, "over")
            large, codes = codes.join(over, "block", "left_semi"), codes.join(over, "block", "left_anti")
            near = large.join(over.where(F.col("n") <= MOST), "block", "left_semi") if has_least(metric, limit) else None
    options = {"tie": tie, "max_cost": limit}
    if algorithm == "bounded":
        options |= {"profile": profile, "independence": independence, "lower": lower}

    #: no search of its own was asked for, only the tree
    plain = algorithm == "bounded" and (profile, independence, lower) == ("star+inherit", True, "profile") and metric.kind == "diameter" and has_least(metric, limit)

    def grow(pdf: pd.DataFrame) -> pd.DataFrame:
        if len(pdf) > max_block:
            raise ValueError(f"block {pdf['block'].iloc[0]!r} has {len(pdf)} codes; over {max_block} only the bounded search goes on, in rounds")
        if plain and len(pdf) > FROM:
            return grow_near(pdf)
        return framed(pdf, T.run(pdf["code"].tolist(), metric, algorithm, pdf["weight"].tolist(), **options))

    def grow_near(pdf: pd.DataFrame) -> pd.DataFrame:
        return framed(pdf, fuse_large(pdf["code"].tolist(), metric, pdf["weight"].tolist(), tie, limit, max_block))

    def framed(pdf: pd.DataFrame, fused: T.Fused | None) -> pd.DataFrame:
        rows = [] if fused is None else list(_rows(pdf["block"].iloc[0], fused))
        out = pd.DataFrame(rows, columns=[c.split(" ")[0] for c in NODES.replace(", ", ",").replace("map<string,long>", "x").replace("map<int,long>", "x").split(",")])
        for c in ("counters", "refine_hist"):
            out[c] = out[c].map(lambda x: None if x is None else dict(x))
        for c in ("left_card", "right_card"):
            out[c] = out[c].astype("Int64")
        return out

    grown = scratch.save(codes.select("block", "code", "weight").groupBy("block").applyInPandas(grow, NODES), "grown")
    if near is not None:
        done = scratch.save(near.select("block", "code", "weight").groupBy("block").applyInPandas(grow_near, NODES), "near")
        grown, large = grown.unionByName(done), large.join(done.select("block").distinct(), "block", "left_anti")
        if large.isEmpty():
            large = None
    return Tree(grown if large is None else grown.unionByName(in_rounds(large)), metric, tie)


SEARCHES = {"pair": {"algorithm": "pair"}, "bounded_star": {"algorithm": "bounded", "profile": "star"}, "bounded_inherit": {"algorithm": "bounded", "profile": "star+inherit"}, "bounded_profile": {"algorithm": "bounded", "profile": "star+inherit", "lower": "profile"}}


def compare_searches(codes: DataFrame, metric: CharMetric | None = None, tie: str = "gap_late", searches: tuple[str, ...] = tuple(SEARCHES), repeats: int = 1) -> DataFrame:
    """(method, block, n, fuse_evals, fuse_done, refines, tightenings, wall_ms, refine_hist): one task per block, search and repeat.

    Only figures come back, no nodes. wall_ms is the median of the repeats; all else is the same in each.
    """
    metric = metric or CharMetric.classes()
    if "block" not in codes.columns:
        codes = block_by(codes)
    each = codes.select("block", "code", "weight", F.explode(F.array(*[F.lit(s) for s in searches])).alias("method")).withColumn("turn", F.explode(F.sequence(F.lit(1), F.lit(repeats))))

    def measure(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        x = T.run(pdf["code"].tolist(), metric, weights=pdf["weight"].tolist(), **{"tie": tie, **SEARCHES[key[0]]})
        return pd.DataFrame([(*key[:2], *[x.counters[k] for k in figures], dict(x.refine_hist))], columns=["method", "block", *figures, "refine_hist"])

    figures = ["n", "fuse_evals", "fuse_done", "refines", "tightenings", "wall_ms"]
    schema = f"method string, block string, {', '.join(f'{k} long' for k in figures)}, refine_hist map<int,long>"
    # long searches do not share a task: each has several of the ranges, of which equal ones are one
    many = each.select("method", "block", "turn").distinct().count()
    runs = each.repartitionByRange(max(1, 4 * many), "method", "block", "turn").groupBy("method", "block", "turn").applyInPandas(measure, schema)
    if repeats == 1:
        return runs
    return runs.groupBy("method", "block").agg(*[F.max(k).alias(k) for k in figures[:-1]], F.median("wall_ms").cast("long").alias("wall_ms"), F.first("refine_hist").alias("refine_hist"))


def length_bounds(codes: DataFrame) -> DataFrame:
    """Range of any alignment's length: the longest code to all codes end to end."""
    return codes.agg(F.max(F.length("code")).cast("long").alias("lo"), F.sum(F.length("code")).cast("long").alias("hi"))


def align_exact(codes: list[str], metric: CharMetric, threshold: int | None = None) -> int | bool:
    """Least spread of any alignment of a few short codes, by search over the lattice of prefixes; a test oracle."""
    if len(codes) > 4:
        raise ValueError("for at most four codes")

    @lru_cache(maxsize=None)
    def rest(at: tuple[int, ...]) -> int:
        if all(k == len(c) for k, c in zip(at, codes)):
            return 0
        best = T.FAR
        for take in product(*[(0, 1) if k < len(c) else (0,) for k, c in zip(at, codes)]):
            if any(take):
                col = frozenset(c[k] if t else GAP for c, k, t in zip(codes, at, take))
                best = min(best, metric.column_spread(col) + rest(tuple(k + t for k, t in zip(at, take))))
        return best

    least = rest((0,) * len(codes))
    return least if threshold is None else least <= threshold


def scs_instance(strings: list[str], k: int, filler: str = "□") -> tuple[list[str], CharMetric, int]:
    """Codes, metric and threshold (half-units) that align within the threshold iff the strings have a common supersequence of length k."""
    return [*strings, filler * k], CharMetric.filler("".join(sorted(set("".join(strings)))), filler), 2 * k


def rank_in_block(codes: DataFrame) -> DataFrame:
    """Position of each code in its block by code point."""
    return codes.withColumn("ix", F.row_number().over(W.partitionBy("block").orderBy("code")))
