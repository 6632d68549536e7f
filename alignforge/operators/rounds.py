"""Round-parallel fusing with intervals: every round fuses all pairs that are first for both of their templates.

State is two tables per block: live templates and cost intervals of pairs. A round is a handful of joins and
aggregates and a batch of alignments of critical pairs on the executors, so a block may be larger than a
worker. The tree is that of pairwise fusing, as mutually first pairs stay first whatever else is fused.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import count

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from ..plans.scratch import Scratch
from .bounded import bounded_fuse
from .kernel import Pool, Template, fuse, fuse_cost, leaf
from .metric import GAP, CharMetric
from .tree import FAR

LIVE = "block string, rep string, card long, weight long, cost_u int, cols array<array<string>>"
PAIRS = "block string, a string, b string, lb int, ub int"
#: Codes of a chunk, and templates of a block that one worker may finish.
CHUNK, FINISH = 500, 2000


def _sets(cols) -> list[frozenset]:
    return [frozenset(c) for c in cols]


def _template(rep: str, card: int, weight: int, cols, metric: CharMetric) -> Template:
    sets = _sets(cols)
    return Template(rep, card, sets, sum(metric.column_spread(c) for c in sets), np.array([metric.pack(c) for c in sets], np.int64) if metric.packed else None, weight)


def pair_costs(pairs: DataFrame, metric: CharMetric) -> DataFrame:
    """Adds cost to pairs (block, a, b, a_cols, b_cols)."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            made: dict[str, Template] = {}

            def of(rep: str, cols) -> Template:
                if rep not in made:
                    made[rep] = _template(rep, 1, 1, cols, metric)
                return made[rep]

            cost = [fuse_cost(of(a, x), of(b, y), metric) for a, b, x, y in zip(pdf["a"], pdf["b"], pdf["a_cols"], pdf["b_cols"])]
            yield pd.DataFrame({"block": pdf["block"], "a": pdf["a"], "b": pdf["b"], "cost": np.array(cost, np.int32)})

    return pairs.select("block", "a", "b", "a_cols", "b_cols").mapInPandas(run, "block string, a string, b string, cost int")


def first_intervals(leaves: DataFrame, metric: CharMetric, max_cost: int | None) -> DataFrame:
    """(block, a, b, lb, ub) of all pairs a < b of a block's codes, without aligning any; with a cost limit only those that may be within it.

    Codes are dealt to chunks and chunks meet in a grid of cells, so a task holds two chunks whatever the block's size.
    """
    size = leaves.groupBy("block").agg(F.ceil(F.count("*") / CHUNK).cast("int").alias("parts"))
    own = leaves.select("block", "rep").join(size, "block").withColumn("mine", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int"))
    dealt = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1))).select("block", "rep", "mine", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"))

    def cell(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("rep", ignore_index=True)
        reps, mine = pdf["rep"].to_numpy(object), pdf["mine"].to_numpy()
        if metric.packed:
            low, high = Pool([leaf(c, metric) for c in reps], metric).intervals()
        else:
            low, high = np.zeros((len(reps), len(reps)), np.int32), np.full((len(reps), len(reps)), FAR, np.int32)
        a, b = np.triu_indices(len(reps), 1)
        wanted = (mine[a] != mine[b]) | (key[1] == key[2])
        if max_cost is not None:
            wanted &= low[a, b] <= max_cost
        a, b = a[wanted], b[wanted]
        return pd.DataFrame({"block": key[0], "a": reps[a], "b": reps[b], "lb": low[a, b].astype(np.int32), "ub": high[a, b].astype(np.int32)})

    return dealt.groupBy("block", "i", "j").applyInPandas(cell, PAIRS)


def firsts(pairs: DataFrame) -> DataFrame:
    """(block, rep, m): the pair that sorts first by (ub, a, b) of those that a template is in."""
    ends = pairs.select("block", F.explode(F.array("a", "b")).alias("rep"), F.struct("ub", "a", "b").alias("m"))
    return ends.groupBy("block", "rep").agg(F.min("m").alias("m"))


def critical(pairs: DataFrame) -> DataFrame:
    """Pairs of unknown cost that may come before the best known pair of one of their templates."""
    best = firsts(pairs)
    side = lambda s: best.select("block", F.col("rep").alias(s), F.struct(F.col("m.ub").alias("lb"), "m.a", "m.b").alias(f"m_{s}"))
    open_ = pairs.where("lb < ub").join(side("a"), ["block", "a"]).join(side("b"), ["block", "b"])
    own = F.struct("lb", "a", "b")
    return open_.where((own < F.col("m_a")) | (own < F.col("m_b"))).select("block", "a", "b")


def round_fuse(codes: DataFrame, metric: CharMetric, tie: str, max_cost: int | None, scratch: Scratch, finish: int = FINISH) -> DataFrame:
    """Rows of align.NODES; counters hold, per block, rounds and evaluations.

    A round measures the critical pairs only, so every template's first pair is known, fuses the mutually first ones
    and lets the new templates inherit bounds. Once no block has more than `finish` templates, each is finished by the
    bounded search on one worker.
    """
    from .align import NODES, _rows

    if metric.kind != "diameter":
        raise ValueError("bounds hold for diameter spreads only")
    spark, plain = codes.sparkSession, [c.split(" ")[0] for c in LIVE.split(", ")]
    leaves = codes.select("block", F.col("code").alias("rep"), F.lit(1).cast("long").alias("card"), "weight", F.lit(0).alias("cost_u"), F.transform(F.split("code", ""), lambda c: F.array(c)).alias("cols"))
    live = scratch.save(leaves.where("rep <> ''"), "live0")
    pairs = scratch.save(first_intervals(live, metric, max_cost), "pairs0")
    schema = scratch.save(_named(live), "made/round=0").schema
    counted = live.groupBy("block").agg(F.count("*").alias("n"))
    counted = scratch.save(counted, "counted")

    def join_all(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            out = []
            for r in pdf.itertuples(index=False):
                p, q = (_template(*x, metric) for x in ((r.a, r.a_card, r.a_weight, r.a_cols), (r.b, r.b_card, r.b_weight, r.b_cols)))
                t, left, right = fuse(p, q, metric, tie)
                cols = [sorted(c, key=lambda ch: (ch is GAP, ch or "")) for c in t.cols]
                out.append((r.block, t.rep, t.card, t.weight, t.spread, cols, r.a, r.a_card, r.b, r.b_card, left, right))
            yield pd.DataFrame(out, columns=["block", "rep", "card", "weight", "cost_u", "cols", "left_rep", "left_card", "right_rep", "right_card", "left_map", "right_map"])

    fused_schema = f"{LIVE}, left_rep string, left_card long, right_rep string, right_card long, left_map array<int>, right_map array<int>"
    for turn in count(1):
        most = live.groupBy("block").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0
        if most <= finish:
            break
        cols = lambda s: live.select("block", F.col("rep").alias(s), F.col("cols").alias(f"{s}_cols"))  # noqa: B023, E731
        asked = critical(pairs).join(cols("a"), ["block", "a"]).join(cols("b"), ["block", "b"])
        met = scratch.save(pair_costs(asked, metric), f"met/round={turn}")
        known = pairs.join(met, ["block", "a", "b"], "left").select("block", "a", "b", F.coalesce("cost", "lb").alias("lb"), F.coalesce("cost", "ub").alias("ub"))
        known = scratch.save(known, f"known{turn}")
        best = firsts(known if max_cost is None else known.where(F.col("ub") <= max_cost))
        mutual = best.groupBy("block", "m").agg(F.count("*").alias("k")).where("k = 2").select("block", "m.a", "m.b")
        side = lambda s: live.select("block", F.col("rep").alias(s), *[F.col(c).alias(f"{s}_{c}") for c in ("card", "weight", "cols")])  # noqa: B023, E731
        chosen = mutual.join(side("a"), ["block", "a"]).join(side("b"), ["block", "b"])
        fused = scratch.save(chosen.mapInPandas(join_all, fused_schema), f"fused{turn}")
        if fused.isEmpty():
            break
        scratch.save(_named(fused).select(*schema.names), f"made/round={turn}")
        to = fused.select("block", F.explode(F.array("left_rep", "right_rep")).alias("old"), "rep", F.col("cost_u").alias("cost"))
        kept = live.join(to.select("block", F.col("old").alias("rep")), ["block", "rep"], "left_anti")
        now = scratch.save(kept.unionByName(fused.select(*plain)), f"live{turn}")
        for s in ("a", "b"):
            known = known.join(to.select("block", F.col("old").alias(s), F.col("rep").alias(f"{s}_new"), F.col("cost").alias(f"{s}_cost")), ["block", s], "left")
        ends, extra = (F.coalesce("a_new", "a"), F.coalesce("b_new", "b")), [F.coalesce(f"{s}_cost", F.lit(0)) for s in ("a", "b")]
        # a fused template costs at least itself and each of its parts, and at most one part's cost and its own
        named = known.select("block", F.least(*ends).alias("a"), F.greatest(*ends).alias("b"), F.greatest("lb", *extra).alias("lb"), F.least(F.lit(FAR), F.col("ub") + extra[0] + extra[1]).alias("ub"))
        pairs = named.where("a <> b").groupBy("block", "a", "b").agg(F.max("lb").alias("lb"), F.min("ub").alias("ub"))
        pairs = scratch.save(pairs if max_cost is None else pairs.where(F.col("lb") <= max_cost), f"pairs{turn}")
        for old in (f"live{turn - 1}", f"pairs{turn - 1}", f"known{turn}", f"fused{turn}"):
            scratch.drop(old)
        live = now

    def rest(pdf: pd.DataFrame) -> pd.DataFrame:
        items = [_template(*x, metric) for x in zip(pdf["rep"], pdf["card"], pdf["weight"], pdf["cols"])]
        fused = bounded_fuse([], metric, tie=tie, max_cost=max_cost, templates=items)
        out = pd.DataFrame(list(_rows(pdf["block"].iloc[0], fused)), columns=_names(NODES))
        out["round"] += turn
        last = {k: fused.counters[k] for k in ("fuse_evals", "refines", "tightenings")}, dict(fused.refine_hist)
        for c, own in zip(("counters", "refine_hist"), last):  # on the last node only
            out[c] = pd.Series([None] * (len(out) - 1) + [own] if len(out) else [], dtype=object)
        return out

    nodes = spark.read.schema(StructType([*schema.fields, StructField("round", IntegerType())])).parquet(scratch.path("made"))
    nodes = nodes.withColumn("counters", F.lit(None).cast("map<string,long>")).withColumn("refine_hist", F.lit(None).cast("map<int,long>")).select(*_names(NODES))
    if most <= finish:
        nodes = scratch.save(nodes.unionByName(live.groupBy("block").applyInPandas(rest, NODES)), "nodes")
    evals = spark.read.schema("block string, a string, b string, cost int, round int").parquet(scratch.path("met")).groupBy("block").agg(F.count("*").alias("met")) if turn > 1 or most > finish else spark.createDataFrame([], "block string, met long")
    local = nodes.groupBy("block").agg(*[F.coalesce(F.sum(F.col("counters")[c]), F.lit(0)).alias(c) for c in ("fuse_evals", "refines", "tightenings")], F.count_if(F.col("card") > 1).alias("fuse_done"), F.max(F.struct("round", "card", "rep")).alias("last"))
    figures = local.join(evals, "block", "left").join(counted, "block")
    held = [("n", F.col("n")), ("fuse_evals", F.col("fuse_evals") + F.coalesce("met", F.lit(0))), ("rounds", F.lit(turn - 1).cast("long")), *((c, F.col(c)) for c in ("fuse_done", "refines", "tightenings")), ("wall_ms", F.lit(0).cast("long"))]
    figures = figures.select("block", F.col("last.rep").alias("rep"), F.col("last.card").alias("card"), F.create_map(*[x for k, v in held for x in (F.lit(k), v)]).alias("counters"))
    return nodes.drop("counters").join(figures, ["block", "rep", "card"], "left").select(*_names(NODES))


def _names(schema: str) -> list[str]:
    depth, out, start = 0, [], 0
    for k, ch in enumerate(schema + ","):
        depth += (ch == "<") - (ch == ">")
        if ch == "," and depth == 0:
            out.append(schema[start:k].strip().split(" ")[0])
            start = k + 1
    return out


def _named(rows: DataFrame) -> DataFrame:
    """Adds display, regex and missing node columns."""
    import pandas as pd

    from .pattern import to_display, to_regex

    @F.pandas_udf("string")
    def display(cols: pd.Series) -> pd.Series:
        return cols.map(lambda x: to_display(_sets(x)))

    @F.pandas_udf("string")
    def regex(cols: pd.Series) -> pd.Series:
        return cols.map(lambda x: to_regex(_sets(x)))

    for c, kind in (("left_rep", "string"), ("left_card", "long"), ("right_rep", "string"), ("right_card", "long"), ("left_map", "array<int>"), ("right_map", "array<int>")):
        if c not in rows.columns:
            rows = rows.withColumn(c, F.lit(None).cast(kind))
    return rows.withColumn("n_cols", F.size("cols")).withColumn("pattern", display("cols")).withColumn("regex", regex("cols"))
