"""SQL names of the methods: scalar, aggregate and table functions, all Arrow-batched where Python is needed."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..operators.kernel import Template, align_costs, align_pair
from ..operators.metric import CROSS, GAP_COST, SAME, CharMetric
from ..operators.pattern import fit_to, key_of, parse_display


def cost_udf(metric: CharMetric):
    @F.pandas_udf("double")
    def align_cost(a: pd.Series, b: pd.Series) -> pd.Series:
        ok = (a.notna() & b.notna()).to_numpy()
        out = np.full(len(a), np.nan)
        if ok.any():
            out[ok] = align_costs(a[ok].tolist(), b[ok].tolist(), metric) / 2
        return pd.Series(out).astype(object).where(ok, None)

    return align_cost


def show_udf(metric: CharMetric, tie: str = "gap_late"):
    @F.pandas_udf("string")
    def align_show(a: pd.Series, b: pd.Series) -> pd.Series:
        one = lambda x, y: None if x is None or y is None else "|".join("".join(c or "_" for c in r) for r in align_pair(x, y, metric, tie)[1:])
        return pd.Series([one(x, y) for x, y in zip(a, b)], dtype=object)

    return align_show


def _of_display(text: str, metric: CharMetric) -> Template:
    cols = parse_display(text)
    return Template("", 1, cols, 0, np.array([metric.pack(c) for c in cols], np.int64) if metric.packed else None)


def key_udf(metric: CharMetric):
    @F.pandas_udf("string")
    def code_key(code: pd.Series, pattern: pd.Series, i: pd.Series) -> pd.Series:
        made = {p: _of_display(p, metric) for p in pattern.dropna().unique()}
        return pd.Series([key_of(c, made[p], int(k), metric) if c is not None and p is not None and k == k else None for c, p, k in zip(code, pattern, i)], dtype=object)

    return code_key


def spread_agg(metric: CharMetric):
    """Aggregate: spread of the set of characters of a group; null is the gap."""

    @F.pandas_udf("double")
    def column_spread(ch: pd.Series) -> float:
        return metric.column_spread(None if c is None or c != c else c for c in ch.unique()) / 2

    return column_spread


def spread_native(ch: Column, same: float = SAME, cross: float = CROSS, gap: float = GAP_COST) -> Column:
    """The same without Python: class bits, distinct characters and gaps are built-in aggregates."""
    bit = F.when(ch.isNull(), 0).when(ch.rlike("^[0-9]$"), 1).when(ch.rlike(r"^\p{L}$"), 2).otherwise(4)
    classes = F.bit_count(F.bit_or(bit))
    return F.greatest(
        F.when(F.count_distinct(ch) > 1, F.lit(same)).otherwise(F.lit(0.0)), F.when(classes > 1, F.lit(cross)).otherwise(F.lit(0.0)), F.when(F.bool_or(ch.isNull()) & (classes > 0), F.lit(gap)).otherwise(F.lit(0.0))
    )


def pattern_agg():
    """Aggregate: display text of one column's characters."""
    from ..operators.pattern import to_display

    @F.pandas_udf("string")
    def column_pattern(ch: pd.Series) -> str:
        return to_display([frozenset(None if c is None or c != c else c for c in ch.unique())])

    return column_pattern


class AlignColumns:
    """Table function: (pos, ch) of a code laid out in a display pattern; no rows if it does not match."""

    def eval(self, code: str, pattern: str) -> Iterator[tuple[int, str | None]]:
        metric = CharMetric.classes()
        laid = fit_to(code, _of_display(pattern, metric), metric) if code is not None and pattern is not None else None
        for k, ch in enumerate(laid or [], 1):
            yield k, ch


class TreeEdges:
    """Table function: (child_rep, child_card) of a node given as JSON."""

    def eval(self, node: str) -> Iterator[tuple[str, int]]:
        x = json.loads(node)
        for side in ("left", "right"):
            if x.get(f"{side}_rep") is not None:
                yield x[f"{side}_rep"], int(x[f"{side}_card"])


def register(spark: SparkSession, metric: CharMetric | None = None) -> None:
    """Registers align_cost, align_show, code_key, column_spread, column_pattern, align_columns and tree_edges."""
    metric = metric or CharMetric.classes()
    spark.udf.register("align_cost", cost_udf(metric))
    spark.udf.register("align_show", show_udf(metric))
    spark.udf.register("code_key", key_udf(metric))
    spark.udf.register("column_spread", spread_agg(metric))
    spark.udf.register("column_pattern", pattern_agg())
    spark.udtf.register("align_columns", F.udtf(AlignColumns, returnType="pos int, ch string"))
    spark.udtf.register("tree_edges", F.udtf(TreeEdges, returnType="child_rep string, child_card long"))
