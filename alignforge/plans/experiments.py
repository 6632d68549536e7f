"""The efficiency grid: counts and times of the searches over length, number, clusters and variation of generated codes.

Every setting is a block of its own, so a grid is one job per search and settings run side by side.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.align import SEARCHES, compare_searches, dedupe
from ..sources.codes import relation
from ..sources.synth import DEFAULTS, coded_strings

# The parameter ranges of the experiments.
LENGTHS, NUMBERS, CLUSTERS, VARIATIONS = (10, 12, 14, 16, 18, 20), (1000, 2000, 3000, 4000, 5000), (10, 25, 50, 75, 100), (0.01, 0.03, 0.05, 0.07, 0.10)


def generated(spark: SparkSession, settings: list[dict]) -> DataFrame:
    """Distinct codes of all settings, one block each."""
    out = None
    for s in settings:
        own = DEFAULTS | s
        one = dedupe(coded_strings(spark, **own)).withColumn("block", F.lit(",".join(f"{k}={v}" for k, v in own.items())))
        out = one if out is None else out.unionByName(one)
    return out


def costs(codes: DataFrame, searches: tuple[str, ...] = tuple(SEARCHES)) -> DataFrame:
    """Counters per block and search."""
    return compare_searches(codes, searches=searches)


def real(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three stand-ins as blocks."""
    out = None
    for name in ("part_code", "page_url", "order_code"):
        one = dedupe(relation(spark, sf_dir, name)).withColumn("block", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out
