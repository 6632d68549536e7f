"""Shared helpers of the training-data operators: scratch tables, word rules, components."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scratch import Scratch, shared_dir  # noqa: F401

#: White space of the word contracts: space and the controls tab to carriage return.
SPACE_CLASS = r"[\x20\x09-\x0D]"
SPACE_CHARS = " \t\n\x0b\x0c\r"
WORD_RE = r"[^\x20\x09-\x0D]+"


#: Rows and bytes of an Arrow batch of whole texts: two workers and their buffers must fit beside the heap.
BATCH_ROWS, BATCH_BYTES = 500, 4 << 20


@contextmanager
def lean_batches(spark: SparkSession) -> Iterator[None]:
    """Holds the session's Arrow batch limits at what rows of long texts need while an action runs, then restores them.

    Results don't depend on them. Frames that are returned unexecuted run under the caller's own limits.
    """
    keys = {"spark.sql.execution.arrow.maxRecordsPerBatch": BATCH_ROWS, "spark.sql.execution.arrow.maxBytesPerBatch": BATCH_BYTES}
    before = {k: spark.conf.get(k) for k in keys}
    for k, v in keys.items():
        spark.conf.set(k, str(v))
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_count(text: Column) -> Column:
    """Number of runs of non-space characters; null and blank texts have none."""
    bare = F.btrim(text, F.lit(SPACE_CHARS))
    return F.when(text.isNull() | (bare == ""), F.lit(0)).otherwise(F.size(F.split(bare, f"{SPACE_CLASS}+"))).cast("long")


def row_hash(df: DataFrame) -> Column:
    """A hash of all columns, equal for equal rows; a map counts by its sorted entries, a nested one by its JSON."""

    def plain(name: str, kind: str) -> Column:
        own = df[f"`{name}`"]
        if kind.startswith("map<"):
            return F.to_json(F.array_sort(F.map_entries(own)))
        return F.to_json(F.struct(own)) if "map<" in kind else own

    return F.xxhash64(*[plain(*c) for c in df.dtypes])


_UPPER = {c: c + 32 for c in range(65, 91)}


def ascii_lower(text: str) -> str:
    """A-Z only; other letters keep their case."""
    return text.translate(_UPPER) if not text.isascii() else text.lower()


def min_label_components(edges: DataFrame, scratch: Scratch, max_rounds: int = 60) -> DataFrame:
    """(node, root) of every node on an edge (u, v); root is the smallest node it can reach.

    Alternating star contraction: each round points larger neighbours at the smallest one, first
    from the larger side, then from the smaller. Rounds are written to the shared folder, so a lost
    executor costs a reread. No adjacency list is gathered: only minima are aggregated and joined.
    """
    cur = scratch.save(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "cc0")
    before = None
    for i in range(1, max_rounds + 1):
        both = cur.unionByName(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low2 = large.groupBy("u").agg(F.min("v").alias("m"))
        small = (
            large.join(low2, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
            .unionByName(low2.select("u", F.col("m").alias("v")))
            .where("u <> v").distinct()
        )
        nxt = scratch.save(small, f"cc{i}")
        # A forest of stars keeps its edge count and label sum from one round to the next.
        now = nxt.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        scratch.drop(f"cc{i - 1}")
        cur = nxt
        if before is not None and tuple(now) == before:
            break
        before = tuple(now)
    else:
        raise RuntimeError(f"components still change after {max_rounds} rounds")
    return cur.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(cur.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
