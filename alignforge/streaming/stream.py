"""Rules on streams: violation counts by window, claims kept as state, duplicates, joins of two streams.

Learned rules are a static table. The same functions take a stream or a batch; only the watermark matters
to a stream.
"""

from __future__ import annotations

from collections.abc import Iterator
from typing import Any

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

DELAY = "10 minutes"


def read_stream(spark: SparkSession, path: str, schema: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def flagged(events: DataFrame, rule_map: DataFrame, key: Column, value: str) -> DataFrame:
    """Adds expected and violates; events with an unknown key do not violate. The map joins as a small table."""
    known = rule_map.select(F.col("key").alias("__key"), F.col("value").alias("expected"))
    joined = events.withColumn("__k", key).join(known, F.col("__k") == F.col("__key"), "left").drop("__k", "__key")
    return joined.withColumn("violates", F.coalesce(F.col("expected") != F.col(value), F.lit(False)))


def violation_counts(rows: DataFrame, width: str = "1 hour", slide: str | None = None, delay: str = DELAY) -> DataFrame:
    """Tumbling or sliding counts of events and violations by event time; late rows beyond the delay are dropped."""
    span = F.window("ts", width, slide) if slide else F.window("ts", width)
    return rows.withWatermark("ts", delay).groupBy(span.alias("w")).agg(F.count("*").alias("events"), F.count_if("violates").alias("violations")).select(F.col("w.start").alias("w_start"), "events", "violations")


def violation_sessions(rows: DataFrame, gap: str = "2 hours", delay: str = DELAY) -> DataFrame:
    """Per user, runs of violations no further apart than the gap."""
    bad = rows.where("violates").withWatermark("ts", delay)
    return bad.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("violations")).select("user_id", F.col("w.start").alias("w_start"), F.col("w.end").alias("w_end"), "violations")


def distinct_events(rows: DataFrame, delay: str = DELAY) -> DataFrame:
    """One row per event_id within the delay."""
    return rows.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def claim_counts(rows: DataFrame, key: Column, value: str, delay: str = DELAY) -> DataFrame:
    """Running (key, value, n) as state per key; each batch emits the changed counts. State is one row per pair."""

    def update(k: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        have: dict[Any, int] = dict(zip(*[list(x) for x in state.get])) if state.exists else {}
        changed: set = set()
        for pdf in parts:
            for v, n in pdf["value"].value_counts().items():
                have[v] = have.get(v, 0) + int(n)
                changed.add(v)
        state.update((list(have), list(have.values())))
        yield pd.DataFrame({"key": [k[0]] * len(changed), "value": list(changed), "n": [have[v] for v in changed]})

    pairs = rows.select(key.alias("key"), F.col(value).alias("value")).where("key is not null and value is not null")
    return pairs.groupBy("key").applyInPandasWithState(update, "key string, value string, n long", "vs array<string>, ns array<long>", "update", GroupStateTimeout.NoTimeout)


def paired(left: DataFrame, right: DataFrame, within: str = "30 minutes", delay: str = DELAY) -> DataFrame:
    """Violations of one stream with the same user's events of another up to so much later."""
    a = left.where("violates").select("user_id", F.col("ts").alias("v_ts"), F.col("event_id").alias("v_id")).withWatermark("v_ts", delay)
    b = right.select(F.col("user_id").alias("e_user"), F.col("ts").alias("e_ts"), F.col("event_id").alias("e_id")).withWatermark("e_ts", delay)
    near = (F.col("user_id") == F.col("e_user")) & (F.col("e_ts") > F.col("v_ts")) & (F.col("e_ts") <= F.col("v_ts") + F.expr(f"interval {within}"))
    return a.join(b, near).select("user_id", "v_id", "e_id")
