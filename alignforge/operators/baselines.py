"""Comparators: rules on whole values, on conditions, on reference data, and on unaligned positions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .claims import measures, unpivot_counts


def fd_measures(df: DataFrame, lhs: str, rhs: str) -> DataFrame:
    """The four measures of the dependency of one whole column on another."""
    claims = df.select(F.col(lhs).cast("string").alias("key"), F.col(rhs).cast("string").alias("value"), F.lit(1).cast("long").alias("n")).where("key is not null and value is not null")
    return measures(claims, [])


def cfd_measures(df: DataFrame, cond: str, lhs: str, rhs: str) -> DataFrame:
    """The same under each constant of a condition column."""
    claims = df.select(F.col(cond).cast("string").alias("condition"), F.col(lhs).cast("string").alias("key"), F.col(rhs).cast("string").alias("value"), F.lit(1).cast("long").alias("n"))
    return measures(claims.where("condition is not null and key is not null and value is not null"), ["condition"])


def lookup_fill(df: DataFrame, ref: DataFrame, on: str, attr: str) -> DataFrame:
    """Missing values taken from reference data with a unique key; adds <attr>_filled."""
    unique = ref.where(F.col(on).isNotNull()).groupBy(F.col(on).alias("__on")).agg(F.min(attr).alias("__low"), F.max(attr).alias("__high")).where("__low = __high")
    return df.join(unique, df[on] == F.col("__on"), "left").withColumn(f"{attr}_filled", F.coalesce(F.col(attr), F.col("__low"))).drop("__on", "__low", "__high")


def raw_position_measures(df: DataFrame, code: str, attrs: list[str], from_end: bool = False) -> DataFrame:
    """(pos, attr, measures): the i-th character, counted from the front or the back, without alignment."""
    counts = unpivot_counts(df, code, attrs)
    text = F.reverse("code") if from_end else F.col("code")
    claims = counts.select("attr", "value", "n", F.posexplode(F.split(text, "")).alias("pos", "key")).withColumn("pos", F.col("pos") + 1)
    return measures(claims, ["pos", "attr"])
