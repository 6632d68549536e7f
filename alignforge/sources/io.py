"""Readers of code lists and the rule catalog's sinks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_codes(spark: SparkSession, path: str, fmt: str = "parquet", code: str = "code", schema: str | None = None) -> DataFrame:
    """Codes from Parquet, CSV with a header, JSON lines or plain text (one code a line)."""
    if fmt == "text":
        return spark.read.text(path).select(F.col("value").alias(code))
    reader = spark.read.schema(schema) if schema else spark.read
    return reader.option("header", True).format(fmt).load(path)


def write_catalog(rules: DataFrame, path: str, version: int) -> None:
    """Adds a version of the rules, partitioned by attribute."""
    rules.withColumn("version", F.lit(version)).write.mode("append").partitionBy("attr").parquet(path)


def read_catalog(spark: SparkSession, path: str, version: int | None = None) -> DataFrame:
    """The rules of one version, by default the latest."""
    rules = spark.read.parquet(path)
    want = version if version is not None else rules.agg(F.max("version")).first()[0]
    return rules.where(F.col("version") == want).drop("version")


def write_members(members: DataFrame, table: str, buckets: int = 64) -> None:
    """Members as a table bucketed by code, so joins on the code need no shuffle of it."""
    members.write.mode("overwrite").bucketBy(buckets, "code").sortBy("code").saveAsTable(table)
