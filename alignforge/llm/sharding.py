"""Operator 5, native: fixed virtual slots with a versioned slot-to-shard map.

Rows hash into a fixed number of virtual slots, bytes are added up per slot, and a map of that fixed
size says which shard owns which slot. The first version of the map places slots, largest first, on
the least loaded shard; later versions are edits of the one before, which move only the slots that a
rebalancing needs. Only the map ever changes, never a row's virtual slot.

Rows that agree in doc_id, crc and size are counted before they are shuffled, and placed in runs of RUN: each
run hashes on its own, so a row that makes up a third of the table is spread over all slots.

Defined results: a null or empty text has size 1 and crc 0; a null doc_id hashes like any other value;
an empty table gives no rows; repeated rows are all placed; extra columns are ignored. Ties of load go
to the smaller shard, ties of slot bytes to the smaller slot.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Scratch

N_SLOTS = 4096
#: Equal rows that stay together in one virtual slot.
RUN = 64


def sized(docs: DataFrame, n_slots: int = N_SLOTS) -> DataFrame:
    """doc_id, size, text_crc32, copies, run and virtual slot: one row per run of at most RUN equal rows; text goes no further."""
    body = F.encode(F.coalesce(F.col("text"), F.lit("")), "UTF-8")
    rows = docs.select("doc_id", (F.octet_length(body) + 1).cast("long").alias("size"), F.crc32(body).alias("text_crc32"))
    same = rows.groupBy("doc_id", "text_crc32", "size").agg(F.count("*").alias("n"))
    upto = lambda n: F.sequence(F.lit(0).cast("long"), n)
    # two steps, so that no array grows with a group
    stride = RUN << 16
    far = same.withColumn("far", F.explode(upto(F.expr(f"(n - 1) div {stride}"))))
    runs = far.withColumn("near", F.explode(upto(F.expr(f"(least(n - far * {stride}, {stride}) - 1) div {RUN}")))).withColumn("run", F.col("far") * (1 << 16) + F.col("near"))
    salted = F.when(F.col("run") == 0, F.xxhash64("doc_id", "text_crc32", "size")).otherwise(F.xxhash64("doc_id", "text_crc32", "size", "run"))
    return runs.select("doc_id", "size", "text_crc32", F.least(F.lit(RUN).cast("long"), F.col("n") - F.col("run") * RUN).alias("copies"), "run", F.pmod(salted, F.lit(n_slots)).cast("int").alias("virtual_slot"))


def slot_bytes(rows: DataFrame) -> DataFrame:
    """Bytes and rows per virtual slot: n_slots rows at most, summed on the map side first."""
    return rows.groupBy("virtual_slot").agg(F.sum(F.col("size") * F.col("copies")).alias("bytes"), F.sum("copies").alias("rows"))


def _least(loads: Column) -> Column:
    return F.array_position(loads, F.array_min(loads)).cast("int") - 1


def _add(loads: Column, at: Column, amount: Column) -> Column:
    return F.transform(loads, lambda x, i: F.when(i == at, x + amount).otherwise(x))


def first_map(slots: DataFrame, n_shards: int, version: int = 1) -> DataFrame:
    """(version, virtual_slot, shard, bytes): largest slot first, each to the least loaded shard.

    One row folds the whole list; its length is bounded by the number of virtual slots.
    """
    ordered = slots.agg(F.array_sort(F.collect_list(F.struct((-F.col("bytes")).alias("neg"), F.col("virtual_slot").alias("vs")))).alias("q"))
    start = F.struct(F.array_repeat(F.lit(0).cast("long"), n_shards).alias("loads"), F.array().cast("array<int>").alias("owner"))
    folded = ordered.select(
        "q",
        F.aggregate(
            "q", start,
            lambda s, x: F.struct(_add(s["loads"], _least(s["loads"]), -x["neg"]).alias("loads"), F.concat(s["owner"], F.array(_least(s["loads"]))).alias("owner")),
            lambda s: s["owner"],
        ).alias("owner"),
    )
    return folded.select(F.explode(F.arrays_zip("q", "owner")).alias("x")).select(
        F.lit(version).alias("version"), F.col("x.q.vs").alias("virtual_slot"), F.col("x.owner").alias("shard"), (-F.col("x.q.neg")).alias("bytes")
    )


def edit_map(old: DataFrame, slots: DataFrame, n_shards: int, tolerance: float = 0.01) -> DataFrame:
    """The next version: new byte counts, possibly more shards, as few slots moved as it takes.

    Slots are visited largest first; one moves only if its shard is above the mean by more than the
    tolerance, stays at it without the slot, and the least loaded shard does not exceed it with the slot. Untouched slots keep their shard;
    slots that the old map lacks go to the least loaded shard.
    """
    joined = slots.join(old.select("virtual_slot", "shard"), "virtual_slot", "left")
    top = old.agg(F.max("version").alias("v"))
    one = joined.agg(
        F.array_sort(F.collect_list(F.struct((-F.col("bytes")).alias("neg"), F.col("virtual_slot").alias("vs"), F.col("shard").alias("own")))).alias("q"),
        (F.sum("bytes") / n_shards).alias("mean"),
    )
    loads = F.aggregate(
        "q", F.array_repeat(F.lit(0).cast("long"), n_shards), lambda s, x: F.transform(s, lambda y, i: F.when(i == x["own"], y - x["neg"]).otherwise(y))
    )

    def step(s: Column, x: Column) -> Column:
        least, size = _least(s["loads"]), -x["neg"]
        over = F.element_at(s["loads"], F.coalesce(x["own"], F.lit(0)) + 1) > F.col("mean") * (1 + tolerance)
        fits = (F.array_min(s["loads"]) < F.col("mean") * (1 - tolerance)) & (F.array_min(s["loads"]) + size <= F.col("mean") * (1 + tolerance))
        spare = F.element_at(s["loads"], F.coalesce(x["own"], F.lit(0)) + 1) - size >= F.col("mean") * (1 - tolerance)
        to = F.when(x["own"].isNull() | (over & fits & spare), least).otherwise(x["own"])
        freed = F.when(x["own"].isNull(), s["loads"]).otherwise(_add(s["loads"], x["own"], -size))
        return F.struct(_add(freed, to, size).alias("loads"), F.concat(s["owner"], F.array(to)).alias("owner"))

    folded = one.select("q", F.aggregate("q", F.struct(loads.alias("loads"), F.array().cast("array<int>").alias("owner")), step, lambda s: s["owner"]).alias("owner"), "mean")
    return folded.select(F.explode(F.arrays_zip("q", "owner")).alias("x")).crossJoin(F.broadcast(top)).select(
        (F.col("v") + 1).alias("version"), F.col("x.q.vs").alias("virtual_slot"), F.col("x.owner").alias("shard"), (-F.col("x.q.neg")).alias("bytes")
    )  # top is one row


def save_map(slot_map: DataFrame, path: str) -> None:
    """Adds a version to the stored map; older versions stay readable."""
    slot_map.write.mode("append").partitionBy("version").parquet(path)


def load_map(spark: SparkSession, path: str, version: int | None = None) -> DataFrame:
    """A stored version, by default the latest."""
    all_ = spark.read.parquet(path)
    want = F.lit(version) if version is not None else all_.agg(F.max("version")).first()[0]
    return all_.where(F.col("version") == want).select("version", "virtual_slot", "shard", "bytes")


def shard_rows(docs: DataFrame, n_shards: int = 8, n_slots: int = N_SLOTS, slot_map: DataFrame | None = None) -> DataFrame:
    """Every row with its virtual slot, shard and gapless position within the shard.

    The map (n_slots rows at most) is broadcast. A row's position is its rank within the virtual slot
    plus the rows of the shard's earlier slots, so no window spans a whole shard. Texts are read once.
    """
    rows = Scratch(docs.sparkSession, "shards").save(sized(docs, n_slots), "sized")
    slots = slot_bytes(rows)
    owner = (slot_map if slot_map is not None else first_map(slots, n_shards)).select("virtual_slot", "shard")
    w = W.partitionBy("shard").orderBy("virtual_slot").rowsBetween(W.unboundedPreceding, -1)
    placed = slots.join(F.broadcast(owner), "virtual_slot").select("virtual_slot", "shard", F.coalesce(F.sum("rows").over(w), F.lit(0)).alias("before"))
    ahead = W.partitionBy("virtual_slot").orderBy("doc_id", "text_crc32", "size", "run").rowsBetween(W.unboundedPreceding, -1)
    each = rows.withColumn("rank", F.coalesce(F.sum("copies").over(ahead), F.lit(0))).join(F.broadcast(placed), "virtual_slot")
    each = each.withColumn("k", F.explode(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1)))  # RUN at most
    return each.select(
        "doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard",
        (F.col("before") + F.col("rank") + F.col("k")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"), "virtual_slot",
    )
