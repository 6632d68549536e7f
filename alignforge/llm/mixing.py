"""Operator 6, native: mixing sources to target weights by a low-discrepancy schedule.

The budget is cut into equal slots. Slot i takes the golden-ratio point frac(offset + i * phi), which
cumulative target shares map to a source; the slots of a source are ranked, and slot rank k takes the
k-th equal-token block of that source's shuffled, repeated token stream. Any prefix of the schedule is
within a few slots of the target mix. Every row is cut at the block borders of each pass of the stream and
joined with the ranked blocks; what it gives is the sum of the pieces that found one. Blocks grow with the
corpus, so a source whose slots miss its target by more than TOLERANCE has its last block cut, or partial
blocks added at the schedule's end: it gives its target's words exactly.

Rows that agree in doc_id, source and size are counted before they are shuffled and stand side by side in the
stream, so one that makes up a third of the table is no task's burden.

Defined results: null or blank texts have size 0 and are taken 0 times, and copied where their place falls in
a given block; a null source is a source of its own, ordered last; no rows give no rows; repeated rows are each
placed in the stream; extra columns are ignored. Reruns agree, as the shuffle is an md5 order and the points
depend on the slot number only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Scratch, row_hash, word_count

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MAX_EPOCHS = 2
N_SLOTS = 1 << 18
GOLDEN = 0.6180339887498949
CELLS = 1024
#: Share of a source's target that whole blocks may miss; beyond it the last block is cut or added in part.
TOLERANCE = 0.01
#: Equal rows that are laid out at once.
RUN = 4096


def measured(docs: DataFrame) -> DataFrame:
    """doc_id, source, size, the md5 that shuffles, and n, the rows that agree in these; texts go no further."""
    key = F.md5(F.concat_ws("|", F.lit("mix"), F.col("doc_id").cast("string")).cast("binary"))
    return docs.select("doc_id", "source", word_count(F.col("text")).alias("size"), key.alias("key")).groupBy("doc_id", "source", "size", "key").agg(F.count("*").alias("n"))


def targets(rows: DataFrame) -> DataFrame:
    """(source, source_size, weight, target, budget), one row a source.

    The reshared excess has a closed form: a source is held at its cap if the level (budget left over by
    the capped ones, by weight of the rest) exceeds its cap per weight; sources are taken by cap per weight.
    """
    per = rows.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size"))
    named = W.orderBy(F.col("source").asc_nulls_last())
    one = per.withColumn("turn", (F.row_number().over(named) - 1) % len(WEIGHTS))
    pick = F.when(F.col("turn") == 0, F.lit(WEIGHTS[0])).when(F.col("turn") == 1, F.lit(WEIGHTS[1])).otherwise(F.lit(WEIGHTS[2]))
    one = one.withColumn("weight", pick.cast("double")).withColumn("cap", (F.col("source_size") * MAX_EPOCHS).cast("double")).withColumn("fill", F.col("cap") / F.col("weight"))
    by_fill = W.orderBy("fill", F.col("source").asc_nulls_last())
    everything = W.partitionBy()
    one = (
        one.withColumn("budget", F.sum("source_size").over(everything) * F.lit(SHARE))
        .withColumn("capped_before", F.coalesce(F.sum("cap").over(by_fill.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("weight_left", F.sum("weight").over(by_fill.rowsBetween(W.currentRow, W.unboundedFollowing)))
        .withColumn("level", (F.col("budget") - F.col("capped_before")) / F.col("weight_left"))
        .withColumn("free", F.when(F.col("level") <= F.col("fill"), F.col("level")))
        .withColumn("water", F.first("free", ignorenulls=True).over(by_fill.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)))
    )
    aim = F.least("cap", F.coalesce(F.col("water"), F.lit(float("inf"))) * F.col("weight"))
    return one.select("source", "source_size", "weight", F.round(aim, 6).alias("target"), "budget")


def schedule(goals: DataFrame, n_slots: int = N_SLOTS) -> DataFrame:
    """(slot, source, block_tokens): one row a slot, in the order in which the mix is read.

    Cumulative shares are cut at CELLS grid cells, so mapping a point to its source is an equi join on
    the cell with a range filter.
    """
    spark = goals.sparkSession
    upto = W.orderBy(F.col("source").asc_nulls_last())
    spans = goals.where("target > 0").withColumn("hi", F.sum("target").over(upto.rowsBetween(W.unboundedPreceding, W.currentRow)))
    spans = spans.withColumn("all", F.sum("target").over(W.partitionBy())).withColumn("lo", F.coalesce(F.lag("hi").over(upto), F.lit(0.0)) / F.col("all")).withColumn("hi", F.when(F.lead("hi").over(upto).isNull(), F.lit(2.0)).otherwise(F.col("hi") / F.col("all")))
    spans = spans.select(
        "source", "lo", "hi", F.greatest(F.lit(1), F.ceil(F.col("budget") / n_slots)).cast("long").alias("block_tokens"), "budget",
        F.explode(F.sequence(F.floor(F.col("lo") * CELLS), F.least(F.floor(F.col("hi") * CELLS), F.lit(CELLS - 1)))).alias("cell"),
    )
    raw = F.col("id") * F.lit(GOLDEN) + F.lit(0.5)
    points = spark.range(n_slots).select(F.col("id").alias("slot"), (raw - F.floor(raw)).alias("u")).withColumn("cell", F.floor(F.col("u") * CELLS))
    return points.join(spans, "cell").where("u >= lo and u < hi and slot < ceil(budget / block_tokens)").select("slot", "source", "block_tokens")


def ranked(slots: DataFrame) -> DataFrame:
    """Adds block, the rank of the slot among its source's slots; bounded by the number of slots."""
    return slots.withColumn("block", F.row_number().over(W.partitionBy("source").orderBy("slot")) - 1)


def blocks_given(goals: DataFrame, n_slots: int = N_SLOTS) -> DataFrame:
    """(b_source, block, slot, tokens): every block that the schedule takes, with the words it gives.

    At most n_slots rows and one for each block's worth of a target that the slots missed.
    """
    taken = ranked(schedule(goals, n_slots))
    per = taken.groupBy(F.col("source").alias("c_source")).agg(F.count("*").alias("blocks"))
    own = goals.join(per, F.col("source").eqNullSafe(F.col("c_source")), "left")
    size, count = F.greatest(F.lit(1), F.ceil(F.col("budget") / n_slots)).cast("long"), F.coalesce("blocks", F.lit(0).cast("long"))
    whole = F.when(F.abs(count * size - F.col("target")) > F.col("target") * TOLERANCE, F.round("target").cast("long")).otherwise(count * size)
    own = own.select(F.col("source").alias("b_source"), size.alias("of"), count.alias("blocks"), F.least(whole, F.col("source_size") * MAX_EPOCHS).alias("given"))
    planned = taken.select(F.col("source").alias("t_source"), F.col("block").cast("long").alias("block"), "slot")
    first = own.join(planned, F.col("b_source").eqNullSafe(F.col("t_source"))).select("b_source", "of", "given", "block", "slot")
    short = own.where("given > blocks * of").select("b_source", "of", "given", F.explode(F.sequence(F.col("blocks"), F.expr("(given - 1) div of"))).alias("block"))
    added = short.select("b_source", "of", "given", "block", F.lit(n_slots).cast("long").alias("slot"))
    return first.unionByName(added).withColumn("tokens", F.least(F.col("of"), F.col("given") - F.col("block") * F.col("of"))).where("tokens > 0").select("b_source", "block", "slot", "tokens")


def streamed(rows: DataFrame, goals: DataFrame, n_slots: int = N_SLOTS) -> DataFrame:
    """Every row with start, its first token in the shuffled stream of its source, and the source's figures.

    Sums per 4096 md5 buckets come first; a window then runs within one bucket of one source only. The
    goals join the sums, not the rows, so no task gets a whole source. Equal rows are laid out in runs.
    """
    put = rows.withColumn("bucket", F.substring("key", 1, 3))
    words = F.col("size") * F.col("n")
    ahead = W.partitionBy("source").orderBy("bucket").rowsBetween(W.unboundedPreceding, -1)
    offsets = put.groupBy("source", "bucket").agg(F.sum(words).alias("words")).select(F.col("source").alias("o_source"), F.col("bucket").alias("o_bucket"), F.coalesce(F.sum("words").over(ahead), F.lit(0)).alias("offset"))
    figures = goals.select(F.col("source").alias("g_source"), "source_size", "target", F.greatest(F.lit(1), F.ceil(F.col("budget") / n_slots)).cast("long").alias("block_tokens"))
    offsets = offsets.join(figures, F.col("o_source").eqNullSafe(F.col("g_source"))).drop("g_source")
    inner = W.partitionBy("source", "bucket").orderBy("key", "doc_id", "size").rowsBetween(W.unboundedPreceding, -1)
    laid = put.withColumn("inside", F.coalesce(F.sum(words).over(inner), F.lit(0))).join(offsets, (F.col("bucket") == F.col("o_bucket")) & F.col("source").eqNullSafe(F.col("o_source")))
    runs = laid.withColumn("run", F.explode(F.sequence(F.lit(0).cast("long"), F.expr(f"(n - 1) div {RUN}"))))
    # runs are dealt out anew before they unfold; all that follows on a row stays where it is
    runs = runs.repartition("doc_id", "source", "size", "run")
    each = runs.withColumn("k", F.explode(F.sequence(F.col("run") * RUN, F.least(F.col("n"), (F.col("run") + 1) * RUN) - 1)))
    return each.select("doc_id", "source", "size", "run", "k", "source_size", "target", "block_tokens", (F.col("offset") + F.col("inside") + F.col("k") * F.col("size")).alias("start"))


def mix(docs: DataFrame, n_slots: int = N_SLOTS) -> DataFrame:
    """Per row: size, source_size, target, taken (words, repeats counted), copies (whole documents), and slot, the first that reads of it.

    A pass of a row is cut at its source's block borders and joined with the blocks given, of which there are
    about n_slots: they are broadcast. A row is copied in each pass whose middle word falls in a given block.
    """
    scratch = Scratch(docs.sparkSession, "mix")
    rows = scratch.save(measured(docs), "rows")
    goals = scratch.save(targets(rows), "goals")
    given = scratch.save(blocks_given(goals, n_slots), "blocks")
    passed = streamed(rows, goals, n_slots).withColumn("epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(MAX_EPOCHS - 1).cast("long"))))
    passed = passed.withColumn("at", F.col("start") + F.col("source_size") * F.col("epoch")).withColumn("end", F.col("at") + F.col("size"))
    pieces = passed.withColumn("piece", F.explode(F.sequence(F.expr("at div block_tokens"), F.expr("(at + greatest(size, 1) - 1) div block_tokens"))))
    found = pieces.join(F.broadcast(given), (F.col("piece") == F.col("block")) & F.col("source").eqNullSafe(F.col("b_source")), "left")
    begin = F.col("block") * F.col("block_tokens")
    stop, middle = begin + F.col("tokens"), F.expr("at + size div 2")
    words = F.when(F.col("block").isNotNull(), F.greatest(F.lit(0).cast("long"), F.least("end", stop) - F.greatest("at", begin)))
    per = found.groupBy("doc_id", "source", "size", "run", "k").agg(
        F.first("source_size").alias("source_size"), F.first("target").alias("target"), F.coalesce(F.sum(words), F.lit(0)).cast("long").alias("taken"),
        F.count_if((middle >= begin) & (middle < stop)).cast("int").alias("copies"), F.min(F.when(F.col("at") < stop, F.col("slot"))).alias("slot"),
    )
    return per.select("doc_id", "source", "size", "source_size", "target", "taken", "copies", "slot")


def mix_documents(docs: DataFrame, n_slots: int = N_SLOTS) -> DataFrame:
    """The documents themselves, each as often as mix() says, all columns kept.

    Rows with equal doc_id, source and size are alike to the mix: what it gives to all of them together is
    dealt over them by row hash, so their sum holds.
    """
    plan = mix(docs, n_slots).groupBy(F.col("doc_id").alias("__mix_id"), F.col("source").alias("__mix_source"), F.col("size").alias("__mix_size")).agg(F.sum("copies").alias("__mix_copies"), F.count("*").alias("__mix_rows"))
    plan = Scratch(docs.sparkSession, "plan").save(plan.where("__mix_copies > 0"), "plan")

    row = F.struct(*[docs[f"`{c}`"] for c in docs.columns]).alias("row")

    def joined(part: DataFrame) -> DataFrame:
        same = docs["doc_id"].eqNullSafe(part["__mix_id"]) & docs["source"].eqNullSafe(part["__mix_source"]) & (word_count(docs["text"]) == part["__mix_size"])
        return docs.join(part.hint("shuffle_hash"), same)

    def unfolded(rows: DataFrame) -> DataFrame:  # (row, copies)
        return rows.where("copies > 0").select("row", F.explode(F.sequence(F.lit(1).cast("long"), "copies")).alias("turn")).select("row.*")

    once, several = plan.where("__mix_rows = 1"), plan.where("__mix_rows > 1")
    out = unfolded(joined(once).select(row, once["__mix_copies"].alias("copies")))
    if several.isEmpty():
        return out
    at = F.row_number().over(W.partitionBy(several["__mix_id"], several["__mix_source"], several["__mix_size"]).orderBy(row_hash(docs)))
    rest = several["__mix_copies"] % several["__mix_rows"]
    share = ((several["__mix_copies"] - rest) / several["__mix_rows"]).cast("long") + (at <= rest).cast("long")
    return out.unionByName(unfolded(joined(several).select(row, share.alias("copies"))))
