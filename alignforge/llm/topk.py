"""Operator 10: exact top-k inner-product search by MaxScore.

Dimensions are query terms. Within a shard every term has a score bound. Terms whose bounds together stay
below the k-th best score are non-essential; the others are traversed for all vectors, the rest is probed
only for vectors whose partial score plus the bounds left can still reach it. Shards are merged at the end.

Defined results: a null vector, or one with a null or non-finite component, takes no part, nor does a
row without vec_id; missing components of a shorter vector count as 0; an empty vector scores 0 with
every other; rows that share a query's vec_id are its own; repeated candidate rows each count; ties go
to the smaller vec_id; fewer than k candidates are all returned. Finite components of any size take part
with exact whole numbers; a score beyond a long stops at its end, and is ranked as such. Extra columns are
ignored.
"""

from __future__ import annotations

from math import ceil, floor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

K = 10
#: Vectors of a shard and queries of a block; a task holds one of each.
SHARD = 10_000
BLOCK = 2_000
#: Share of the terms, widest first, whose partial scores choose the vectors that set the first threshold; later terms go in steps of PROBE.
LEAD = 0.25
PROBE = 8
#: Components below this stay finite when scaled; a double then holds their floor. Sums beyond 2^52 are taken in whole numbers.
FINITE = 1e300
LOW, HIGH = -(2**63), 2**63 - 1


def usable(vectors: DataFrame) -> DataFrame:
    """vec_id and embedding of the rows that take part."""
    x = F.col("embedding")
    whole = F.col("vec_id").isNotNull() & x.isNotNull() & F.forall(x, lambda e: e.isNotNull() & ~F.isnan(e) & (F.abs(e) != float("inf")))
    return vectors.where(F.coalesce(whole, F.lit(False))).select("vec_id", "embedding")


def _dense(col: pa.Array, width: int) -> np.ndarray:
    """floor(1024 x) of a list column as a matrix, short rows filled with 0: doubles, or whole numbers of any size where one is beyond doubles."""
    n = len(col)
    flat, lens = col.flatten().to_numpy(zero_copy_only=False).astype(np.float64), col.value_lengths().to_numpy(zero_copy_only=False)
    if (np.abs(flat) < FINITE).all():
        flat = np.floor(flat * 1024)
    else:
        flat = np.array([floor(x * 1024) if abs(x) < FINITE else int(x) * 1024 for x in flat.tolist()], object)
    if n and (lens == width).all():
        return flat.reshape(n, width)
    out = np.zeros((n, width), flat.dtype)
    out[np.repeat(np.arange(n), lens), np.arange(len(flat)) - np.repeat(np.cumsum(lens) - lens, lens)] = flat
    return out


def _top(ids: np.ndarray, score: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    best = np.lexsort((ids, -score))[:k]
    return ids[best], score[best]


def largest(q: np.ndarray, lists: np.ndarray, ids: np.ndarray, own: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, scores) of the k best by whole numbers of any size; scores stop at the ends of a long before they are ranked."""
    others = np.flatnonzero(ids != own)
    score = [min(max(sum((a * b for a, b in zip(q, lists[:, o])), 0), LOW), HIGH) for o in others]
    best = sorted(range(len(others)), key=lambda x: (-score[x], ids[others[x]]))[:k]
    return ids[others[best]] if best else ids[:0], np.array([score[x] for x in best], np.int64)


def maxscore(q: np.ndarray, lists: np.ndarray, high: np.ndarray, low: np.ndarray, ids: np.ndarray, own: int, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, scores) of the k best; lists holds one row of values per term.

    The threshold is the k-th best exact score among vectors that lead on the widest terms. Terms whose upper
    bounds together stay below it are non-essential: no vector reaches the threshold by them alone.
    """
    others = np.flatnonzero(ids != own)
    if not len(others):
        return ids[:0], np.zeros(0, lists.dtype)
    upper, lower = np.maximum(q * high, q * low), np.minimum(q * high, q * low)
    order = np.argsort(lower - upper, kind="stable")
    lead = ceil(LEAD * len(order))
    if len(others) <= 4 * k or lead == len(order):
        return _top(ids[others], (q @ lists)[others], k)
    score = q[order[:lead]] @ lists[order[:lead]]
    seed = others[np.argpartition(score[others], len(others) - 4 * k)[-4 * k :]]
    exact = score[seed] + q[order[lead:]] @ lists[np.ix_(order[lead:], seed)]
    least = np.partition(exact, len(exact) - k)[-k]
    left = np.append(np.cumsum(upper[order][::-1])[::-1], 0.0)  # upper bound of all terms from a place on
    essential = max(lead, int(np.argmax(left < least)) if (left < least).any() else len(order))
    score = score + q[order[lead:essential]] @ lists[order[lead:essential]]
    alive = others[score[others] + left[essential] >= least]
    part = score[alive]
    for at in range(essential, len(order), PROBE):
        terms = order[at : at + PROBE]
        part = part + q[terms] @ lists[np.ix_(terms, alive)]
        near = part + left[min(at + PROBE, len(order))] >= least
        alive, part = alive[near], part[near]
    return _top(ids[alive], part, k)


def top_k(vectors: DataFrame, every: int = 100, k: int = K, shard: int = SHARD, block: int = BLOCK) -> DataFrame:
    """query_id, rank, vec_id, score of the k best candidates of each row whose vec_id is divisible by every.

    Rows meet queries in a grid of shards and blocks, each cell one bounded task; a cell returns k rows
    a query, cut again by a partial limit before they are shuffled to the final ranking.
    """
    rows = usable(vectors)
    n, width = rows.agg(F.count("*"), F.max(F.size("embedding"))).first()
    queries = rows.where(F.col("vec_id") % every == 0)
    shards, blocks = max(1, ceil((n or 0) / shard)), max(1, ceil(queries.count() / block))
    width = width or 0
    salt = F.pmod(F.xxhash64("vec_id", "embedding"), F.lit(shards)).cast("int")
    turn = F.pmod(F.xxhash64(F.lit("q"), "vec_id", "embedding"), F.lit(blocks)).cast("int")
    pool = rows.select(F.lit(False).alias("is_query"), "vec_id", "embedding", salt.alias("s"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("b"))
    asked = queries.select(F.lit(True).alias("is_query"), "vec_id", "embedding", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("s"), turn.alias("b"))

    def cell(t: pa.Table) -> pa.Table:
        flag = t.column("is_query").to_numpy()
        ids, v = t.column("vec_id").to_numpy(), _dense(t.column("embedding").combine_chunks(), width)
        q_ids, q, c_ids, c = ids[flag], v[flag], ids[~flag], v[~flag]
        out_q, out_r, out_v, out_s = [], [], [], []
        if len(q) and len(c):
            lists = np.ascontiguousarray(c.T)
            small = q.dtype != object and c.dtype != object and float(np.abs(q).max(initial=0)) * float(np.abs(c).max(initial=0)) * max(1, width) < 2.0**52
            if small:  # every partial sum is a whole number that doubles hold
                high, low = (lists.max(axis=1), lists.min(axis=1)) if width else (np.zeros(0), np.zeros(0))
                search = lambda one, name: maxscore(one, lists, high, low, c_ids, name, k)
            else:
                q, whole = ([[int(x) for x in row] for row in m] for m in (q, lists))
                whole = np.array(whole, object).reshape(width, len(c_ids))
                search = lambda one, name: largest(one, whole, c_ids, name, k)
            for one, name in zip(q, q_ids):
                found, score = search(one, name)
                out_q.append(np.full(len(found), name)), out_v.append(found), out_s.append(score.astype(np.int64))
        join = lambda x: np.concatenate(x).astype(np.int64) if x else np.zeros(0, np.int64)
        return pa.table({"query_id": join(out_q), "vec_id": join(out_v), "score": join(out_s)})

    found = pool.unionByName(asked).groupBy("s", "b").applyInArrow(cell, "query_id long, vec_id long, score long")
    order = W.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
