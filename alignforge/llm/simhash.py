"""Operator 3: SimHash near-duplicates by a binary-trie self-join.

A text's fingerprint takes the majority of every bit over the XXH64 of its 4-word shingles. Distinct
fingerprints are joined with themselves by walking a binary trie in pairs of nodes: a pair splits into
its children's pairs, unlike branches cost one bit of the budget, and a pair over budget is dropped.

To spread the walk, the 64 bits are cut into blocks; two fingerprints within the budget agree on at
least blocks - budget of them, so for each such choice of blocks a trie with these bits on top is walked
below every common top path. Work is dealt by that path. A path with too many fingerprints is cut into
hashed chunks that are walked two at a time, so no task grows with a group. A walk returns each
fingerprint with one representative it is linked to, never all pairs, and skips node pairs that are
already linked.

Defined results: null, empty and blank texts have fingerprint zero and are linked like any other; fewer
than four words form one shingle; repeated rows get equal rows; a component without any doc_id has a
null component_id; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations
from math import ceil

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, lean_batches, min_label_components, row_hash

SHINGLE = 4
BUDGET = 4
SEED = 42
#: Fingerprints that one walk takes; larger groups are cut.
CHUNK = 50_000
#: Node pairs with at most so many element pairs are compared outright.
LEAF = 512


def fingerprint(text: str | None) -> int:
    """Unsigned 64-bit SimHash of the whole text."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: A-Z and the contract's white space only
    n = len(words)
    if not n:
        return 0
    joined = b" ".join(words)
    if n <= SHINGLE:
        return xxhash.xxh64_intdigest(joined, SEED)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, n) + 1) - 1
    starts, last = np.concatenate(([0], ends[: n - SHINGLE] + 1)), ends[SHINGLE - 1 :]
    del words
    digest, seed = xxhash.xxh64_intdigest, SEED
    ones, total = np.zeros(64, np.int64), n - SHINGLE + 1
    for lo in range(0, total, 1 << 14):
        part = slice(lo, lo + (1 << 14))
        h = np.fromiter((digest(joined[a:b], seed) for a, b in zip(starts[part].tolist(), last[part].tolist())), np.uint64)
        ones += np.unpackbits(h.view(np.uint8), bitorder="little").reshape(-1, 64).sum(axis=0, dtype=np.int64)
    return int((np.uint64(1) << np.flatnonzero(2 * ones > total).astype(np.uint64)).sum(dtype=np.uint64))


def fingerprints(docs: DataFrame, rows: bool = False) -> DataFrame:
    """doc_id and signed fp of every row, and row, where asked a hash of all its columns; one scan, no shuffle."""
    row = row_hash(docs) if rows else F.lit(None).cast("long")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fp = np.fromiter((fingerprint(t.as_py()) for t in batch.column("text")), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(fp.view(np.int64)), batch.column("row")], ["doc_id", "fp", "row"])

    return docs.select("doc_id", "text", row.alias("row")).mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, fp long, row long")


class Walk:
    """Self-join of a sorted array of distinct uint64 by a trie whose top bits must be equal."""

    def __init__(self, values: np.ndarray, top: int, budget: int = BUDGET):
        self.v, self.top, self.budget = np.sort(values), top, budget
        self.label = np.arange(len(values))
        self.ones: dict[int, np.ndarray] = {}
        self.pending: list[tuple[np.ndarray, np.ndarray]] = []
        self.waiting = 0

    def _ones(self, depth: int) -> np.ndarray:
        if depth not in self.ones:
            bits = (self.v >> np.uint64(63 - depth)) & np.uint64(1)
            self.ones[depth] = np.concatenate(([0], np.cumsum(bits.astype(np.int64))))
        return self.ones[depth]

    def _flush(self) -> None:
        if not self.waiting:
            return
        a, b = (np.concatenate(x) for x in zip(*self.pending))
        self.pending, self.waiting = [], 0
        while True:
            la, lb = self.label[a], self.label[b]
            open_ = la != lb
            if not open_.any():
                return
            a, b, la, lb = a[open_], b[open_], la[open_], lb[open_]
            to = np.arange(len(self.label))
            np.minimum.at(to, np.maximum(la, lb), np.minimum(la, lb))
            while (to != to[to]).any():
                to = to[to]
            self.label = to[self.label]

    def _leaves(self, lo1: np.ndarray, hi1: np.ndarray, lo2: np.ndarray, hi2: np.ndarray) -> None:
        n2 = hi2 - lo2
        size = (hi1 - lo1) * n2
        cut = np.cumsum(size)
        begin = 0
        while begin < len(size):  # at most about a million element pairs at a time
            end = max(begin + 1, int(np.searchsorted(cut, (cut[begin - 1] if begin else 0) + (1 << 20))))
            s = size[begin:end]
            of = np.repeat(np.arange(begin, end), s)
            k = np.arange(int(s.sum())) - np.repeat(np.cumsum(s) - s, s)
            i, j = lo1[of] + k // n2[of], lo2[of] + k % n2[of]
            near = (i < j) & (np.bitwise_count(self.v[i] ^ self.v[j]) <= self.budget)
            if near.any():
                self.pending.append((i[near], j[near]))
                self.waiting += int(near.sum())
                if self.waiting > 200_000:
                    self._flush()
            begin = end

    def _linked(self, lo1: np.ndarray, hi1: np.ndarray, lo2: np.ndarray, hi2: np.ndarray) -> np.ndarray:
        """Node pairs of many elements whose elements all have one label already."""
        big = np.flatnonzero((hi1 - lo1) * (hi2 - lo2) > 1 << 14)
        done = np.zeros(len(lo1), bool)
        if len(big):
            self._flush()
            for x in big:
                first = self.label[lo1[x]]
                done[x] = (self.label[lo1[x] : hi1[x]] == first).all() and (self.label[lo2[x] : hi2[x]] == first).all()
        return done

    def links(self) -> tuple[np.ndarray, np.ndarray]:
        """Positions that are linked to an earlier one, and that one."""
        if len(self.v) > 1:
            heads = self.v >> np.uint64(64 - self.top) if self.top else np.zeros(len(self.v), np.uint64)
            lo = np.flatnonzero(np.concatenate(([True], heads[1:] != heads[:-1])))
            hi = np.append(lo[1:], len(self.v))
            keep = hi - lo > 1
            lo, hi = lo[keep], hi[keep]
            stack = [(self.top, lo, hi, lo, hi, np.zeros(len(lo), np.int64))]
            while stack:
                depth, lo1, hi1, lo2, hi2, err = stack.pop()
                if len(lo1) > 1 << 17:
                    half = len(lo1) // 2
                    stack.append((depth, *(x[:half] for x in (lo1, hi1, lo2, hi2, err))))
                    stack.append((depth, *(x[half:] for x in (lo1, hi1, lo2, hi2, err))))
                    continue
                open_ = ~self._linked(lo1, hi1, lo2, hi2)
                small = ((hi1 - lo1) * (hi2 - lo2) <= LEAF) | (depth >= 64)
                if (x := open_ & small).any():
                    self._leaves(lo1[x], hi1[x], lo2[x], hi2[x])
                x = open_ & ~small
                if not x.any():
                    continue
                lo1, hi1, lo2, hi2, err = lo1[x], hi1[x], lo2[x], hi2[x], err[x]
                c = self._ones(depth)
                m1, m2 = hi1 - (c[hi1] - c[lo1]), hi2 - (c[hi2] - c[lo2])
                same = (lo1 == lo2) & (hi1 == hi2)
                kids = [(lo1, m1, m2, hi2, err + 1), tuple(y[~same] for y in (m1, hi1, lo2, m2, err + 1)), (lo1, m1, lo2, m2, err), (m1, hi1, m2, hi2, err)]
                for a1, b1, a2, b2, e in kids:  # like branches last, so they are walked first
                    live = (b1 > a1) & (b2 > a2) & (e <= self.budget) & ((a1 != a2) | (b1 != b2) | (b1 - a1 > 1))
                    if live.any():
                        stack.append((depth + 1, a1[live], b1[live], a2[live], b2[live], e[live]))
            self._flush()
        moved = np.flatnonzero(self.label != np.arange(len(self.v)))
        return self.v[moved], self.v[self.label[moved]]


def tables(n_blocks: int, budget: int = BUDGET) -> list[tuple[list[tuple[int, int]], int]]:
    """For each choice of blocks that must agree: bit spans (start, width from the top), these first, and their bits."""
    widths = [64 // n_blocks + (i < 64 % n_blocks) for i in range(n_blocks)]
    spans = [(sum(widths[:i]), widths[i]) for i in range(n_blocks)]
    out = []
    for own in combinations(range(n_blocks), n_blocks - budget):
        rest = [i for i in range(n_blocks) if i not in own]
        out.append(([spans[i] for i in (*own, *rest)], sum(widths[i] for i in own)))
    return out


def arranged(fp: np.ndarray, spans: list[tuple[int, int]]) -> np.ndarray:
    """Fingerprints with their bit spans in another order."""
    out = np.zeros(len(fp), np.uint64)
    for start, width in spans:
        out = (out << np.uint64(width)) | ((fp >> np.uint64(64 - start - width)) & np.uint64((1 << width) - 1))
    return out


def restored(values: np.ndarray, spans: list[tuple[int, int]]) -> np.ndarray:
    out, at = np.zeros(len(values), np.uint64), 64
    for start, width in spans:
        at -= width
        out |= ((values >> np.uint64(at)) & np.uint64((1 << width) - 1)) << np.uint64(64 - start - width)
    return out


def block_count(n: int, chunk: int = CHUNK, budget: int = BUDGET) -> int:
    """Fewest blocks whose common path leaves a chunk's worth of n evenly spread fingerprints."""
    for b in range(budget + 1, budget + 4):
        if n / 2 ** min(bits for _, bits in tables(b, budget)) <= chunk / 4:
            return b
    return budget + 4


def _path(fp: Column, spans: list[tuple[int, int]], top: int) -> Column:
    """The leading bits of arranged(), as a long."""
    out, used = F.lit(0).cast("long"), 0
    for start, width in spans:
        if used == top:
            break
        out = F.shiftleft(out, width).bitwiseOR(F.shiftrightunsigned(fp, 64 - start - width).bitwiseAND(F.lit((1 << width) - 1).cast("long")))
        used += width
    return out


def trie_links(distinct: DataFrame, scratch: Scratch, chunk: int = CHUNK, budget: int = BUDGET) -> DataFrame:
    """(u, v): fingerprints with a linked one, enough of them to connect every pair within the budget."""
    n = distinct.count()
    plan = tables(block_count(n, chunk, budget), budget)
    buckets = max(24, ceil(len(plan) * n / (chunk // 2)))
    keyed = distinct.select("fp", F.explode(F.array(*[F.struct(F.lit(t).alias("t"), _path(F.col("fp"), spans, top).alias("path")) for t, (spans, top) in enumerate(plan)])).alias("k")).select("fp", "k.t", "k.path")
    hot = scratch.save(keyed.groupBy("t", "path").agg(F.count("*").alias("n")).where(F.col("n") > chunk).withColumn("parts", F.ceil(F.col("n") / chunk).cast("int")), "hot")
    usual = F.concat_ws(":", F.lit("b"), F.pmod(F.xxhash64("t", "path"), F.lit(buckets)))
    if hot.isEmpty():
        dealt = keyed.select("fp", "t", usual.alias("task"))
    else:
        mine = F.pmod(F.xxhash64("fp"), F.col("parts"))
        pair = F.concat_ws(":", F.lit("h"), "t", "path", F.least("mine", "other"), F.greatest("mine", "other"))
        joined = keyed.join(hot.drop("n"), ["t", "path"], "left").withColumn("mine", mine)
        dealt = joined.withColumn("other", F.explode(F.when(F.col("parts").isNull(), F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.col("parts") - 1))))
        dealt = dealt.select("fp", "t", F.when(F.col("parts").isNull(), usual).otherwise(pair).alias("task"))

    def walk(pdf: pd.DataFrame) -> pd.DataFrame:
        us, vs = [], []
        fp, t = pdf["fp"].to_numpy().view(np.uint64), pdf["t"].to_numpy()
        for k in np.unique(t):
            spans, top = plan[k]
            u, v = Walk(np.unique(arranged(fp[t == k], spans)), top, budget).links()
            us.append(restored(u, spans))
            vs.append(restored(v, spans))
        return pd.DataFrame({"u": np.concatenate(us).view(np.int64), "v": np.concatenate(vs).view(np.int64)})

    return dealt.groupBy("task").applyInPandas(walk, "u long, v long")


def components(docs: DataFrame, chunk: int = CHUNK, rows: bool = False) -> DataFrame:
    """doc_id, fp, row (see fingerprints) and component_id of every row; texts go no further than the fingerprints."""
    scratch = Scratch(docs.sparkSession, "simhash")
    with lean_batches(docs.sparkSession):
        prints = scratch.save(fingerprints(docs, rows), "prints")
    distinct = scratch.save(prints.groupBy("fp").agg(F.min("doc_id").alias("low")), "distinct")
    roots = min_label_components(trie_links(distinct.select("fp"), scratch, chunk), scratch)
    rooted = scratch.save(distinct.join(roots, distinct["fp"] == roots["node"], "left").select("fp", "low", F.coalesce("root", "fp").alias("root")), "rooted")
    lows = rooted.groupBy("root").agg(F.min("low").alias("component_id"))
    named = rooted.join(lows, "root").select("fp", "component_id")
    return prints.join(named, "fp").select("doc_id", "fp", "row", "component_id")


def near_duplicates(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, fingerprint as 16 hex digits, component_id."""
    return components(docs).select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one_each(docs: DataFrame) -> DataFrame:
    """All columns of one document per component, that with the smallest doc_id; of rows that repeat it, the one with the smallest row hash.

    Everything is decided on (doc_id, row hash). Texts move once, to a hash join that sorts none of them; only
    doc_ids that several rows carry take a second way. Rows without a doc_id can't be told apart by it: they all stay.
    """
    scratch = Scratch(docs.sparkSession, "keep")
    chosen = components(docs, rows=True).where("doc_id = component_id").groupBy("doc_id").agg(F.min("row").alias("low"), F.count("*").alias("n"))
    chosen = scratch.save(chosen.withColumnRenamed("doc_id", "kept"), "chosen")
    once, again = (chosen.where(c).hint("shuffle_hash") for c in ("n = 1", "n > 1"))
    out = docs.join(once, docs["doc_id"] == once["kept"], "left_semi").unionByName(docs.where(docs["doc_id"].isNull()))
    if again.isEmpty():
        return out
    # equal hashes are equal rows, so it does not matter which of them a partial aggregate keeps
    repeated = docs.join(again, (docs["doc_id"] == again["kept"]) & (row_hash(docs) == again["low"]), "left_semi")
    return out.unionByName(repeated.dropDuplicates(["doc_id"]))
