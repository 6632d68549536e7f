"""Operator 7: benchmark decontamination by greedy string tiling.

Documents and benchmark items are compared as lower-cased letter and digit words. Rolling Karp-Rabin
hashes of MIN_TILE words join a document with the items as seeds; seeds on one diagonal form maximal
matches; the longest match becomes a tile, its words are marked, and what marking leaves of the others
competes on. An item whose words are covered by tiles to at least the threshold is contained, in any
order of its passages. Where a text repeats its words so often that its seeds would fill memory, the
longest free match is searched by window hashes of falling length instead; both ways give the same tiles.

Defined results: null, empty and wordless texts match nothing; an item of fewer than MIN_TILE words is
contained where all its words stand in a row; repeated items and documents are each reported; ties of
length go to the earlier place in the document, then in the item; extra columns are ignored; item_id
keeps its type. Hashes only propose: words are always compared.
"""

from __future__ import annotations

import heapq
import re
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from .common import Scratch, lean_batches

MIN_TILE = 5
COVERAGE = 0.5
#: Seed pairs of a document that are laid out at once; texts with more are tiled by falling window lengths.
MAX_SEEDS = 500_000
#: Bytes of benchmark text that one pass ships to the executors; a larger benchmark takes several passes.
PASS_BYTES = 64 << 20
BASE = np.uint64(0x9E3779B97F4A7C15)

_word = re.compile(r"[^\W_]+")


def words(text: str | None) -> list[str]:
    return _word.findall(text.lower()) if text else []


def rolling(ids: np.ndarray, width: int) -> np.ndarray:
    """Karp-Rabin hashes (mod 2^64) of all windows."""
    n = len(ids) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    x = ids.astype(np.uint64)
    for k in range(width):
        out = out * BASE + x[k : k + n]
    return out


class Seeds:
    """The benchmark's words, numbered from 1, and its seed hashes in order; shorter items apart, by their length."""

    def __init__(self, items: list[tuple[object, str | None]], width: int = MIN_TILE):
        self.width, self.keys, self.vocab, self.own = width, [], {}, []
        self.short: dict[int, dict[bytes, list[object]]] = {}
        for key, text in items:
            got = words(text)
            ids = np.array([self.vocab.setdefault(w, len(self.vocab) + 1) for w in got], np.int64)
            if len(got) >= width:
                self.keys.append(key), self.own.append(ids)
            elif got:
                self.short.setdefault(len(got), {}).setdefault(ids.tobytes(), []).append(key)
        self.length = [len(x) for x in self.own]
        self.begin = np.concatenate(([0], np.cumsum(self.length))).astype(np.int64)
        hashes, at, item = [], [], []
        for k, ids in enumerate(self.own):
            h = rolling(ids, width)
            hashes.append(h), at.append(np.arange(len(h)) + self.begin[k]), item.append(np.full(len(h), k))
        join = lambda x, t: np.concatenate(x) if x else np.zeros(0, t)
        self.flat, h = join(self.own, np.int64), join(hashes, np.uint64)
        order = np.argsort(h, kind="stable")
        self.hash, self.at, self.item = h[order], join(at, np.int64)[order], join(item, np.int64)[order]

    def numbered(self, text: str | None) -> np.ndarray:
        """The text's words by number, 0 for those that no item has."""
        got, get = words(text), self.vocab.get
        return np.fromiter((get(w, 0) for w in got), np.int64, len(got))

    def places(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Document places whose window some item has, with the range of its seeds."""
        none = np.zeros(0, np.int64)
        if len(ids) < self.width or not len(self.hash):
            return none, none, none
        h = rolling(ids, self.width)
        lo = np.searchsorted(self.hash, h, "left")
        place = np.flatnonzero(self.hash[np.minimum(lo, len(self.hash) - 1)] == h)
        return place, lo[place], np.searchsorted(self.hash, h[place], "right")

    def matches(self, ids: np.ndarray, place: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> dict[int, list[tuple[int, int, int]]]:
        """Maximal matches (document place, item place, length) by item."""
        n = hi - lo
        i = np.repeat(place, n)
        k = np.repeat(lo, n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        j, item = self.at[k], self.item[k]
        step = np.arange(self.width)
        true = (ids[i[:, None] + step] == self.flat[j[:, None] + step]).all(axis=1)
        i, j, item = i[true], j[true] - self.begin[item[true]], item[true]
        if not len(i):
            return {}
        order = np.lexsort((i, i - j, item))
        i, j, item = i[order], j[order], item[order]
        head = np.flatnonzero(np.concatenate(([True], (item[1:] != item[:-1]) | (i[1:] != i[:-1] + 1) | (j[1:] != j[:-1] + 1))))
        size = np.diff(np.append(head, len(i))) + self.width - 1
        out: dict[int, list[tuple[int, int, int]]] = {}
        for a, s in zip(head.tolist(), size.tolist()):
            out.setdefault(int(item[a]), []).append((int(i[a]), int(j[a]), s))
        return out

    def whole(self, ids: np.ndarray) -> Iterator[tuple[object, int]]:
        """Keys and lengths of the short items that stand in the text as a whole."""
        for n, own in self.short.items():
            known = np.convolve(ids > 0, np.ones(n, np.int64), "valid") == n if len(ids) >= n else np.zeros(0, bool)
            for window in {ids[k : k + n].tobytes() for k in np.flatnonzero(known)} & own.keys():
                yield from ((key, n) for key in own[window])


class Windows:
    """Hashes of all windows of any one length of a word list."""

    def __init__(self, ids: np.ndarray):
        power, back = np.full(len(ids), BASE, np.uint64), np.full(len(ids), pow(int(BASE), -1, 1 << 64), np.uint64)
        power[:1] = back[:1] = 1
        self.back = np.cumprod(back, dtype=np.uint64)
        self.sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(ids.astype(np.uint64) * np.cumprod(power, dtype=np.uint64), dtype=np.uint64)))

    def of(self, n: int, free: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places and hashes of the windows of n words that are all free."""
        busy = np.concatenate(([0], np.cumsum(~free)))
        at = np.flatnonzero(busy[n:] == busy[:-n])
        return at, (self.sums[at + n] - self.sums[at]) * self.back[at]


def tile_repeats(ids: np.ndarray, item: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """The tiles of tile(), without laying out seeds: memory is linear in both texts, whatever repeats in them."""
    doc, own, free, left, tiles = Windows(ids), Windows(item), ids > 0, np.ones(len(item), bool), []

    def shared(n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        (i, h), (j, g) = doc.of(n, free), own.of(n, left)
        both = np.isin(h, g)
        return i[both], h[both], j, g

    longest = min(len(ids), len(item))
    while longest >= least:
        lo, hi = least - 1, longest  # the longest length that windows of both share; shorter ones are shared too
        while lo < hi:
            mid = (lo + hi + 1) // 2
            lo, hi = (mid, hi) if len(shared(mid)[0]) else (lo, mid - 1)
        n, longest, after = lo, lo - 1, 0
        while n >= least:
            i, h, j, g = shared(n)
            found = None
            for a, x in zip(i[i >= after].tolist(), h[i >= after]):
                found = next(((a, b) for b in j[g == x].tolist() if (ids[a : a + n] == item[b : b + n]).all()), None)
                if found:
                    break
            if not found:
                break
            a, b = found
            tiles.append((a, b, n))
            free[a : a + n] = left[b : b + n] = False
            after = a + n
    return tiles


def tile(found: list[tuple[int, int, int]], least: int) -> list[tuple[int, int, int]]:
    """Greedy tiles: longest first, none overlapping in the document or the item."""
    queue = [(-n, i, j) for i, j, n in found]
    heapq.heapify(queue)
    in_doc: set[int] = set()
    in_item: set[int] = set()
    tiles = []
    while queue:
        neg, i, j = heapq.heappop(queue)
        n = -neg
        taken = [x for x in range(n) if i + x in in_doc or j + x in in_item]
        if not taken:
            tiles.append((i, j, n))
            in_doc.update(range(i, i + n)), in_item.update(range(j, j + n))
            continue
        for a, b in zip([-1, *taken], [*taken, n]):  # free stretches between marked words compete again
            if b - a - 1 >= least:
                heapq.heappush(queue, (-(b - a - 1), i + a + 1, j + a + 1))
    return tiles


def contained(seeds: Seeds, text: str | None, coverage: float = COVERAGE, max_seeds: int = MAX_SEEDS) -> list[tuple[object, int, int, int, float]]:
    """(item key, tiles, covered words, item words, coverage) of the items that a text contains."""
    ids, out = seeds.numbered(text), []
    place, lo, hi = seeds.places(ids)
    if len(place):
        if int((hi - lo).sum()) <= max_seeds:
            laid = ((k, tile(found, seeds.width)) for k, found in sorted(seeds.matches(ids, place, lo, hi).items()))
        else:
            span = np.unique(lo, return_index=True)[1]  # each range of seeds once
            touched = np.unique(np.concatenate([np.unique(seeds.item[a:b]) for a, b in zip(lo[span], hi[span])]))
            laid = ((k, tile_repeats(ids, seeds.own[k], seeds.width)) for k in touched.tolist())
        for k, tiles in laid:
            covered = sum(n for _, _, n in tiles)
            if tiles and covered >= coverage * seeds.length[k]:
                out.append((seeds.keys[k], len(tiles), covered, seeds.length[k], covered / seeds.length[k]))
    return out + [(key, 1, n, n, 1.0) for key, n in seeds.whole(ids)]


def passes(benchmark: DataFrame, limit: int = PASS_BYTES) -> Iterator[tuple[int, Seeds]]:
    """(number of parts, part): the benchmark in parts of a checked size, so what is shipped at a time is bounded; usually one."""
    rows = benchmark.select("item_id", "text")
    total = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = max(1, -(-total // limit))
    for p in range(parts):
        own = rows if parts == 1 else rows.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == p)
        yield parts, Seeds([(r["item_id"], r["text"]) for r in own.orderBy("item_id", "text").toLocalIterator()])


def _over_parts(docs: DataFrame, benchmark: DataFrame, apply, limit: int, chained: bool = False) -> list[DataFrame]:
    """apply(docs, broadcast part) for every part, where chained on what the part before left.

    Of several parts, each result is written and its broadcast freed before the next is shipped.
    """
    spark, scratch, out = docs.sparkSession, Scratch(docs.sparkSession, "tiling"), []
    for k, (parts, seeds) in enumerate(passes(benchmark, limit)):
        own = spark.sparkContext.broadcast(seeds)
        got = apply(docs, own)
        if parts > 1:
            with lean_batches(spark):
                got = scratch.save(got, f"part{k}")
            own.destroy()
        out.append(got)
        docs = got if chained else docs
    return out


def leaks(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, limit: int = PASS_BYTES) -> DataFrame:
    """(doc_id, item_id, tiles, covered_words, item_words, coverage) of every contained item."""
    kinds = {"doc_id": docs.select("doc_id").schema[0].dataType, "item_id": benchmark.select("item_id").schema[0].dataType}
    schema = ", ".join([*(f"{c} {k.simpleString()}" for c, k in kinds.items()), "tiles int, covered_words int, item_words int, coverage double"])
    item_type = to_arrow_type(kinds["item_id"])

    def find(rows: DataFrame, own) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seeds = own.value
            for batch in batches:
                got = [(d.as_py(), *x) for d, t in zip(batch.column("doc_id"), batch.column("text")) for x in contained(seeds, t.as_py(), coverage)]
                arrow = [batch.schema.field("doc_id").type, item_type, pa.int32(), pa.int32(), pa.int32(), pa.float64()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*got)) or [()] * 6, arrow)], ["doc_id", "item_id", "tiles", "covered_words", "item_words", "coverage"])

        return rows.select("doc_id", "text").mapInArrow(run, schema)

    return reduce(DataFrame.unionByName, _over_parts(docs, benchmark, find, limit))


def drop_leaks(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE, limit: int = PASS_BYTES) -> DataFrame:
    """All columns of the documents that contain no benchmark item."""

    def keep(rows: DataFrame, own) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seeds = own.value
            for batch in batches:
                yield batch.filter(pa.array([not contained(seeds, t.as_py(), coverage) for t in batch.column("text")], pa.bool_()))

        return rows.mapInArrow(run, rows.schema)

    return _over_parts(docs, benchmark, keep, limit, chained=True)[-1]
