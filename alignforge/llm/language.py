"""Operator 2: language identification with hyperdimensional profiles.

Every letter owns a random +1/-1 vector. A trigram is the elementwise product of its letters' vectors,
each rotated by its place; a text is the sum of its trigram vectors, a language the sum of its training
texts' unit bundles. A document goes to the language prototype with the highest cosine.

Defined results: text null or without any letter gives `und` with score 0; so does every text if no
language was learned. Ties go to the language name that sorts first. Extra columns are ignored, repeated
rows are each scored. lang, source and doc_id never enter a prediction; doc_id only picks training rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean_batches

DIM = 512
SEED = 20_211
#: Expected training rows per language at most; they are drawn by a hash of doc_id.
FIT_ROWS = 4000
#: Trigram vectors a worker keeps before it starts anew, one byte an element: 20 MB at most, as workers outlive tasks.
BOOK = 40_000
UND = "und"
#: Cosine from which the language found counts more than the one a document states.
MIN_SCORE = 0.5

_alpha: np.ndarray | None = None


def _letters() -> np.ndarray:
    global _alpha
    if _alpha is None:
        _alpha = np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000)
    return _alpha


def trigrams(text: str) -> tuple[np.ndarray, np.ndarray] | None:
    """Distinct packed trigrams and their counts over the whole lower-cased text; None without a letter.

    Runs of anything but letters count as one gap, and a gap stands before and after the text.
    """
    codes = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), "<u4")
    codes = np.where(_letters()[codes], codes, 0)
    codes = np.concatenate(([0], codes, [0])).astype(np.uint64)
    codes = codes[(codes != 0) | np.concatenate(([True], codes[:-1] != 0))]
    if len(codes) < 3:
        return None
    return np.unique((codes[:-2] << np.uint64(42)) | (codes[1:-1] << np.uint64(21)) | codes[2:], return_counts=True)


class Codebook:
    """Trigram vectors on demand; bounded, and the same in every process."""

    def __init__(self, dim: int = DIM, seed: int = SEED):
        self.dim, self.seed = dim, seed
        self.letter: dict[int, np.ndarray] = {}
        self.clear()

    def clear(self) -> None:
        self.at: dict[int, int] = {}
        self.rows = np.empty((1024, self.dim), np.int8)

    def _of(self, code: int) -> np.ndarray:
        if code not in self.letter:
            bits = np.random.Generator(np.random.PCG64([self.seed, code])).integers(0, 2, self.dim)
            self.letter[code] = (2 * bits - 1).astype(np.int8)
        return self.letter[code]

    def lookup(self, grams: np.ndarray) -> np.ndarray:
        if len(self.at) + len(grams) > BOOK and len(self.at):
            self.clear()
        need = len(self.at) + len(grams)
        if need > len(self.rows):
            self.rows = np.concatenate((self.rows, np.empty((max(need, min(2 * len(self.rows), BOOK)) - len(self.rows), self.dim), np.int8)))
        out = np.empty(len(grams), np.int64)
        for i, g in enumerate(grams.tolist()):
            k = self.at.get(g)
            if k is None:
                k = self.at[g] = len(self.at)
                a, b, c = g >> 42, (g >> 21) & 0x1FFFFF, g & 0x1FFFFF
                self.rows[k] = np.roll(self._of(a), 2) * np.roll(self._of(b), 1) * self._of(c)
            out[i] = k
        return out

    def bundle(self, text: str | None) -> np.ndarray | None:
        found = trigrams(text) if text else None
        if found is None:
            return None
        grams, counts = found
        total = np.zeros(self.dim, np.float32)
        for lo in range(0, len(grams), 2048):  # long texts in pieces
            rows = self.lookup(grams[lo : lo + 2048])
            total += counts[lo : lo + 2048].astype(np.float32) @ self.rows[rows].astype(np.float32)
        return total


_book: Codebook | None = None


def _codebook() -> Codebook:
    global _book
    if _book is None:
        _book = Codebook()
    return _book


def training_split(docs: DataFrame) -> DataFrame:
    """doc_id, text, lang and held_out: crc32 of doc_id as text leaves remainder 2 by 4."""
    crc = F.crc32(F.encode(F.col("doc_id").cast("string"), "UTF-8"))
    return docs.select("doc_id", "text", "lang", F.coalesce(crc % 4 == 2, F.lit(False)).alias("held_out"))


def learn(docs: DataFrame, fit_rows: int = FIT_ROWS) -> dict[str, np.ndarray]:
    """Unit prototypes by language from rows that are not held out.

    Language counts cover all rows; each language then keeps about fit_rows of its rows by hash. Partial
    bundles are summed per language and dimension on the executors, so languages x DIM numbers come back.
    """
    rows = training_split(docs).where("not held_out and lang is not null and doc_id is not null and text is not null")
    share = {r["lang"]: fit_rows / r["n"] for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # one row a language
    if not share:
        return {}
    at = F.create_map(*[x for k, v in share.items() for x in (F.lit(k), F.lit(min(1.0, v)))])
    picked = rows.where(F.pmod(F.xxhash64(F.lit("fit"), "doc_id"), F.lit(1 << 20)) < F.element_at(at, F.col("lang")) * (1 << 20))

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        book, sums = _codebook(), {}
        for batch in batches:
            for text, lang in zip(batch.column("text"), batch.column("lang")):
                v = book.bundle(text.as_py())
                if v is not None and (n := float(np.linalg.norm(v))) > 0:
                    key = lang.as_py()
                    sums[key] = sums.get(key, 0) + v.astype(np.float64) / n
        for key, v in sums.items():
            yield pa.RecordBatch.from_pydict({"lang": [key] * DIM, "dim": np.arange(DIM, dtype=np.int32), "x": v})

    parts = picked.select("text", "lang").mapInArrow(partial, "lang string, dim int, x double")
    protos: dict[str, np.ndarray] = {}
    with lean_batches(docs.sparkSession):
        sums = parts.groupBy("lang", "dim").agg(F.sum("x").alias("x")).collect()  # languages x DIM rows
    for r in sums:
        protos.setdefault(r["lang"], np.zeros(DIM))[r["dim"]] = r["x"]
    return {k: v / np.linalg.norm(v) for k, v in sorted(protos.items()) if np.linalg.norm(v) > 0}


class Profiles:
    """Prototypes with their common part taken out, ready to score a bundle."""

    def __init__(self, protos: dict[str, np.ndarray]):
        self.names = list(protos)
        if protos:
            m = np.stack([protos[k] for k in self.names])
            self.raw = m.astype(np.float32)
            centred = m - m.mean(axis=0) * (len(m) > 1)
            self.centred = (centred / np.maximum(np.linalg.norm(centred, axis=1, keepdims=True), 1e-12)).astype(np.float32)

    def judge(self, bundle: np.ndarray | None) -> tuple[str, float]:
        """Language by the centred cosine; the score is the cosine with its plain prototype, cut to 0..1."""
        if bundle is None or not self.names or not (n := float(np.linalg.norm(bundle))):
            return UND, 0.0
        best = int(np.argmax(self.centred @ bundle))
        return self.names[best], float(min(1.0, max(0.0, self.raw[best] @ bundle / n)))


def predict(docs: DataFrame, protos: dict[str, np.ndarray]) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every row, one scan and no shuffle."""
    profiles = Profiles(protos)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        book = _codebook()
        for batch in batches:
            got = [profiles.judge(book.bundle(t.as_py())) for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("held_out"), pa.array([x for x, _ in got], pa.string()), pa.array([x for _, x in got], pa.float64())],
                ["doc_id", "held_out", "lang_pred", "score"],
            )

    rows = training_split(docs).select("doc_id", "held_out", "text")
    return rows.mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, held_out boolean, lang_pred string, score double")


def identify(docs: DataFrame) -> DataFrame:
    return predict(docs, learn(docs))


def keep_identified(docs: DataFrame, min_score: float = MIN_SCORE) -> DataFrame:
    """All columns of the rows with a language (not `und`); lang becomes the language found in the text.

    A text less like its prototype than min_score, such as one of a few words, keeps the language it states, if any.
    """
    profiles = Profiles(learn(docs))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        book = _codebook()
        for batch in batches:
            at = batch.schema.get_field_index("lang")
            got = [profiles.judge(book.bundle(t.as_py())) for t in batch.column("text")]
            lang = [found if score >= min_score or not stated.is_valid else stated.as_py() for (found, score), stated in zip(got, batch.column(at))]
            batch = batch.set_column(at, batch.schema.field(at), pa.array(lang, batch.schema.field(at).type))
            yield batch.filter(pa.array([found != UND for found, _ in got], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)
