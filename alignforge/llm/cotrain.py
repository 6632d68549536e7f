"""Operator 1: quality classification by co-training of a text view and a metadata view.

The text view sees hashed words and the shape of the text, the metadata view language, source and length.
Each is a logistic model. In every round each view scores all unlabelled documents, hands its most
confident positives and negatives to the other view's training set, and both are fitted again. At the
end each view is calibrated on labelled rows kept out of fitting, and the calibrated views are combined
by a weight chosen on them; every document gets the combined score.

Defined results: without labels of both classes every score is 0.5 and everything is kept; null or empty
texts have an empty text view; null metadata is a value of its own; repeated rows are scored alike; of
several labels of a doc_id the highest counts; labels without a document are ignored; extra columns are
ignored. Ties of confidence go to the smaller row hash.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import Scratch, lean_batches

HASHED = 96
SHAPE = 14
TEXT = HASHED + SHAPE
META = 64
#: Expected labelled rows that fitting takes at most, drawn by hash; the rest of the labels is not read.
FIT_ROWS = 8000
#: One labelled row in so many is kept out of fitting and used for calibration.
CALIBRATE = 4
ROUNDS = 4
#: Rows of either class that a view hands over in a round: this share of the unlabelled ones, within these limits. Equal pairs of views count once.
HANDED_SHARE, HANDED_LEAST, HANDED_MOST = 0.002, 40, 500
#: Lowest score that is kept; low, as clean short texts score near the middle.
KEEP = 0.3

_word = re.compile(r"[^\x20\x09-\x0D]+")


def text_view(text: str | None) -> np.ndarray:
    """Hashed word shares and 14 figures of the text's shape, as bytes 0..255, over the whole text."""
    out = np.zeros(TEXT, np.uint8)
    if not text:
        return out
    words = _word.findall(text)
    n, m = max(1, len(words)), len(text)
    if words:
        seen: dict[str, int] = {}
        for w in words:
            seen[w] = seen.get(w, 0) + 1
        at = np.fromiter((zlib.crc32(w.lower().encode("utf-8", "surrogatepass")) % HASHED for w in seen), np.int64, len(seen))
        share = np.bincount(at, np.fromiter(seen.values(), np.float64, len(seen)), HASHED) / n
        out[:HASHED] = np.minimum(255, np.sqrt(share) * 400)
        top = max(seen.values()) / n
    lines = text.split("\n")
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    ascii_ = codes[codes < 128].astype(np.uint8)
    counts = np.bincount(ascii_, minlength=128)
    upper, lower, digit = counts[65:91].sum(), counts[97:123].sum(), counts[48:58].sum()
    marks = counts[33:48].sum() + counts[58:65].sum() + counts[91:97].sum() + counts[123:127].sum()
    stops = counts[46] + counts[44]
    figures = (
        upper / m, lower / m, digit / m, marks / m, (marks - stops) / m, stops / m, counts[124] / m * 4, (counts[35] + counts[36] + counts[37] + counts[38] + counts[42] + counts[33]) / m * 2,
        (m - len(ascii_)) / m, min(1.0, len(seen) / n) if words else 0, top if words else 0, len(set(lines)) / len(lines), min(1.0, m / n / 20), min(1.0, np.log1p(m) / 14),
    )
    out[HASHED:] = [min(255, int(255 * x)) for x in figures]
    return out


def meta_view(lang: str | None, source: str | None, n_chars: int | None) -> np.ndarray:
    """Language and source by hash, length by steps of a power of two, as bytes."""
    out = np.zeros(META, np.uint8)
    out[zlib.crc32(repr(lang).encode("utf-8", "surrogatepass")) % 16] = 255
    out[16 + zlib.crc32(repr(source).encode("utf-8", "surrogatepass")) % 32] = 255
    out[48 + (15 if n_chars is None or n_chars < 0 else min(14, int(n_chars).bit_length()))] = 255
    return out


def featured(docs: DataFrame) -> DataFrame:
    """doc_id, h (a row hash) and both views of every row as binaries of fixed size; one scan."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            text = [text_view(t.as_py()).tobytes() for t in batch.column("text")]
            meta = [meta_view(*x).tobytes() for x in zip(*(batch.column(c).to_pylist() for c in ("lang", "source", "n_chars")))]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("h"), pa.array(text, pa.binary()), pa.array(meta, pa.binary())], ["doc_id", "h", "text_view", "meta_view"])

    rows = docs.select("doc_id", "text", "lang", "source", F.col("n_chars").cast("long").alias("n_chars"), F.xxhash64("doc_id", "n_chars", "source").alias("h"))
    return rows.mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, h long, text_view binary, meta_view binary")


def _matrix(col: pa.Array | list, width: int) -> np.ndarray:
    raw = b"".join(x.as_py() if hasattr(x, "as_py") else bytes(x) for x in col)
    return np.frombuffer(raw, np.uint8).reshape(-1, width).astype(np.float64) / 255


def fit(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 1.0) -> np.ndarray:
    """Ridge-penalised logistic regression by Newton steps; the last weight is the intercept."""
    z = np.concatenate((x, np.ones((len(x), 1))), axis=1)
    pull = np.full(z.shape[1], ridge)
    pull[-1] = 1e-6
    w = np.zeros(z.shape[1])
    for _ in range(25):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        g = z.T @ (weight * (y - p)) - pull * w
        step = np.linalg.solve((z * (weight * p * (1 - p))[:, None]).T @ z + np.diag(pull), g)
        w = w + step
        if np.abs(step).max() < 1e-6:
            break
    return w


def margin(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    return x @ w[:-1] + w[-1]


def platt(m: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Slope and intercept that turn margins to probabilities."""
    return fit(m[:, None] / max(1e-9, np.abs(m).max()), y, np.ones(len(y)), 1e-2) / np.array([max(1e-9, np.abs(m).max()), 1.0])


def sigmoid(m: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(m, -30, 30)))


class Views:
    """Both fitted views with calibrations and the weight of the text view's log odds."""

    def __init__(self, w: dict[str, np.ndarray], cal: dict[str, np.ndarray], share: float):
        self.w, self.cal, self.share = w, cal, share

    def parts(self, x: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Calibrated text score, metadata score and combined score."""
        odds = {v: self.cal[v][0] * margin(x[v], self.w[v]) + self.cal[v][1] for v in ("text", "meta")}
        return sigmoid(odds["text"]), sigmoid(odds["meta"]), sigmoid(self.share * odds["text"] + (1 - self.share) * odds["meta"])


def _confident(features: DataFrame, w: dict[str, np.ndarray], handed: int) -> dict[tuple[str, int], list]:
    """For each view and class, the rows of all unlabelled ones that it is surest of, equal pairs of views once.

    One pass: batches keep their best, a partial group limit on every task and a final one leave `handed` rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            h = batch.column("h").to_numpy()
            raw = np.array([a + b for a, b in zip(batch.column("text_view").to_pylist(), batch.column("meta_view").to_pylist())], f"S{TEXT + META}")  # of one length, so the cut of trailing zeros tells no two apart
            order = np.argsort(h, kind="stable")
            once = order[np.sort(np.unique(raw[order], return_index=True)[1])]  # of equal rows that with the smallest h
            for view, width in (("text", TEXT), ("meta", META)):
                m = margin(_matrix(batch.column(f"{view}_view"), width)[once], w[view])
                for side in (1, 0):
                    best = np.lexsort((h[once], -m if side else m))[:handed]
                    rows = batch.take(pa.array(once[best]))
                    sure = m[best] if side else -m[best]
                    yield pa.RecordBatch.from_arrays([pa.array([view] * len(best)), pa.array([side] * len(best), pa.int32()), pa.array(sure), rows.column("h"), rows.column("text_view"), rows.column("meta_view")], ["view", "side", "sure", "h", "text_view", "meta_view"])

    tops = features.where("quality is null").select("h", "text_view", "meta_view").mapInArrow(run, "view string, side int, sure double, h long, text_view binary, meta_view binary")
    once = tops.groupBy("view", "side", "text_view", "meta_view").agg(F.max("sure").alias("sure"), F.min("h").alias("h"))
    order = W.partitionBy("view", "side").orderBy(F.desc("sure"), "h", "text_view", "meta_view")
    best = once.withColumn("at", F.row_number().over(order)).where(F.col("at") <= handed)
    out: dict[tuple[str, int], list] = {}
    for r in best.collect():  # 4 x handed rows
        out.setdefault((r["view"], r["side"]), []).append(r)
    return {k: sorted(v, key=lambda r: r["at"]) for k, v in sorted(out.items())}


def learn(features: DataFrame, rounds: int = ROUNDS, handed: int | None = None) -> Views | None:
    """Co-trains both views on the labelled rows of the feature table; None without both classes."""
    seed = features.where("quality is not null").select("h", "quality", "text_view", "meta_view").toPandas()  # about FIT_ROWS rows, see labelled()
    seed = seed.sort_values("h", ignore_index=True)
    out = (seed["h"].to_numpy().astype(np.int64) // 7) % CALIBRATE == 0
    y = seed["quality"].to_numpy().astype(np.float64)
    if len(seed) < 8 or len(np.unique(y[~out])) < 2 or len(np.unique(y[out])) < 2:
        return None
    x = {"text": _matrix(seed["text_view"], TEXT), "meta": _matrix(seed["meta_view"], META)}
    train = {v: [(x[v][~out], y[~out], np.ones((~out).sum()))] for v in x}
    model = lambda v: fit(*(np.concatenate(c) for c in zip(*train[v])))
    w = {v: model(v) for v in x}
    rate = np.array([1 - y.mean(), y.mean()])
    if handed is None:
        handed = min(HANDED_MOST, max(HANDED_LEAST, int(HANDED_SHARE * features.where("quality is null").count())))
    for _ in range(rounds):
        for (view, side), rows in _confident(features, w, handed).items():
            other = "meta" if view == "text" else "text"
            width = META if other == "meta" else TEXT
            got = _matrix([r[f"{other}_view"] for r in rows], width)
            # Classes weigh as in the labels, and what a weak view hands over weighs less.
            trust = max(0.0, 2 * _auc(margin(x[view][out], w[view]), y[out]) - 1)
            train[other].append((got, np.full(len(got), float(side)), np.full(len(got), trust * 2 * rate[side])))
        w = {v: model(v) for v in x}
    m = {v: margin(x[v][out], w[v]) for v in x}
    cal = {v: platt(m[v], y[out]) for v in x}
    odds = {v: cal[v][0] * m[v] + cal[v][1] for v in x}
    losses = []
    for share in np.linspace(0, 1, 21):
        p = np.clip(sigmoid(share * odds["text"] + (1 - share) * odds["meta"]), 1e-9, 1 - 1e-9)
        losses.append((-(y[out] * np.log(p) + (1 - y[out]) * np.log(1 - p)).mean(), -share))
    return Views(w, cal, -min(losses)[1])


def _auc(m: np.ndarray, y: np.ndarray) -> float:
    order = np.argsort(m, kind="stable")
    rank = np.empty(len(m))
    rank[order] = np.arange(1, len(m) + 1)
    a, b = (y == 1).sum(), (y == 0).sum()
    return float((rank[y == 1].sum() - a * (a + 1) / 2) / (a * b)) if a and b else 0.5


def labelled(features: DataFrame, labels: DataFrame, fit_rows: int = FIT_ROWS) -> DataFrame:
    """Adds quality, set on about fit_rows rows drawn by a hash of doc_id, null elsewhere."""
    usable = labels.where("quality in (0, 1) and doc_id is not null")
    n = max(1, usable.count())
    own = usable.where(F.pmod(F.xxhash64(F.lit("quality"), "doc_id"), F.lit(1 << 20)) < min(1.0, fit_rows / n) * (1 << 20))
    own = own.groupBy(F.col("doc_id").alias("l_id")).agg(F.max("quality").alias("quality"))
    return features.join(own, features["doc_id"] == own["l_id"], "left").drop("l_id")


def score(docs: DataFrame, labels: DataFrame, keep: float = KEEP) -> DataFrame:
    """doc_id, text_score, meta_score, score and keep of every document."""
    scratch = Scratch(docs.sparkSession, "cotrain")
    with lean_batches(docs.sparkSession):
        features = scratch.save(labelled(featured(docs), labels), "features")
    views = learn(features)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if views is None or not n:
                t = m = s = np.full(n, 0.5)
            else:
                t, m, s = views.parts({"text": _matrix(batch.column("text_view"), TEXT), "meta": _matrix(batch.column("meta_view"), META)})
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(t), pa.array(m), pa.array(s), pa.array(s >= keep)], ["doc_id", "text_score", "meta_score", "score", "keep"])

    rows = features.select("doc_id", "text_view", "meta_view")
    return rows.mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, text_score double, meta_score double, score double, keep boolean")
