"""Operator 8: personal data by candidate generation and gradient boosting.

Exact patterns give the base spans, which always stay. High-recall generators propose further spans,
also overlapping ones: spelled-out mail addresses, local phone numbers, 13 to 15 digit cards, IPv6
addresses. Boosted trees score every candidate by its format and the words around it; scores are
calibrated, and each kind has the threshold that holds the wanted precision on a calibration split.

The trees are fitted here, on sentences made by rule; no corpus row is used, so the model is the same in
every run. Defined results: null and empty texts have no spans; repeated rows get equal rows; an added
span that overlaps a base span or a better added one is dropped; ties go to the earlier start. Offsets
are code points. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
import socket
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

KINDS = ("email", "ip", "card", "phone")
PRECISION = 0.99
CONTEXT = 32

# ------------------------------------------------------------------ base spans

_domain = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++")
_ip = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_card = re.compile(r"[0-9](?:[ -]?[0-9])+")
_phone = re.compile(r"\+[0-9][ ().0-9-]+[0-9]")
_digit = re.compile(r"[0-9]")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        total += d if k % 2 == 0 else 2 * d - 9 * (d > 4)
    return total % 10 == 0


def _emails(text: str) -> list[tuple[int, int]]:
    """Leftmost matches, found from their @ outward so that long runs cost linear time."""
    out, end, at = [], 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > end and text[begin - 1] in _LOCAL:
            begin -= 1
        if begin < at and (m := _domain.match(text, at + 1)):
            out.append((begin, m.end()))
            end = m.end()
        floor = max(at + 1, end)
        end = max(end, at + 1)
        at = text.find("@", floor)
    return out


def base_spans(text: str) -> list[tuple[str, int, int]]:
    """(kind, start, end) by kind as listed, then start."""
    out = [("email", a, b) for a, b in _emails(text)]
    if not _digit.search(text):
        return out
    # A match takes the whole of its digit runs, so it can only begin where one begins.
    out += [("ip", *m.span()) for m in _ip.finditer(text) if all(len(p := x.lstrip("0")) <= 3 and int(p or 0) <= 255 for x in m[0].split("."))]
    for m in _card.finditer(text):
        digits = re.sub("[^0-9]", "", m[0])
        if 16 <= len(digits) <= 19 and luhn(digits):
            out.append(("card", *m.span()))
    if "+" in text:
        out += [("phone", *m.span()) for m in _phone.finditer(text) if 8 <= sum("0" <= c <= "9" for c in m[0]) <= 15]
    return out


# ------------------------------------------------------------------ candidates

_AT = r"(?:\s?[\[({<]\s?at\s?[\])}>]\s?|\sat\s)"
_DOT = r"(?:\s?[\[({<]\s?dot\s?[\])}>]\s?|\sdot\s|\.)"
# The generators, by the kind they propose.
GENERATORS = {
    "email": re.compile(rf"(?<![A-Za-z0-9._%+-])[A-Za-z0-9][A-Za-z0-9._%+-]{{1,63}}{_AT}[A-Za-z0-9-]{{2,63}}(?:{_DOT}[A-Za-z0-9-]{{2,63}}){{1,3}}", re.I),
    "phone": re.compile(r"(?<![\w.+-])(?:\([0-9]{2,4}\) ?|[0-9]{2,4}[ .-])[0-9]{3,4}[ .-][0-9]{3,4}(?:[ .-][0-9]{2,4})?(?![\w-])"),
    "card": re.compile(r"(?<![\w.+-])[0-9]{4}[ -]?[0-9]{5,6}[ -]?[0-9]{4,5}(?![\w-])"),
    "ip": re.compile(r"(?<![\w:])(?:(?:[0-9a-f]{1,4}:){3,7}[0-9a-f]{1,4}|(?:[0-9a-f]{1,4}:){0,6}(?:[0-9a-f]{1,4}:|:)(?::[0-9a-f]{1,4}){1,6})(?![\w:])", re.I),
}
# all that the mail generator proposes holds one of these
_AT_SIGN = re.compile(_AT, re.I)
# Words that speak for a kind, and words that speak against personal data.
CUES = {
    "email": ("mail", "contact", "write", "reach", "send", "address"),
    "phone": ("tel", "phone", "call", "mobile", "fax", "cell", "contact"),
    "card": ("card", "visa", "master", "amex", "credit", "payment", "paid"),
    "ip": ("ip", "host", "address", "server", "login", "client", "addr"),
}
AGAINST = ("order", "isbn", "issn", "version", "invoice", "serial", "part", "model", "page", "total", "price", "sha", "hash", "id", "no", "nr", "build", "time", "date", "ratio")


def candidates(text: str) -> list[tuple[str, int, int]]:
    out: list[tuple[str, int, int]] = []
    if _AT_SIGN.search(text):
        out += [("email", *m.span()) for m in GENERATORS["email"].finditer(text)]
    if ":" in text:
        out += [("ip", *m.span()) for m in GENERATORS["ip"].finditer(text)]
    if _digit.search(text):
        for kind in ("card", "phone"):
            out += [(kind, *m.span()) for m in GENERATORS[kind].finditer(text)]
    return out


def is_ipv6(span: str) -> bool:
    try:
        return bool(socket.inet_pton(socket.AF_INET6, span))
    except (OSError, ValueError):
        return False


def features(text: str, kind: str, start: int, end: int) -> np.ndarray:
    """Format of the span, and what stands around it."""
    span = text[start:end]
    left, right = text[max(0, start - CONTEXT) : start].lower(), text[end : end + CONTEXT].lower()
    near = re.findall(r"[a-z]+", left)[-4:] + re.findall(r"[a-z]+", right)[:3]
    digits = re.sub("[^0-9]", "", span)
    groups = re.split(r"[^0-9A-Za-z]+", span)
    seps = re.sub(r"[0-9A-Za-z]", "", span)
    runs = max((len(m[0]) for m in re.finditer(r"(.)\1*", digits)), default=0)
    x = [KINDS.index(kind) == k for k in range(4)]
    x += [len(span), len(digits), len(groups), min(map(len, groups)), max(map(len, groups)), len(set(seps)), seps.count(" "), seps.count("-"), seps.count("."), seps.count("("), seps.count(":")]
    x += [luhn(digits) if digits else 0, len(set(digits)), runs, digits[:1] == "0", digits[:1] in ("3", "4", "5", "6") if digits else 0]
    x += [any(c in "[({<" for c in span), " dot " in span.lower(), span.lower().endswith((".com", ".org", ".net", "com", "org", "net", "edu", "gov", "de", "fr", "es", "io"))]
    x += [sum(w.startswith(c) for w in near for c in CUES[kind]), sum(w in AGAINST for w in near), sum(w.startswith(c) for w in near[-6:] for k in KINDS for c in CUES[k])]
    x += [kind == "ip" and is_ipv6(span), "::" in span, sum(map(str.isdigit, span)) / len(span)]
    x += [left.rstrip()[-1:] in (":", "="), bool(re.search(r"[0-9]\s?$", left)), bool(re.match(r"\s?[0-9]", right)), sum(c.isdigit() for c in left), left.rstrip()[-1:] in ("#", "$", "€", "v")]
    return np.array(x, np.float64)


# ------------------------------------------------------------------ boosted trees


class Boosted:
    """Gradient-boosted regression trees for the log loss, on binned features, with a Platt calibration."""

    def __init__(self, rounds: int = 60, depth: int = 3, rate: float = 0.2, bins: int = 16, least: int = 8):
        self.rounds, self.depth, self.rate, self.bins, self.least = rounds, depth, rate, bins, least

    def fit(self, x: np.ndarray, y: np.ndarray) -> Boosted:
        self.cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, self.bins + 1)[1:-1])) for j in range(x.shape[1])]
        b = np.stack([np.searchsorted(c, x[:, j], "right") for j, c in enumerate(self.cuts)], axis=1)
        self.start = float(np.log((y.mean() + 1e-9) / (1 - y.mean() + 1e-9)))
        f, self.trees = np.full(len(y), self.start), []
        for _ in range(self.rounds):
            p = 1 / (1 + np.exp(-f))
            tree = self._grow(b, y - p, p * (1 - p), np.arange(len(y)), self.depth)
            self.trees.append(tree)
            f = f + self.rate * self._apply(tree, b)
        return self

    def _grow(self, b: np.ndarray, g: np.ndarray, h: np.ndarray, rows: np.ndarray, depth: int):
        leaf = float(g[rows].sum() / (h[rows].sum() + 1.0))
        if not depth or len(rows) < 2 * self.least:
            return leaf
        base, best = g[rows].sum() ** 2 / (h[rows].sum() + 1.0), (1e-6, None)
        for j in range(b.shape[1]):
            n = len(self.cuts[j]) + 1
            if n < 2:
                continue
            gs, hs, cs = (np.cumsum(np.bincount(b[rows, j], w, n))[:-1] for w in (g[rows], h[rows], None))
            gain = gs**2 / (hs + 1) + (g[rows].sum() - gs) ** 2 / (h[rows].sum() - hs + 1) - base
            gain[(cs < self.least) | (len(rows) - cs < self.least)] = 0
            k = int(np.argmax(gain))
            if gain[k] > best[0]:
                best = (float(gain[k]), (j, k))
        if best[1] is None:
            return leaf
        j, k = best[1]
        low = b[rows, j] <= k
        return (j, k, self._grow(b, g, h, rows[low], depth - 1), self._grow(b, g, h, rows[~low], depth - 1))

    def _apply(self, tree, b: np.ndarray) -> np.ndarray:
        if not isinstance(tree, tuple):
            return np.full(len(b), tree)
        j, k, low, high = tree
        return np.where(b[:, j] <= k, self._apply(low, b), self._apply(high, b))

    def margin(self, x: np.ndarray) -> np.ndarray:
        b = np.stack([np.searchsorted(c, x[:, j], "right") for j, c in enumerate(self.cuts)], axis=1)
        return self.start + self.rate * sum(self._apply(t, b) for t in self.trees)

    def calibrate(self, x: np.ndarray, y: np.ndarray) -> None:
        """Two Platt parameters by Newton steps."""
        m, ab = self.margin(x), np.array([1.0, 0.0])
        for _ in range(30):
            p = 1 / (1 + np.exp(-(ab[0] * m + ab[1])))
            z = np.stack((m, np.ones_like(m)), axis=1)
            ab = ab + np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + 1e-3 * np.eye(2), z.T @ (y - p) - 1e-3 * (ab - [1.0, 0.0]))
        self.platt = ab

    def probability(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-(self.platt[0] * self.margin(x) + self.platt[1])))


def _examples(n: int, seed: int) -> Iterator[tuple[str, bool]]:
    """Made sentences with one thing in each that a generator proposes, and whether it is personal."""
    r = np.random.default_rng(seed)
    pick = lambda xs: xs[int(r.integers(len(xs)))]
    num = lambda k: "".join(map(str, r.integers(0, 10, k)))
    word = lambda: "".join(pick(("an", "er", "on", "ti", "es", "lo", "ma", "ri", "ta", "ne", "su", "ko")) for _ in range(int(r.integers(1, 4))))
    prose = lambda k: " ".join(word() for _ in range(int(r.integers(1, k + 1))))

    def card(k: int) -> str:
        body = pick(("34", "37", "4", "36", "5", "60")) + num(k)
        body = body[: k - 1]
        return next(body + d for d in "0123456789" if luhn(body + d))

    for _ in range(n):
        kind, good = pick(KINDS), bool(r.integers(2))
        cue = pick(CUES[kind]) if good else pick(AGAINST)
        lead = f"{prose(4)} {cue}{pick((': ', ' ', ' is ', '= '))}" if r.random() < 0.9 else f"{prose(5)} "
        if kind == "email":
            sep = [(" at ", " dot "), ("[at]", "[dot]"), (" (at) ", " (dot) "), (" [at] ", "."), ("(at)", ".")]
            if good:
                a, d = pick(sep)
                thing = f"{word()}{pick(('', '.', '_'))}{word()}{a}{word()}{d}{pick(('com', 'org', 'net', 'de', 'fr', 'es', 'io', 'edu'))}"
            else:
                lead = f"{prose(5)} "
                thing = pick((f"{word()} at {word()}.{word().capitalize()}", f"{word()} at {word()}. {word()}", f"{word()} at {word()} dot {word()}", f"{word()} at {word()}.{word()}"))
        elif kind == "phone":
            forms = (f"({num(3)}) {num(3)}-{num(4)}", f"{num(3)}-{num(3)}-{num(4)}", f"0{num(2)} {num(4)} {num(4)}", f"{num(3)}.{num(3)}.{num(4)}")
            thing = pick(forms) if good else pick((f"{num(4)}-{num(4)}-{num(4)}", f"{num(2)}.{num(4)}.{num(3)}", f"{num(3)} {num(3)} {num(3)}", pick(forms), f"{num(4)}.{num(3)}.{num(3)}"))
        elif kind == "card":
            k = int(r.integers(13, 16))
            c = card(k)
            if good:
                thing = f"{c[:4]} {c[4:10]} {c[10:]}" if k == 15 and r.random() < 0.7 else c
            else:
                bad = num(k)
                thing = bad if not luhn(bad) or r.random() < 0.3 else num(k - 1) + pick("123456789")
        else:
            hexa = lambda: f"{int(r.integers(0, 65536)):x}"
            most = lambda k: ":".join(hexa() for _ in range(int(r.integers(1, k + 1))))
            whole = ":".join(hexa() for _ in range(8))
            short = pick((f"{pick(('fe80', '2001:db8', 'fd00', '2a02:8071'))}::{most(4)}", f"{pick(('fe80', '2001:db8', 'fd00'))}:{most(3)}::{most(2)}", f"2001:{most(4)}::{num(1)}"))
            hexish = lambda: pick(("a", "b", "add", "bad", "cafe", "dead", "face", "fed", "be", "ad", "c", "f"))
            thing = pick((whole, short)) if good else pick((f"{hexish()}::{hexish()}", f"{num(2)}::{num(2)}", ":".join(num(2) for _ in range(4)), ":".join(num(1) for _ in range(int(r.integers(4, 7)))), ":".join(f"{int(r.integers(0, 256)):02x}" for _ in range(6)), ":".join(num(2) for _ in range(5))))
        yield f"{lead}{thing}{pick((' ', ', ', '. ', ') '))}{prose(4)}", good


@lru_cache(maxsize=1)
def model() -> tuple[Boosted, dict[str, float]]:
    """Trees fitted on one set of made examples; calibration and thresholds from another."""

    def table(n: int, seed: int):
        rows, ys, kinds = [], [], []
        for text, good in _examples(n, seed):
            for kind, a, b in candidates(text):
                rows.append(features(text, kind, a, b)), ys.append(float(good)), kinds.append(kind)
        return np.stack(rows), np.array(ys), np.array(kinds)

    x, y, _ = table(4000, 8)
    trees = Boosted().fit(x, y)
    x, y, kinds = table(3000, 9)
    trees.calibrate(x, y)
    p, cut = trees.probability(x), {}
    for kind in KINDS:
        own, good = p[kinds == kind], y[kinds == kind]
        order = np.argsort(-own)
        exact = np.cumsum(good[order]) / np.arange(1, len(order) + 1)
        ok = np.flatnonzero(exact >= PRECISION)
        cut[kind] = max(0.8, float(own[order][ok[-1]])) if len(ok) else 1.1
    return trees, cut


def spans(text: str | None, trees: Boosted, cut: dict[str, float]) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int, float]]]:
    """Base spans, and all spans with their scores (base ones score 1), by kind and start."""
    text = text or ""
    base = base_spans(text)
    more = []
    taken = sorted((a, b) for _, a, b in base)
    begins, reach = [a for a, _ in taken], list(accumulate((b for _, b in taken), max))
    found = []
    for kind, a, b in candidates(text):
        before = bisect_left(begins, b)  # base spans that start before the candidate ends
        if not before or reach[before - 1] <= a:
            found.append((kind, a, b))
    if found:
        p = trees.probability(np.stack([features(text, *c) for c in found]))
        free_from: list[tuple[int, int]] = []
        for s, (kind, a, b) in sorted(zip(p.tolist(), found), key=lambda z: (-z[0], z[1][1])):
            if s >= cut[kind] and all(b <= x or a >= y for x, y in free_from):
                free_from.append((a, b))
                more.append((kind, a, b, s))
    every = sorted([(k, a, b, 1.0) for k, a, b in base] + more, key=lambda z: (KINDS.index(z[0]), z[1]))
    return base, every


def detect(docs: DataFrame) -> DataFrame:
    """doc_id, kinds, starts, ends, scores, is_base of all spans of every row; one scan, no shuffle."""
    trees, cut = model()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = []
            for t in batch.column("text"):
                base, every = spans(t.as_py(), trees, cut)
                own = set(base)
                rows.append([{"kind": k, "start": a, "end": b, "score": s, "base": (k, a, b) in own} for k, a, b, s in every])
            kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64()), ("base", pa.bool_())]))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(rows, kind)], ["doc_id", "found"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {dict(docs.dtypes)['doc_id']}, found array<struct<kind:string,start:long,end:long,score:double,base:boolean>>")


def redact(text: str | None, mask: str = "[{}]") -> str | None:
    """The text with every span replaced by its kind."""
    if text is None:
        return None
    out, end = [], 0
    for kind, a, b, _ in sorted(spans(text, *model())[1], key=lambda z: (z[1], -z[2])):
        if a >= end:
            out += [text[end:a], mask.format(kind)]
            end = b
        end = max(end, b)
    return "".join([*out, text[end:]])


def digest(pieces: list[str]) -> str:
    return hashlib.sha256(",".join(pieces).encode()).hexdigest()
