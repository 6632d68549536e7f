"""Character metrics, column summaries and spreads. Costs are whole half-units: 0.5 is 1, 1.5 is 3.

For metrics by character class a column of characters is summarised by one integer, from which its
spread follows exactly: class bits, whether a gap is in it, whether it has several characters, and the
only character if there is one. Metrics by table keep the character set itself.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np

GAP = None
#: Layout of a packed summary: code point, then class bits, then gap and several flags.
CHAR_BITS, CLASS_BITS = 21, 5
CLASS_AT, GAP_BIT, MANY_BIT = CHAR_BITS, 1 << (CHAR_BITS + CLASS_BITS), 1 << (CHAR_BITS + CLASS_BITS + 1)
CHAR_MASK, CLASS_MASK = (1 << CHAR_BITS) - 1, ((1 << CLASS_BITS) - 1) << CHAR_BITS
#: Number of set class bits, for all class masks.
_SEVERAL = np.array([bin(k).count("1") > 1 for k in range(1 << CLASS_BITS)])

# The three cost constants and the class scheme of the experiments; the gap cost is ours.
SAME, CROSS, GAP_COST = 0.5, 1.5, 1.0


def digit_letter_other(ch: str) -> int:
    return 0 if "0" <= ch <= "9" else 1 if ch.isalpha() else 2


def digit_upper_lower_other(ch: str) -> int:
    return 0 if "0" <= ch <= "9" else 2 if not ch.isalpha() else 1 if ch.isupper() else 3


SCHEMES = {"digit/letter/other": digit_letter_other, "digit/upper/lower/other": digit_upper_lower_other, "one": lambda ch: 0}


def _half(x: float) -> int:
    if 2 * x != int(2 * x):
        raise ValueError(f"{x} is not a multiple of 0.5")
    return int(2 * x)


class CharMetric:
    """A distance on characters and the gap."""

    def __init__(self, same: int, cross: int, gap: int, scheme: str, table: dict | None = None, spread: str = "diameter"):
        self.same, self.cross, self.gap, self.scheme, self.table, self.kind = same, cross, gap, scheme, table, spread
        #: packed summaries of single characters, once asked for
        self.ones: dict[str, int] = {}

    # ---- makers

    @classmethod
    def classes(cls, same: float = SAME, cross: float = CROSS, gap: float = GAP_COST, scheme: str = "digit/letter/other", spread: str = "diameter") -> CharMetric:
        """0 for equal characters, `same` within a class, `cross` between classes."""
        return cls(_half(same), _half(cross), _half(gap), scheme, None, spread)

    @classmethod
    def unit(cls) -> CharMetric:
        """1 for any two different symbols: edit distance for two strings."""
        return cls(2, 2, 2, "one")

    @classmethod
    def from_table(cls, pairs: dict[tuple, float], gap: float | None = None) -> CharMetric:
        """Any finite table of (a, b) -> cost; symmetric entries may be left out, a gap is None."""
        table = {frozenset((a, b)): _half(c) for (a, b), c in pairs.items()}
        if gap is not None:
            for a in {c for k in table for c in k if c is not None}:
                table.setdefault(frozenset((a, GAP)), _half(gap))
        return cls(0, 0, 0, "one", table)

    @classmethod
    def filler(cls, alphabet: str, filler: str) -> CharMetric:
        """The hardness construction: 1 against the gap or the filler symbol, 2 between others."""
        symbols = [*alphabet, filler, GAP]
        one = lambda a, b: 1.0 if GAP in (a, b) or filler in (a, b) else 2.0
        return cls.from_table({(a, b): one(a, b) for a, b in combinations(symbols, 2)})

    # ---- distances

    def distance(self, a: str | None, b: str | None) -> int:
        if a == b:
            return 0
        if self.table is not None:
            return self.table[frozenset((a, b))]
        if a is GAP or b is GAP:
            return self.gap
        of = SCHEMES[self.scheme]
        return self.same if of(a) == of(b) else self.cross

    def check(self, alphabet: str) -> list[tuple]:
        """Violations of identity, symmetry or the triangle inequality, the gap included; empty for a metric."""
        symbols, bad = [*alphabet, GAP], []
        for a in symbols:
            for b in symbols:
                if (self.distance(a, b) == 0) != (a == b) or self.distance(a, b) != self.distance(b, a):
                    bad.append((a, b))
                bad += [(a, c, b) for c in symbols if self.distance(a, b) > self.distance(a, c) + self.distance(c, b)]
        return bad

    def column_spread(self, chars) -> int:
        """Largest distance in a set; with kind 'pairsum' the rejected alternative, the sum over all pairs."""
        pairs = [self.distance(a, b) for a, b in combinations(set(chars), 2)]
        return sum(pairs) if self.kind == "pairsum" else max(pairs, default=0)

    @property
    def packed(self) -> bool:
        """Whether packed summaries determine spreads."""
        return self.table is None and self.kind == "diameter"

    # ---- packed summaries

    def pack(self, chars) -> int:
        of, out, own = SCHEMES[self.scheme], 0, [c for c in set(chars) if c is not GAP]
        for c in own:
            out |= 1 << (CLASS_AT + of(c))
        if len(own) > 1:
            out |= MANY_BIT
        elif own:
            out |= ord(own[0])
        return out | (GAP_BIT if GAP in chars else 0)

    def pack_code(self, code: str) -> np.ndarray:
        one = self.ones
        for c in code:
            if c not in one:
                one[c] = self.pack((c,))
        return np.array([one[c] for c in code], np.int64)

    def spread_of(self, s: np.ndarray) -> np.ndarray:
        """Spreads of packed summaries."""
        cls = (s & CLASS_MASK) >> CLASS_AT
        out = np.where((s & MANY_BIT) != 0, self.same, 0)
        out = np.maximum(out, np.where(_SEVERAL[cls], self.cross, 0))
        return np.maximum(out, np.where(((s & GAP_BIT) != 0) & (cls != 0), self.gap, 0)).astype(np.int32)


def union(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Packed summaries of unions."""
    ca, cb = a & CHAR_MASK, b & CHAR_MASK
    flags = (a | b) & ~np.int64(CHAR_MASK)
    clash = (ca != 0) & (cb != 0) & (ca != cb)
    flags = flags | np.where(clash, np.int64(MANY_BIT), np.int64(0))
    one = np.where(ca != 0, ca, cb)
    return flags | np.where((flags & MANY_BIT) != 0, np.int64(0), one)
