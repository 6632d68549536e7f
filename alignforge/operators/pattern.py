"""Compact patterns of templates: display text, Java regex, matching and keys.

Display: a column that always holds one character is that character; several are listed in braces, and a
column that may be a gap is listed in square brackets. Runs of three or more neighbours show as a range.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from .kernel import Template, fuse, leaf
from .metric import GAP, CharMetric

# Characters with a meaning in the display, written with a backslash when meant literally.
SPECIAL = "{}[]\\-<>"


def _listed(chars: list[str]) -> str:
    """Characters by code point, runs of three or more as a range."""
    out, k = [], 0
    chars = sorted(chars)
    while k < len(chars):
        end = k
        while end + 1 < len(chars) and ord(chars[end + 1]) == ord(chars[end]) + 1:
            end += 1
        run = chars[k : end + 1]
        out += [f"{_plain(run[0])}-{_plain(run[-1])}"] if len(run) > 2 else [_plain(c) for c in run]
        k = end + 1
    return "".join(out)


def _plain(ch: str) -> str:
    return f"\\{ch}" if ch in SPECIAL else ch


def to_display(cols, mark: int | None = None) -> str:
    """Display dialect; the 1-based column to mark is put in angle brackets."""
    out = []
    for k, col in enumerate(cols, 1):
        chars = [c for c in col if c is not GAP]
        text = f"[{_listed(chars)}]" if GAP in col else _plain(chars[0]) if len(chars) == 1 else f"{{{_listed(chars)}}}"
        out.append(f"<{text}>" if k == mark else text)
    return "".join(out)


def parse_display(text: str) -> list[frozenset]:
    """Columns of a display pattern; marks are dropped."""
    cols, k = [], 0

    def one() -> str:
        nonlocal k
        k += text[k] == "\\"
        k += 1
        return text[k - 1]

    while k < len(text):
        if text[k] in "<>":
            k += 1
            continue
        if text[k] not in "{[":
            cols.append(frozenset(one()))
            continue
        close, gap, chars = ("}", (), set()) if text[k] == "{" else ("]", (GAP,), set())
        k += 1
        while text[k] != close:
            first = one()
            if text[k] == "-" and text[k + 1] != close:
                k += 1
                chars.update(map(chr, range(ord(first), ord(one()) + 1)))
            else:
                chars.add(first)
        k += 1
        cols.append(frozenset((*chars, *gap)))
    return cols


def to_regex(cols, capture: bool = True) -> str:
    """Anchored Java and Python regex; each column is a group if captured."""
    out = []
    for col in cols:
        chars = sorted(c for c in col if c is not GAP)
        esc = "".join(f"\\{c}" if c in r"\[]^-&" else c for c in chars)
        unit = re.escape(chars[0]) if len(chars) == 1 else f"[{esc}]"
        unit += "?" if GAP in col else ""
        out.append(f"({unit})" if capture else unit)
    return f"^{''.join(out)}$"


def matches(code: Column, regex: str | Column) -> Column:
    return F.coalesce(code.rlike(regex) if isinstance(regex, str) else F.rlike(code, regex), F.lit(False))


def key_regex(code: Column, regex: str, i: int) -> Column:
    """Character at column i of a matching code by the regex's leftmost greedy reading; null for a gap or no match."""
    return F.nullif(F.regexp_extract(code, regex, i), F.lit(""))


def key_at(aligned: Column, i: int | Column) -> Column:
    """Character at column i of an aligned code."""
    return F.try_element_at(aligned, F.lit(i) if isinstance(i, int) else i)


def degap(aligned: Column) -> Column:
    return F.array_join(F.filter(aligned, lambda c: c.isNotNull()), "")


def render(aligned: Column, gap: str = "_") -> Column:
    return F.array_join(aligned, "", gap)


def fit_to(code: str, template: Template, metric: CharMetric, tie: str = "gap_late") -> list[str | None] | None:
    """A code laid out in a template's columns without changing it; None if it does not match.

    Only columns that may be gaps are left out, and a character must be of the column. Of several layouts
    the one that leaves its gaps late (or early) is taken.
    """
    n, m = len(code), len(template)
    ok = np.zeros((n + 1, m + 1), bool)
    ok[0, 0] = True
    for j, col in enumerate(template.cols, 1):
        for i in range(n + 1):
            ok[i, j] = (GAP in col and ok[i, j - 1]) or (i > 0 and code[i - 1] in col and ok[i - 1, j - 1])
    if not ok[n, m]:
        return None
    out, i = [], n
    for j in range(m, 0, -1):
        col = template.cols[j - 1]
        gap, use = GAP in col and ok[i, j - 1], i > 0 and code[i - 1] in col and ok[i - 1, j - 1]
        skip = gap and (tie == "gap_late" or not use)
        out.append(GAP if skip else code[i - 1])
        i -= not skip
    return out[::-1]


def key_of(code: str, template: Template, i: int, metric: CharMetric, how: str = "align", tie: str = "gap_late") -> str | None:
    """Key of any code at column i: by rigid alignment with the template, or by the regex."""
    if how == "regex":
        m = re.match(to_regex(template.cols), code)
        return (m[i] or None) if m else None
    laid = fit_to(code, template, metric, tie)
    if laid is None:
        t, a, b = fuse(template, leaf(code, metric), metric, tie)
        if len(t) != len(template):
            return None  # the code needs a column that the template lacks
        laid = [code[k - 1] if k else GAP for k in b]
    return laid[i - 1]
