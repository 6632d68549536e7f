"""Operator 9, native: license scan by ordered signature rules.

A text becomes its lower-cased words joined by single spaces. Rules are regexes over that line, built
from license names and the phrases that licenses are stated in; each has keywords, a priority and a
confidence. A detection inside another one of the same or a higher priority is suppressed.

No rule matches more than REACH words, so a line is read in cores of CORE words with margins that hold
whatever a detection that starts in the core can touch. A core is screened by gate words and by one regex of
all rules; what passes, each text of a core once, meets the rules whose keywords it holds. Work and memory
are linear in the text, however many detections are in it.

Everything is one projection per row: no shuffle, no join, no Python. Defined results: null and empty
texts have no words and no labels; a document's repeated detections count once per label; repeated rows
get equal rows; extra columns are ignored. Ties of equal intervals and priorities go to the rule that
comes first.
"""

from __future__ import annotations

import json
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Words of a core, and most words that any rule matches.
CORE, REACH = 64, 24
SEPARATORS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"

# The contract's base phrases and their labels.
BASE = {"the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}

# Label, keyword (or one for each alternative), name as a regex over words, SPDX identifier as words.
NAMES = (
    ("mit", "mit", r"mit", "mit"),
    ("mit-0", "mit", r"mit (?:0|no attribution)", "mit 0"),
    ("x11", "x11", r"x11", "x11"),
    ("apache-1.1", "apache", r"apache (?:software )?(?:licen[cs]e )?(?:version |v)?1 1", "apache 1 1"),
    ("apache-2", "apache", r"apache (?:software )?(?:licen[cs]e )?(?:version |v ?)?2(?: 0)?", "apache 2 0"),
    ("gpl-1", "gpl", r"(?:gnu )?gpl ?(?:version |v ?)?1(?: 0)?", r"gpl 1 0(?: only| or later)?"),
    ("gpl-2", "gpl", r"(?:gnu )?gpl ?(?:version |v ?)?2(?: 0)?", r"gpl 2 0(?: only| or later)?"),
    ("gpl-3", "gpl", r"(?:gnu )?gpl ?(?:version |v ?)?3(?: 0)?", r"gpl 3 0(?: only| or later)?"),
    ("gpl-2", "general public", r"gnu general public licen[cs]e (?:as published by the free software foundation )?(?:either )?version 2", "gplv2"),
    ("gpl-3", "general public", r"gnu general public licen[cs]e (?:as published by the free software foundation )?(?:either )?version 3", "gplv3"),
    ("lgpl-2.1", "lgpl", r"(?:gnu )?lgpl ?(?:version |v ?)?2(?: 1| 0)?", r"lgpl 2 [01](?: only| or later)?"),
    ("lgpl-3", "lgpl", r"(?:gnu )?lgpl ?(?:version |v ?)?3(?: 0)?", r"lgpl 3 0(?: only| or later)?"),
    ("agpl-3", "agpl", r"(?:gnu )?agpl ?(?:version |v ?)?3(?: 0)?", r"agpl 3 0(?: only| or later)?"),
    ("mpl-1.1", "mozilla", r"mozilla public licen[cs]e (?:version |v)?1 1", "mpl 1 1"),
    ("mpl-2", "mozilla", r"mozilla public licen[cs]e (?:version |v)?2(?: 0)?", "mpl 2 0"),
    ("bsd-2-clause", "bsd", r"(?:bsd 2 clause|2 clause bsd|simplified bsd|freebsd)", "bsd 2 clause"),
    ("bsd-3-clause", "bsd", r"(?:bsd 3 clause|3 clause bsd|new bsd|modified bsd|revised bsd)", "bsd 3 clause"),
    ("bsd-4-clause", "bsd", r"(?:bsd 4 clause|4 clause bsd|original bsd)", "bsd 4 clause"),
    ("0bsd", ("0bsd", "zero clause"), r"(?:0bsd|zero clause bsd)", "0bsd"),
    ("bsd", "bsd", r"bsd(?: style)?", "bsd"),
    ("isc", "isc", r"isc", "isc"),
    ("zlib", "zlib", r"zlib(?: libpng)?", "zlib"),
    ("cc0-1.0", "cc0", r"cc0(?: 1 0)?", "cc0 1 0"),
    ("cc-by-3.0", "attribution", r"creative commons attribution 3 0", "cc by 3 0"),
    ("cc-by-4.0", "attribution", r"creative commons attribution 4 0", "cc by 4 0"),
    ("cc-by-sa-3.0", "attribution", r"creative commons attribution share ?alike 3 0", "cc by sa 3 0"),
    ("cc-by-sa-4.0", "attribution", r"creative commons attribution share ?alike 4 0", "cc by sa 4 0"),
    ("cc-by-nc-4.0", "attribution", r"creative commons attribution non ?commercial 4 0", "cc by nc 4 0"),
    ("cc-by-nd-4.0", "attribution", r"creative commons attribution no ?deriv(?:ative)?s 4 0", "cc by nd 4 0"),
    ("cc-by-nc-sa-4.0", "attribution", r"creative commons attribution non ?commercial share ?alike 4 0", "cc by nc sa 4 0"),
    ("cc-by-nc-nd-4.0", "attribution", r"creative commons attribution non ?commercial no ?deriv(?:ative)?s 4 0", "cc by nc nd 4 0"),
    ("cc-by", "cc by", r"cc by(?! (?:nc|sa|nd))", r"cc by(?! (?:nc|sa|nd))"),
    ("cc-by-sa", "cc by sa", r"cc by sa", "cc by sa"),
    ("cc-by-nd", "cc by nd", r"cc by nd", "cc by nd"),
    ("cc-by-nc-sa", "cc by nc sa", r"cc by nc sa", "cc by nc sa"),
    ("cc-by-nc-nd", "cc by nc nd", r"cc by nc nd", "cc by nc nd"),
    ("epl-1", "eclipse", r"eclipse public (?:licen[cs]e )?(?:version |v ?)?1(?: 0)?", "epl 1 0"),
    ("epl-2", "eclipse", r"eclipse public (?:licen[cs]e )?(?:version |v ?)?2(?: 0)?", "epl 2 0"),
    ("cddl-1", "cddl", r"cddl(?: (?:version |v)?1 [01])?", r"cddl 1 [01]"),
    ("artistic-1", "artistic", r"artistic (?:licen[cs]e )?1 0", "artistic 1 0"),
    ("artistic-2", "artistic", r"artistic (?:licen[cs]e )?2 0", "artistic 2 0"),
    ("unlicense", "unlicense", r"unlicense", "unlicense"),
    ("wtfpl", "wtfpl", r"wtfpl", "wtfpl"),
    ("bsl-1.0", "boost", r"boost software", "bsl 1 0"),
    ("postgresql", "postgresql", r"postgresql", "postgresql"),
    ("psf-2", ("psf", "python software"), r"(?:psf|python software foundation)", r"(?:psf|python) 2 0"),
    ("ruby", "ruby", r"ruby", "ruby"),
    ("php-3", "php", r"php", r"php 3 0[01]?"),
    ("openssl", "openssl", r"openssl", "openssl"),
    ("eupl-1.2", ("eupl", "european union"), r"(?:eupl|european union public)(?: licen[cs]e)?(?: v?1 2)?", "eupl 1 2"),
    ("odbl-1", "open database", r"open database", "odbl 1 0"),
    ("pddl-1", "public domain dedication", r"public domain dedication", "pddl 1 0"),
    ("ofl-1.1", "sil", r"sil open font", "ofl 1 1"),
    ("ms-pl", "microsoft", r"microsoft public", "ms pl"),
    ("ms-rl", "microsoft", r"microsoft reciprocal", "ms rl"),
    ("vim", "vim", r"vim", "vim"),
    ("ncsa", "ncsa", r"(?:university of illinois )?ncsa(?: open source)?", "ncsa"),
    ("afl-3", "academic", r"academic free(?: licen[cs]e)?(?: v?(?:ersion )?3 0)?", "afl 3 0"),
    ("osl-3", "open software", r"open software(?: licen[cs]e)?(?: v?(?:ersion )?3 0)?", "osl 3 0"),
    ("ecl-2", "educational", r"educational community", "ecl 2 0"),
    ("upl-1", "universal permissive", r"universal permissive", "upl 1 0"),
    ("busl-1.1", "business source", r"business source", "busl 1 1"),
    ("sspl-1", "server side", r"server side public", "sspl 1 0"),
    ("elastic-2", "elastic", r"elastic(?: licen[cs]e)? 2 0", "elastic 2 0"),
)

# How a license is stated; priority, confidence, phrase around {name} or {id}.
STATED = (
    (4, 1.0, r"spdx licen[cs]e identifier {id}"),
    (3, 0.95, r"(?:licen[cs]ed|released|distributed|available|published|provided|covered) under (?:the )?(?:terms of (?:the )?)?{name}(?: licen[cs]e)?"),
    (2, 0.9, r"{name} licen[cs]e"),
    (1, 0.8, r"licen[cs]e (?:is )?(?:the )?{name}"),
    (1, 0.7, r"{name} (?:terms|copyright notice)"),
)

# Whole phrases; label, keyword, priority, confidence, regex.
PHRASES = (
    ("apache-2", "apache org", 3, 0.95, r"apache org licenses license 2 0"),
    ("gpl-2", "gnu org", 3, 0.9, r"gnu org licenses (?:old licenses )?gpl 2 0"),
    ("gpl-3", "gnu org", 3, 0.9, r"gnu org licenses gpl 3 0"),
    ("mit", "permission is hereby granted", 3, 0.95, r"permission is hereby granted free of charge to any person obtaining a copy"),
    ("isc", "permission to use", 3, 0.9, r"permission to use copy modify and or distribute this software for any purpose"),
    ("bsd", "redistribution and use", 3, 0.9, r"redistribution and use in source and binary forms with or without modification"),
    ("cc-by", "creativecommons org", 3, 0.95, r"creativecommons org licenses by [1-4] [05]"),
    ("cc-by-sa", "creativecommons org", 3, 0.95, r"creativecommons org licenses by sa [1-4] [05]"),
    ("cc-by-nc", "creativecommons org", 3, 0.95, r"creativecommons org licenses by nc [1-4] [05]"),
    ("cc-by-nc", "cc by nc", 2, 0.9, r"cc by nc"),
    ("cc-by-nc-sa", "cc by nc sa", 2, 0.9, r"cc by nc sa"),
    ("cc-by-nc-nd", "cc by nc nd", 2, 0.9, r"cc by nc nd"),
    ("cc-by-sa", "cc by sa", 2, 0.9, r"cc by sa"),
    ("cc-by-nd", "cc by nd", 2, 0.9, r"cc by nd"),
    ("cc0-1.0", "creativecommons org", 3, 0.95, r"creativecommons org publicdomain zero 1 0"),
    ("gpl-2", "general public", 2, 0.9, r"(?:gnu )?general public licen[cs]e (?:version |v ?)2(?: 0)?"),
    ("gpl-3", "general public", 2, 0.9, r"(?:gnu )?general public licen[cs]e (?:version |v ?)3(?: 0)?"),
    ("lgpl-2.1", "lesser general", 3, 0.9, r"(?:gnu )?lesser general public licen[cs]e (?:version |v ?)2 1"),
    ("lgpl-3", "lesser general", 3, 0.9, r"(?:gnu )?lesser general public licen[cs]e (?:version |v ?)3(?: 0)?"),
    ("agpl-3", "affero", 3, 0.9, r"(?:gnu )?affero general public licen[cs]e (?:version |v ?)3(?: 0)?"),
    ("mpl-2", "mozilla", 2, 0.9, r"mozilla public licen[cs]e (?:version |v ?)2(?: 0)?"),
    ("public-domain", "public domain", 1, 0.7, r"(?:released into|dedicated to|placed in|in) the public domain"),
    ("proprietary", "all rights reserved", 1, 0.6, r"all rights reserved"),
    ("commons-clause", "commons clause", 2, 0.9, r"commons clause"),
)

# A document without any of these can match no rule.
GATES = ("licen", " under ", "spdx", "cc by", "creativecommons", "apache org", "gnu org", "permission ", "redistribution and use", "public domain", "rights reserved", "commons clause", " terms", "copyright notice")


def rules() -> list[tuple[int, float, str, tuple[str, ...], str]]:
    """(priority, confidence, label, keywords, regex) of every rule, in order."""
    out = [(p, c, label, word, x) for label, word, p, c, x in PHRASES]
    for label, word, name, ident in NAMES:
        for p, c, phrase in STATED:
            keyword = "spdx" if "{id}" in phrase else word
            out.append((p, c, label, keyword, phrase.replace("{name}", f"(?:{name})").replace("{id}", f"(?:{ident})")))
    return [(p, c, label, (word,) if isinstance(word, str) else word, f"(?<![^ ])(?:{x})(?![^ ])") for p, c, label, word, x in out]


def screen() -> str:
    """One regex that matches wherever some rule does."""
    return "(?<![^ ])(?:" + "|".join(dict.fromkeys(x.removeprefix("(?<![^ ])").removesuffix("(?![^ ])") for *_, x in rules())) + ")(?![^ ])"


def _rules_column() -> Column:
    """The rules as one constant; the optimizer folds it."""
    rows = [{"p": p, "c": c, "label": label, "words": words, "x": x, "i": i} for i, (p, c, label, words, x) in enumerate(rules())]
    return F.from_json(F.lit(json.dumps(rows)), "array<struct<p:int,c:double,label:string,words:array<string>,x:string,i:int>>")


def _places(line: Column, regex: Column) -> Column:
    """(s, e) of all matches in a core, in order, 0-based code points: the pieces between matches tell where they stand."""
    hits, gaps = F.regexp_extract_all(line, regex, F.lit(0)), F.split(line, regex)
    walked = F.aggregate(
        F.arrays_zip(hits.alias("hit"), F.slice(gaps, 1, F.greatest(F.size(hits), F.lit(1))).alias("gap")),
        F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<s:int,e:int>>").alias("found")),
        lambda a, x: F.struct(
            (a["at"] + F.length(x["gap"]) + F.length(x["hit"])).alias("at"),
            F.concat(a["found"], F.array(F.struct((a["at"] + F.length(x["gap"])).alias("s"), (a["at"] + F.length(x["gap"]) + F.length(x["hit"])).alias("e")))).alias("found"),
        ),
        lambda a: a["found"],
    )
    return F.when(F.size(hits) > 0, walked).otherwise(F.array().cast("array<struct<s:int,e:int>>"))


def _kept(found: Column, lo: Column, hi: Column) -> Column:
    """Labels and best confidence of the detections that start from lo to below hi and that no other one suppresses.

    Detections come by start, longest first, so one is contained exactly if the furthest end seen so far
    among its priority or higher reaches its own end.
    """
    top = max(p for p, *_ in rules())
    state = F.struct(F.array_repeat(F.lit(-1), top).alias("reach"), F.array().cast("array<string>").alias("labels"), F.lit(0.0).alias("score"))

    def step(s: Column, d: Column) -> Column:
        inside = (F.element_at(s["reach"], d["p"]) >= d["e"]) | (d["s"] < lo) | (d["s"] >= hi)
        return F.struct(
            F.transform(s["reach"], lambda r, k: F.when(k < d["p"], F.greatest(r, d["e"])).otherwise(r)).alias("reach"),
            F.when(inside, s["labels"]).otherwise(F.array_union(s["labels"], F.array(d["label"]))).alias("labels"),
            F.when(inside, s["score"]).otherwise(F.greatest(s["score"], d["c"])).alias("score"),
        )

    return F.aggregate(found, state, step, lambda s: F.struct(s["labels"].alias("labels"), s["score"].alias("score")))


def lined(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, and line: lower-cased words joined by spaces, null unless a gate word is in it."""
    words = docs.select("doc_id", F.btrim(F.regexp_replace(F.coalesce("text", F.lit("")), SEPARATORS, " "), F.lit(" ")).alias("words"))
    n = F.when(F.col("words") == "", 0).otherwise(F.octet_length("words") - F.octet_length(F.replace("words", F.lit(" "), F.lit(""))) + 1)
    low = words.select("doc_id", "words", n.cast("long").alias("n_words"), F.concat(F.lit(" "), F.lower("words"), F.lit(" ")).alias("any_case"))
    open_ = F.lit(False)
    for g in GATES:
        open_ = open_ | F.contains("any_case", F.lit(g))
    upper = "".join(map(chr, range(65, 91)))
    return low.select("doc_id", "n_words", F.when(open_, F.translate("words", upper, upper.lower())).alias("line"))


def _cores(words: Column) -> Column:
    """(text, lo, hi) of the screened cores: the words of a core with their margins, and where in the text a core's own words are."""
    at = F.transform(F.sequence(F.lit(0), F.floor((F.size(words) - 1) / CORE).cast("int")), lambda k: k * CORE)

    def cut(k: Column) -> Column:
        before = F.array_join(F.slice(words, F.greatest(F.lit(1), k + 1 - REACH), F.least(k, F.lit(REACH))), " ")
        own = F.array_join(F.slice(words, k + 1, F.lit(CORE)), " ")
        after = F.array_join(F.slice(words, k + 1 + CORE, F.lit(2 * REACH)), " ")
        lo = F.when(k > 0, F.length(before) + 1).otherwise(0)
        return F.struct(F.concat(F.when(k > 0, F.concat(before, F.lit(" "))).otherwise(F.lit("")), F.rtrim(F.concat_ws(" ", own, after))).alias("text"), lo.alias("lo"), (lo + F.length(own)).alias("hi"))

    def passes(c: Column) -> Column:
        text = F.concat(F.lit(" "), c["text"], F.lit(" "))
        return reduce(lambda a, b: a | b, [F.contains(text, F.lit(g)) for g in GATES]) & F.rlike(c["text"], F.lit(screen()))

    return F.array_distinct(F.filter(F.transform(at, cut), passes))


def _judged(core: Column) -> Column:
    """Labels and best confidence of one core."""
    some = F.transform(
        F.filter(_rules_column(), lambda r: F.exists(r["words"], lambda w: F.contains(core["text"], w))),
        lambda r: F.transform(_places(core["text"], r["x"]), lambda m: F.struct(m["s"].alias("s"), (-m["e"]).alias("back"), (-r["p"]).alias("first"), r["i"].alias("i"), m["e"].alias("e"), r["p"].alias("p"), r["c"].alias("c"), r["label"].alias("label"))),
    )
    return _kept(F.array_sort(F.flatten(some)), core["lo"], core["hi"])


def _base(line: Column, phrase: str, label: str) -> Column:
    """(n, first, last, label) of a base phrase: its places and the word numbers of the outermost. The phrases can't overlap themselves."""
    spaces = lambda x: (F.octet_length(x) - F.octet_length(F.replace(x, F.lit(" "), F.lit("")))).cast("long")
    regex = f"(?<![^ ]){phrase}(?![^ ])"
    n = F.regexp_count(line, F.lit(regex)).cast("long")
    first = spaces(F.regexp_extract(line, f"(?s)^(.*?){regex}", 1))  # regexp_instr counts characters beyond U+FFFF twice
    last = spaces(line) - len(phrase.split()) + 1 - spaces(F.regexp_extract(line, f"(?s)^.*(?<![^ ]){phrase}(?![^ ])(.*)$", 1))
    found = F.struct(n.alias("n"), first.alias("first"), last.alias("last"), F.lit(label).alias("label"))
    return F.when(F.contains(line, F.lit(phrase)) & (n > 0), F.array(found)).otherwise(F.array().cast("array<struct<n:bigint,first:bigint,last:bigint,label:string>>"))


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: words, base places, and the labels that stand after suppression."""
    line = F.col("line")
    rows = lined(docs).select("doc_id", "n_words", F.concat(*[_base(line, *x) for x in BASE.items()]).alias("base"), F.split(line, " ").alias("words"))
    # words is a column of its own, as a lambda works out anew for each element what it does not get as one
    rows = rows.select("doc_id", "n_words", "base", _cores(F.col("words")).alias("cores"))
    rows = rows.select("doc_id", "n_words", "base", F.when(F.size("cores") > 0, F.transform("cores", _judged)).alias("kept"))
    base_labels = F.array_sort(F.coalesce(F.col("base.label"), F.array().cast("array<string>")))
    labels = F.array_sort(F.array_union(base_labels, F.coalesce(F.flatten("kept.labels"), F.array().cast("array<string>"))))
    return rows.select(
        "doc_id", "n_words", F.coalesce(F.aggregate("base.n", F.lit(0).cast("long"), lambda a, x: a + x), F.lit(0).cast("long")).alias("n_base"),
        F.array_min("base.first").alias("first_word"), F.array_max("base.last").alias("last_word"),
        F.array_join(base_labels, ",").alias("base_labels"), F.array_join(labels, ",").alias("labels"),
        F.greatest(F.coalesce(F.array_max("kept.score"), F.lit(0.0)), F.when(F.size("base") > 0, F.lit(0.9)).otherwise(F.lit(0.0))).alias("score"),
    )
