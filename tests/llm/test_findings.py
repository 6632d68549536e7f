"""Cases that once were cut short."""

from itertools import product
from re import _parser

from pyspark.sql import functions as F

import corpus_pipeline
from alignforge.llm import language, licenses, mixing


def test_mix_serves_tiny_sources_beside_a_huge_one(spark):
    """Blocks of many times a small source's words still leave each source near its target."""
    rows = [(k, "w " * 5000, "huge") for k in range(60)] + [(1000 + k, "w " * (3 + k), f"tiny{k:03d}") for k in range(100)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    taken = {}
    for r in mixing.mix(df, n_slots=256).collect():
        n, target = taken.get(r["source"], (0, 0.0))
        taken[r["source"]] = (n + r["taken"], r["target"])
    assert len(taken) == 101
    for source, (n, target) in taken.items():
        assert target > 0 and abs(n - target) <= max(0.01 * target, 1), (source, n, target)


def spelled(regex):
    """Every text that a regex without unbounded repeats matches; what it looks around at is left out."""

    def parts(tokens):
        return ["".join(x) for x in product(*map(one, tokens))]

    def one(token):
        kind, arg = str(token[0]), token[1]
        if kind == "LITERAL":
            return [chr(arg)]
        if kind == "IN":
            return [chr(k) for op, v in arg for k in ([v] if str(op) == "LITERAL" else range(v[0], v[1] + 1))]
        if kind == "BRANCH":
            return [x for b in arg[1] for x in parts(b)]
        if kind == "SUBPATTERN":
            return parts(arg[3])
        if kind == "MAX_REPEAT":
            return ([""] if arg[0] == 0 else []) + parts(arg[2])
        return [""]

    return parts(_parser.parse(regex))


def test_every_license_alternative_passes_its_keyword_and_a_gate():
    for _, _, label, words, regex in licenses.rules():
        for text in spelled(regex):
            line = f" {text} "
            assert any(w in line for w in ([words] if isinstance(words, str) else words)), (label, words, text)
            assert any(g in line for g in licenses.GATES), (label, text)


def test_licenses_by_their_long_names(spark):
    cases = [("released under the Python Software Foundation License", "psf-2"), ("European Union Public Licence", "eupl-1.2"), ("Zero-Clause BSD license", "0bsd"), ("PSF license", "psf-2"), ("0BSD license", "0bsd")]
    df = spark.createDataFrame([(k, t) for k, (t, _) in enumerate(cases)], "doc_id long, text string")
    got = {r["doc_id"]: r["labels"] for r in licenses.scan(df).collect()}
    assert [got[k] for k in range(len(cases))] == [x for _, x in cases]


def test_license_places_beside_characters_of_two_units(spark):
    """Word numbers count words, whatever characters stand before the phrase."""
    cases = [("\U0001F600 " * 5 + "the mit license", 5, 5), ("\U0001D49E" * 9 + " the mit license x cc by nc \U0001F600 ", 1, 5), ("the mit license \U0001F600 the mit license", 0, 4)]
    df = spark.createDataFrame([(k, t) for k, (t, *_) in enumerate(cases)], "doc_id long, text string")
    got = {r["doc_id"]: (r["first_word"], r["last_word"]) for r in licenses.scan(df).collect()}
    assert [got[k] for k in range(len(cases))] == [(a, b) for _, a, b in cases]


def test_language_stage_gives_the_language_found(spark, sf):
    """Rows that state no language or a wrong one get that of their text; no row with a letter is lost."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    wrong = F.when(F.col("doc_id") % 10 == 3, F.lit(None)).when(F.col("doc_id") % 10 == 7, F.when(F.col("lang") == "en", "fr").otherwise("en"))
    dirty = docs.withColumn("lang", F.when(F.col("doc_id") % 10 == 3, F.lit(None)).otherwise(F.coalesce(wrong, "lang")))
    got = {r["doc_id"]: r["lang"] for r in corpus_pipeline.language_id(spark, dirty, sf).select("doc_id", "lang").collect()}
    score = {r["doc_id"]: r["score"] for r in language.identify(dirty).collect()}
    rows = docs.select("doc_id", "lang").collect()
    clear = [r for r in rows if score[r["doc_id"]] >= language.MIN_SCORE]
    assert len(clear) > 900 and sum(got[r["doc_id"]] != r["lang"] for r in clear) <= 0.005 * len(clear)
    faint = [r for r in rows if r["doc_id"] in got and score[r["doc_id"]] < language.MIN_SCORE and r["doc_id"] % 10 not in (3, 7)]
    assert faint and all(got[r["doc_id"]] == r["lang"] for r in faint)
    assert set(got) == {d for d, x in score.items() if x > 0} and None not in got.values()
