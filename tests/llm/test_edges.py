"""Every operator and stage takes nulls, empty and long texts, repeated rows, empty tables and clashing extra columns."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from alignforge.llm import cotrain, decontaminate, language, licenses, mixing, pii, sharding, simhash, topk, warc

DOCS = "doc_id long, text string, lang string, source string, n_chars long, fp long, size int, slot string, task string, h int, rank int, key string, line string, u long, kept_id long, component_id long"
LONG = "lorem ipsum dolor " * 60_000
ROWS = [
    (1, "the quick brown fox jumps over the lazy dog", "en", "a", 43),
    (1, "the quick brown fox jumps over the lazy dog", "en", "a", 43),
    (2, "the quick brown fox jumps over the lazy dog", "en", None, 43),
    (3, None, None, "b", None),
    (4, "", "en", "b", 0),
    (5, " \t\n\x0b\x0c\r ", "en", "a", 6),
    (6, LONG, "la", "a", len(LONG)),
    (7, "1234 !!! ???", None, "c", 12),
    (None, "ein kurzer satz ohne nummer", "de", "c", 27),
    (None, None, None, None, None),
    (8, "ÜBER größe naïve 漢字 \U0001f600 x", "de", "c", -5),
    (9, "a" * 300_000, "en", "a", 300_000),
    (10, "1" * 200_000 + "." * 10, "en", "a", 1),
]


def frame(spark, rows):
    return spark.createDataFrame([(*r, 7, 7, "x", "x", 7, 7, "x", "x", 7, 7, 7) for r in rows], DOCS)


@pytest.fixture(scope="module")
def docs(spark):
    return frame(spark, ROWS)


@pytest.fixture(scope="module")
def empty(spark):
    return frame(spark, [])


def ids(df):
    return sorted((r["doc_id"] for r in df.collect()), key=lambda x: (x is None, x or 0))


ALL = sorted((r[0] for r in ROWS), key=lambda x: (x is None, x or 0))


def test_quality(spark, docs, empty):
    labels = spark.createDataFrame([(1, 1, 0, "x"), (1, 0, 0, "x"), (None, 1, 0, "x"), (99, 0, 0, "x"), (4, None, 0, "x")], "doc_id long, quality int, toxic int, text string")
    got = cotrain.score(docs, labels)
    assert ids(got) == ALL and {r["score"] for r in got.collect()} == {0.5}
    assert cotrain.score(empty, labels.limit(0)).count() == 0


def test_language(docs, empty):
    got = {r["doc_id"]: r for r in language.identify(docs).collect()}
    assert all(got[k]["lang_pred"] == "und" and got[k]["score"] == 0 for k in (3, 4, 5, 7))
    assert ids(language.identify(docs)) == ALL
    assert language.identify(empty).count() == 0
    kept = language.keep_identified(docs)
    assert kept.columns == docs.columns and 3 not in ids(kept) and 1 in ids(kept)


def test_near_duplicates(docs, empty):
    got = simhash.near_duplicates(docs).collect()
    assert len(got) == len(ROWS)
    by = {r["doc_id"]: r for r in got}
    assert by[1]["component_id"] == by[2]["component_id"] == 1
    assert by[3]["fingerprint"] == by[4]["fingerprint"] == by[5]["fingerprint"] == "0" * 16 and by[5]["component_id"] == 3
    assert simhash.near_duplicates(empty).count() == 0
    kept = simhash.keep_one_each(docs)
    assert kept.columns == docs.columns
    assert ids(kept).count(1) == 1 and 2 not in ids(kept) and 4 not in ids(kept) and ids(kept).count(None) == 2


def test_decontamination(spark, docs, empty):
    bench = spark.createDataFrame([(1, "quick brown fox jumps over", 5), (2, None, 5), (3, "", 5), (4, "dog", 5), (1, "quick brown fox jumps over", 5)], "item_id long, text string, coverage int")
    got = decontaminate.leaks(docs, bench)
    found = sorted((r["doc_id"], r["item_id"]) for r in got.collect())
    assert found == [(1, 1)] * 4 + [(1, 4)] * 2 + [(2, 1)] * 2 + [(2, 4)]  # item 4 is one word, matched as a whole
    assert decontaminate.leaks(docs, bench.limit(0)).count() == 0 and decontaminate.leaks(empty, bench).count() == 0
    kept = decontaminate.drop_leaks(docs, bench)
    assert kept.columns == docs.columns and kept.count() == len(ROWS) - 3


def test_mixing(docs, empty):
    got = mixing.mix(docs).collect()
    assert len(got) == len(ROWS) and all(0 <= r["taken"] <= 2 * r["size"] for r in got)
    assert mixing.mix(empty).count() == 0
    assert mixing.mix_documents(docs).columns == docs.columns and mixing.mix_documents(empty).count() == 0


def test_sharding(docs, empty):
    got = sharding.shard_rows(docs).collect()
    assert len(got) == len(ROWS)
    for s in range(8):
        own = sorted(r["slot"] for r in got if r["shard"] == s)
        assert own == list(range(len(own)))
    assert {r["doc_id"]: r["size"] for r in got}[3] == 1
    assert sharding.shard_rows(empty).count() == 0


def test_pii(docs, empty):
    got = pii.detect(docs)
    assert ids(got) == ALL and all(r["found"] == [] for r in got.where("doc_id = 3 or doc_id = 4").collect())
    assert pii.detect(empty).count() == 0


def test_licenses(docs, empty):
    got = {r["doc_id"]: r for r in licenses.scan(docs).collect()}
    assert got[3]["n_words"] == 0 and got[4]["labels"] == "" and got[4]["first_word"] is None and got[5]["n_words"] == 0
    assert got[6]["n_words"] == 180_000 and got[8]["n_words"] == 6
    assert licenses.scan(empty).count() == 0


def test_warc(spark):
    body = "<p>" + "é" * 60
    rows = [(3, "http://a.example/x", body), (1, None, body), (None, "http://a.example/x", body), (1, None, body), (4, "x", None), (5, "http://[bad\r\nurl", ""), (6, "y", "short"), (7, "y", "short")]
    pages = spark.createDataFrame([(*r, "z", "z") for r in rows], "page_id long, url string, html string, digest string, file string")
    got = sorted(map(tuple, warc.round_trip(pages).select("page_id", "payload_bytes", "record_type", "refers_to").collect()), key=str)
    assert got == sorted([(3, 123, "revisit", 1), (1, 123, "response", None), (1, 123, "response", None), (None, 123, "revisit", 1), (4, 0, "response", None), (5, 0, "response", None), (6, 5, "response", None), (7, 5, "response", None)], key=str)
    assert warc.round_trip(pages.limit(0)).count() == 0


def test_topk(spark):
    nan, inf = float("nan"), float("inf")
    rows = [(100, [1.0, 0.5]), (1, [1.0, 1.0]), (2, [1.0, 1.0]), (3, [1.0, nan]), (4, [inf, 1.0]), (5, [None, 1.0]), (6, None), (7, []), (None, [9.0, 9.0]), (8, [1.0]), (2, [1.0, 1.0])]
    df = spark.createDataFrame([(*r, 3, 3) for r in rows], "vec_id long, embedding array<float>, rank int, score int")
    got = [tuple(r) for r in topk.top_k(df).orderBy("rank").collect()]
    one = 1024 * 1024 + 512 * 1024
    assert got == [(100, 1, 1, one), (100, 2, 2, one), (100, 3, 2, one), (100, 4, 8, 1024 * 1024), (100, 5, 7, 0)]
    assert topk.top_k(df.limit(0)).count() == 0


def test_stages_keep_columns_and_take_empty_tables(spark, sf, docs, empty):
    plain = ["doc_id", "text", "lang", "source", "n_chars"]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs.select(*plain), sf).columns == plain, name
        assert stage(spark, empty.select(*plain), sf).count() == 0, name
    assert corpus_pipeline.STAGES[-1][1](spark, empty.select(*plain), sf).count() == 0


def test_null_columns(spark):
    """Whole columns of nulls."""
    df = spark.range(6).select(F.col("id").alias("doc_id"), *[F.lit(None).cast(k).alias(c) for c, k in (("text", "string"), ("lang", "string"), ("source", "string"), ("n_chars", "long"))])
    for f in (language.identify, simhash.near_duplicates, mixing.mix, sharding.shard_rows, pii.detect, licenses.scan):
        assert f(df).count() == 6
