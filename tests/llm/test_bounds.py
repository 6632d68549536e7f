"""Repeats, hot groups, very large values and clashing names: results by brute force, work within bounds."""

import struct
import time
import zlib

import pytest
import xxhash
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

import corpus_pipeline
from alignforge.llm import decontaminate, licenses, mixing, pii, queries, sharding, simhash, topk, warc
from test_findings import spelled


# ------------------------------------------------------------------ tiling


@settings(max_examples=80, deadline=None)
@given(st.lists(st.sampled_from("abc"), max_size=40), st.lists(st.sampled_from("abc"), min_size=5, max_size=20))
def test_both_ways_of_tiling_agree(doc, item):
    seeds = decontaminate.Seeds([(1, " ".join(item))])
    assert decontaminate.contained(seeds, " ".join(doc), 0, max_seeds=0) == decontaminate.contained(seeds, " ".join(doc), 0)


def test_repeated_words_stay_within_memory():
    seeds = decontaminate.Seeds([(1, "word " * 1000), (2, "a b " * 300)])
    began = time.perf_counter()
    assert decontaminate.contained(seeds, "word " * 20_000) == [(1, 1, 1000, 1000, 1.0)]
    assert decontaminate.contained(seeds, "a b " * 10_000) == [(2, 1, 600, 600, 1.0)]
    assert time.perf_counter() - began < 20


def test_short_items_and_several_parts(spark):
    docs = spark.createDataFrame([(1, "say hello big world now"), (2, "hello world big"), (3, "one two three four five six"), (4, None)], "doc_id long, text string")
    bench = spark.createDataFrame([("s", "Hello, big world"), ("t", "one two three four five six"), ("u", "world"), ("v", "!!")], "item_id string, text string")
    want = [(1, "s"), (1, "u"), (2, "u"), (3, "t")]
    for limit in (1 << 20, 20):
        got = decontaminate.leaks(docs, bench, limit=limit)
        assert sorted((r["doc_id"], r["item_id"]) for r in got.collect()) == want
        assert [r["doc_id"] for r in decontaminate.drop_leaks(docs, bench, limit=limit).collect()] == [4]


# ------------------------------------------------------------------ personal data

# Sentences written by hand, with the thing that is personal in each.
PERSONAL = (
    ("please contact maria.silva [at] correio [dot] org for access", "maria.silva [at] correio [dot] org"),
    ("Write to JOHN[AT]example[DOT]com today", "JOHN[AT]example[DOT]com"),
    ("mail: o_brien(at)webmail.net please", "o_brien(at)webmail.net"),
    ("send it to peter at firma dot de soon", "peter at firma dot de"),
    ("reach me: li.wei (at) example (dot) org thanks", "li.wei (at) example (dot) org"),
    ("her phone: (212) 555-0187 after six", "(212) 555-0187"),
    ("call 646-555-0133 for the keys", "646-555-0133"),
    ("tel 030 5550 1234 bis 18 Uhr", "030 5550 1234"),
    ("mobile 415.555.0199 any time", "415.555.0199"),
    ("fax: 089 5551 2345 from Munich", "089 5551 2345"),
    ("paid by amex 3782 822463 10005 last week", "3782 822463 10005"),
    ("card 378282246310005 was charged", "378282246310005"),
    ("credit card 30569309025904 on file", "30569309025904"),
    ("visa 4222222222222 expired", "4222222222222"),
    ("login from host fe80::1ff:fe23:4567:890a at noon", "fe80::1ff:fe23:4567:890a"),
    ("client address 2001:db8:85a3:8d3:1319:8a2e:370:7348 seen", "2001:db8:85a3:8d3:1319:8a2e:370:7348"),
    ("server 2001:db8::1 answered", "2001:db8::1"),
    ("ip fd00:1234::8 is blocked", "fd00:1234::8"),
)
# Sentences without anything personal that still look like it.
CLEAN = (
    "order 1234-5678-9012 has shipped", "isbn 978 316 148 for sale", "version 12.345.678 is out", "meet at noon at the bridge. then we walk", "look at chapter two dot by dot",
    "serial 12345678901234 of the pump", "the ratio is 10:20:30:40 in all", "at 12:30:45:10 the timer stopped", "page 123 456 789 of the ledger", "use std::vector and Foo::Bar here",
    "total 4500 1200 3300 in the year", "build 2024.1201.334 failed", "invoice 20240101123456 is due", "part no 555 123 456 is spare", "we arrived at home. dinner was cold",
)


def test_added_spans_on_sentences_that_the_generator_did_not_make():
    trees, cut = pii.model()
    hit = sum(any(t[a:b] == want for _, a, b, _ in pii.spans(t, trees, cut)[1]) for t, want in PERSONAL)
    wrong = [t for t in CLEAN if pii.spans(t, trees, cut)[1]]
    assert hit >= 0.9 * len(PERSONAL) and len(wrong) <= 1, (hit, wrong)


def test_ip_parts_of_any_length():
    zeros = "0" * 5000
    assert pii.base_spans(f"{zeros}.1.2.3") == [("ip", 0, 5006)] and pii.base_spans(f"1.2.3.{zeros}") == [("ip", 0, 5006)]
    assert pii.base_spans(f"{zeros}256.1.2.3") == [] and pii.base_spans("9" * 5000 + ".1.2.3") == [] and pii.base_spans(f"{zeros}255.0.00.000")


def test_generators_are_gated_by_what_they_accept():
    for text in ("x John[AT]example[DOT]com", "x john At example dot com", "x john\tat\nexample.com", "x 2001:db8::1", "x fe80::1", "x ::1:2"):
        assert pii.candidates(text), text


# ------------------------------------------------------------------ top k


def test_scores_beyond_a_long_stop_at_its_ends(spark):
    rows = [(100, [1e300, 1.0]), (1, [1e300, 0.0]), (2, [2e300, 0.0]), (3, [-1e300, 5.0]), (4, [0.0, 7.5]), (5, [1e12, 1.0]), (200, [1e12, -1e12]), (6, [1e307, 1e307]), (7, [3.0, -1e12])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    whole = {k: [int(x) * 1024 if abs(x) >= 1 else int(x * 1024 // 1) for x in v] if k != 4 else [0, 7680] for k, v in rows}
    clip = lambda s: max(-(2**63), min(2**63 - 1, s))
    want = {}
    for q in (100, 200):
        scored = sorted((-clip(sum(a * b for a, b in zip(whole[q], v))), k) for k, v in whole.items() if k != q)
        want[q] = [(k, -s) for s, k in scored]
    got = {}
    for r in topk.top_k(df).orderBy("query_id", "rank").collect():
        got.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert got == want


# ------------------------------------------------------------------ shards


def spark_hash(*longs):
    """XXH64 of whole numbers one after the other, as a signed long."""
    seed = 42
    for x in longs:
        seed = xxhash.xxh64_intdigest(struct.pack("<q", x), seed)
    return seed - (1 << 64) if seed >= 1 << 63 else seed


def test_shard_query_by_brute_force(spark, sf):
    rows = [(r["doc_id"], (r["text"] or "").encode()) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()]
    got = queries.QUERIES["op5_slot_shards"](spark, sf).collect()
    want = sorted((k, len(t) + 1, zlib.crc32(t)) for k, t in rows)
    assert sorted((r["doc_id"], r["size"], r["text_crc32"]) for r in got) == want
    slot_of = {x: spark_hash(x[0], x[2], x[1]) % sharding.N_SLOTS for x in want}
    size = {}
    for x in want:
        size[slot_of[x]] = size.get(slot_of[x], 0) + x[1]
    loads, owner = [0] * 8, {}
    for slot in sorted(size, key=lambda s: (-size[s], s)):
        owner[slot] = loads.index(min(loads))
        loads[owner[slot]] += size[slot]
    place, seen = {}, [0] * 8
    for x in sorted(want, key=lambda x: (slot_of[x], x[0], x[2], x[1])):
        shard = owner[slot_of[x]]
        place[x], seen[shard] = (shard, seen[shard]), seen[shard] + 1
    assert {(r["doc_id"], r["size"], r["text_crc32"]): (r["shard"], r["slot"]) for r in got} == place
    assert {r["law"] for r in got} == {"bytes"} and {r["grown_shard"] for r in got} == {None}


def test_a_row_that_makes_up_a_third_is_spread(spark):
    docs = spark.range(20_000).select(F.when(F.col("id") % 3 == 0, F.lit(None)).otherwise(F.col("id")).alias("doc_id"), F.when(F.col("id") % 3 == 0, "same text").otherwise(F.concat(F.lit("t"), "id")).alias("text"))
    got = sharding.shard_rows(docs)
    loads = [r["b"] for r in got.groupBy("shard").agg(F.sum("size").alias("b")).collect()]
    per_slot = got.where("doc_id is null").groupBy("virtual_slot").count().agg(F.max("count")).first()[0]
    assert got.count() == 20_000 and len(loads) == 8 and max(loads) < 1.02 * min(loads) and per_slot <= 4 * sharding.RUN
    spans = got.groupBy("shard").agg(F.min("slot"), F.max("slot"), F.count("*"), F.count_distinct("slot")).collect()
    assert all((r[1], r[2], r[3]) == (0, r[3] - 1, r[4]) for r in spans)


# ------------------------------------------------------------------ mix


def test_alike_rows_share_what_they_get(spark):
    rows = [(1, "a b c d", "s")] * 3 + [(1, "e f g h", "s")] * 2 + [(None, "x y", "t")] * 4 + [(k, "w " * 9, "t") for k in range(2, 30)] + [(None, None, None)] * 2
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    plan = mixing.mix(df, n_slots=64)
    out = mixing.mix_documents(df, n_slots=64)
    key = ["doc_id", "source", "size"]
    want = {tuple(r[c] for c in key): r["n"] for r in plan.groupBy(*key).agg(F.sum("copies").alias("n")).where("n > 0").collect()}
    got = {tuple(r[c] for c in key): r["n"] for r in out.withColumn("size", mixing.word_count(F.col("text"))).groupBy(*key).agg(F.count("*").alias("n")).collect()}
    assert got == want and plan.count() == len(rows)
    size = plan.groupBy("source").agg(F.sum("taken").alias("taken"), F.first("target").alias("target")).collect()
    assert all(abs(r["taken"] - r["target"]) <= max(1, 0.01 * r["target"]) for r in size)


def test_schedule_ranks_are_gapless(spark):
    goals = mixing.targets(spark.createDataFrame([("a", 500, 1), ("b", 300, 1), (None, 100, 1)], "source string, size long, n long"))
    blocks = mixing.blocks_given(goals, 256).collect()
    for source in {r["b_source"] for r in blocks}:
        own = sorted((r["block"], r["slot"]) for r in blocks if r["b_source"] == source)
        assert [k for k, _ in own] == list(range(len(own))) and [s for _, s in own] == sorted(s for _, s in own)


# ------------------------------------------------------------------ licenses


def test_no_rule_reaches_further_than_the_margins():
    longest = max(len(text.split()) for *_, regex in licenses.rules() for text in spelled(regex))
    assert longest <= licenses.REACH


def test_statements_at_any_place_of_a_core(spark):
    said = [("licensed under the terms of the bsd 3 clause license", "bsd-3-clause"), ("the mit license", "mit"), ("creative commons attribution 4 0 license", "cc-by-4.0"), ("cc by sa", "cc-by-sa")]
    rows = [(k * 1000 + n, "filler " * n + text + " tail" * 150, label) for k, (text, label) in enumerate(said) for n in (0, 1, 23, 24, 40, 57, 60, 62, 63, 64, 65, 100, 127, 128, 129, 200)]
    df = spark.createDataFrame(rows, "doc_id long, text string, want string")
    got = {r["doc_id"]: r["labels"] for r in licenses.scan(df).collect()}
    assert {k: got[k] for k, *_ in rows} == {k: want for k, _, want in rows}


def test_many_detections_take_linear_time(spark):
    df = spark.createDataFrame([(1, "see the mit license, apache license 2.0 and gpl 3 license " * 20_000)], "doc_id long, text string")
    began = time.perf_counter()
    r = licenses.scan(df).first()
    assert r["n_base"] == 20_000 and r["labels"] == "apache-2,gpl-3,mit" and r["last_word"] == 19_999 * 12 + 1
    assert time.perf_counter() - began < 60


# ------------------------------------------------------------------ archives


def test_hot_payloads_are_looked_up_apart(spark, monkeypatch):
    rows = [(k, "http://x.example/p", "same page " * 20) for k in range(40)] + [(100 + k, "http://x.example/q", f"pair {k // 2} " * 30) for k in range(6)] + [(200, None, "tiny")] * 3
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    want = sorted((r["page_id"], r["record_type"], str(r["refers_to"])) for r in warc.round_trip(pages).collect())
    assert sum(t == "revisit" for _, t, _ in want) == 39 + 3
    for hot, most in ((10, 100), (10, 0)):
        monkeypatch.setattr(warc, "HOT", hot), monkeypatch.setattr(warc, "HOT_MOST", most)
        assert sorted((r["page_id"], r["record_type"], str(r["refers_to"])) for r in warc.round_trip(pages).collect()) == want


def test_merge_ranges_follow_the_entries(spark, sf, monkeypatch):
    monkeypatch.setattr(warc, "RANGE", 20)
    index, root = warc.archive(spark.read.parquet(f"{sf}/pages.parquet"))
    files = {}
    for r in index.select("url_key", "ts", "page_id", F.input_file_name().alias("f")).collect():
        files.setdefault(r["f"].rsplit("/", 1)[1], []).append((r["url_key"], r["ts"], r["page_id"]))
    keys = [k for f in sorted(files) for k in files[f]]
    assert keys == sorted(keys) and len(files) > 8
    from pathlib import Path

    assert {p.name for p in Path(root.removeprefix("file:")).glob("*.warc.gz")} == {r["file"] for r in index.select("file").distinct().collect()}


# ------------------------------------------------------------------ near duplicates and stages

CLASH = "doc_id long, text string, lang string, source string, n_chars long, kept long, low long, n long, row long, __mix_id long, __mix_copies long, __mix_rows long, __mix_share long, tags map<string,int>"


def test_stages_take_clashing_names_and_maps(spark, sf):
    text = ["the quick brown fox jumps over the lazy dog again and again", "ein ganz anderer satz ueber das wetter von gestern abend", "un texte qui parle de tout autre chose que les deux autres"]
    rows = [(k, text[k % 3] + f" {k // 3}" * 3, "en", "s", 5, *[9] * 8, {"a": k, "b": 1}) for k in range(9)]
    rows += [rows[0], (0, "another text of the same id", "en", "s", 5, *[9] * 8, {"b": 1, "a": 0}), (None, text[0], "en", None, 5, *[9] * 8, None)]
    docs = spark.createDataFrame(rows, CLASH)
    for name, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, docs, sf)
        assert got.columns == docs.columns and {r["low"] for r in got.collect()} == {9}, name
        assert stage(spark, docs.limit(0), sf).count() == 0
    kept = simhash.keep_one_each(docs).collect()
    ids = [r["doc_id"] for r in kept if r["doc_id"] is not None]
    assert len(ids) == len(set(ids)) and sum(r["doc_id"] is None for r in kept) == 1
    assert sorted(map(str, kept)) == sorted(map(str, simhash.keep_one_each(docs.repartition(5)).collect()))
    assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).count() == len(rows)


def test_sessions_keep_their_arrow_limits(spark, sf):
    keys = ("spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch")
    before = [spark.conf.get(k) for k in keys]
    queries.QUERIES["op3_trie_simhash"](spark, sf).count()
    with pytest.raises(Exception):
        simhash.components(spark.range(1)).count()
    assert [spark.conf.get(k) for k in keys] == before
