"""Each stage on its own input, against plain Python."""

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from alignforge.llm import decontaminate, simhash
from test_brute_force import plain_components, plain_simhash, plain_tiles


@pytest.fixture(scope="module")
def stages(spark, sf, tmp_path_factory):
    out, docs = {}, spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        path = str(tmp_path_factory.mktemp("stage") / name)
        stage(spark, docs, sf).write.parquet(path)
        out[name] = (docs, docs := spark.read.parquet(path))
    return out


def pairs(stages, name):
    before, after = stages[name]
    return before.toPandas(), after.toPandas()


def test_language_keeps_lettered_texts(stages):
    before, after = pairs(stages, "language_id")
    assert set(after.doc_id) == {d for d, t in zip(before.doc_id, before.text) if any(c.isalpha() for c in t or "")}


def test_one_of_each_group(stages):
    before, after = pairs(stages, "near_dedup")
    ids = before.doc_id.tolist()
    label = plain_components(ids, np.array([plain_simhash(t) for t in before.text], np.uint64))
    assert sorted(after.doc_id) == sorted(set(label.tolist()))


def test_no_benchmark_left(stages, sf):
    before, after = pairs(stages, "decontamination")
    bench = [decontaminate.words(t) for (t,) in duckdb.connect().execute(f"SELECT text FROM '{sf}/benchmark.parquet'").fetchall()]
    grams = [{tuple(b[j : j + 5]) for j in range(len(b) - 4)} for b in bench]
    gone = set(before.doc_id) - set(after.doc_id)
    for d, t in zip(before.doc_id, before.text):
        doc = decontaminate.words(t)
        own = {tuple(doc[i : i + 5]) for i in range(len(doc) - 4)}
        hit = any(g & own and plain_tiles(doc, b) >= 0.5 * len(b) for b, g in zip(bench, grams))
        assert (d in gone) == hit


def test_mix_is_near_its_targets(stages):
    before, after = pairs(stages, "source_mix")
    words = lambda t: len((t or "").split())
    size = before.assign(n=before.text.map(words)).groupby("source").n.sum()
    got = after.assign(n=after.text.map(words)).groupby("source").n.sum()
    assert after.doc_id.value_counts().max() <= 2 and abs(got.sum() - 1.5 * size.sum()) < 0.1 * size.sum()


def test_shards_hold_all(stages):
    before, after = pairs(stages, "sharding")
    assert len(before) == len(after) and set(after.law) == {"bytes"}
    load = after.groupby("shard")["size"].sum()
    assert len(load) == 8 and load.max() - load.min() < 0.01 * load.max()


def test_chunked_walk_is_the_same():
    r = np.random.default_rng(1)
    v = np.unique(r.integers(0, 1 << 20, 3000, dtype=np.uint64))
    spans, top = simhash.tables(5)[0]
    assert (simhash.restored(simhash.arranged(v, spans), spans) == v).all()
