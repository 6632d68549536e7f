"""Streams against their batch twins, sources and sinks as round trips, SQL functions, blocks and rounds."""

import datetime

import pytest
from pyspark.sql import functions as F

from alignforge.functions import sql as names
from alignforge.operators import clean, rules
from alignforge.operators.align import block_by, dedupe, learn_tree
from alignforge.operators.rules import Thresholds, discover
from alignforge.plans import relational
from alignforge.sources import io, synth
from alignforge.sources.codes import relation
from alignforge.streaming import stream

SCHEMA = "event_id long, ts timestamp, user_id long, code string, event_type string"


@pytest.fixture(scope="module")
def events(spark, sf, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("events") / "parts")
    rows = relation(spark, sf, "event_code").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "code", "event_type")
    rows.coalesce(1).sortWithinPartitions("ts").write.parquet(path)  # files of one moment come in no set order
    return path


def drained(df, name, mode="append"):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).start()
    try:
        q.processAllAvailable()
    finally:
        q.stop()
    return df.sparkSession.table(name)


def flagged(spark, sf, events, live):
    e = stream.read_stream(spark, events, SCHEMA) if live else spark.read.parquet(events)
    return stream.flagged(e, relational.event_rules(relation(spark, sf, "event_code")), F.col("code"), "event_type")


def test_windowed_counts(spark, sf, events):
    """All closed windows of the stream are those of the batch."""
    got = {tuple(r) for r in drained(stream.violation_counts(flagged(spark, sf, events, True)), "counts").collect()}
    want = {tuple(r) for r in stream.violation_counts(flagged(spark, sf, events, False)).collect()}
    assert got <= want and len(want) - len(got) <= 2 and sum(r[2] for r in got) > 0


def test_late_rows_are_dropped(spark, tmp_path):
    t = datetime.datetime(2024, 1, 1)
    path, name = str(tmp_path / "late"), "late"

    def add(k, hours):
        spark.createDataFrame([(k, t + datetime.timedelta(hours=hours, minutes=k), 1, "AB1", "x")], SCHEMA).coalesce(1).write.mode("append").parquet(path)

    add(0, 0)
    rows = stream.read_stream(spark, path, SCHEMA).withColumn("violates", F.lit(True))
    q = stream.violation_counts(rows).writeStream.outputMode("append").format("memory").queryName(name).start()
    try:
        q.processAllAvailable()
        for k, hours in ((1, 5), (2, 0), (3, 9)):  # the second of these comes too late
            add(k, hours)
            q.processAllAvailable()
    finally:
        q.stop()
    assert [r["events"] for r in spark.table(name).where(F.col("w_start") == F.lit(t)).collect()] == [1]


def test_duplicates(spark, tmp_path):
    t = datetime.datetime(2024, 1, 1)
    spark.createDataFrame([(k % 3, t, 1, "AB1", "x") for k in range(9)], SCHEMA).write.parquet(str(tmp_path / "dup"))
    assert drained(stream.distinct_events(stream.read_stream(spark, str(tmp_path / "dup"), SCHEMA)), "dups").count() == 3


def test_claims_as_state(spark, sf, events):
    live = stream.claim_counts(stream.read_stream(spark, events, SCHEMA), F.substring("code", 1, 2), "event_type")
    got = drained(live, "claims", "update").groupBy("key", "value").agg(F.max("n").alias("n"))
    want = spark.read.parquet(events).groupBy(F.substring("code", 1, 2).alias("key"), F.col("event_type").alias("value")).agg(F.count("*").alias("n"))
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_two_streams(spark, sf, events):
    live = stream.paired(flagged(spark, sf, events, True), stream.read_stream(spark, events, SCHEMA))
    batch = stream.paired(flagged(spark, sf, events, False), spark.read.parquet(events))
    assert {tuple(r) for r in drained(live, "paired").collect()} == {tuple(r) for r in batch.collect()}


def test_generator(spark):
    a, b = (synth.coded_strings(spark, N=300, l=12, CN=10, sigma=0.1, seed=s).orderBy("rec_id").collect() for s in (1, 1))
    assert a == b and len({r["cluster"] for r in a}) == 10
    assert all(set(r["code"]) <= set(synth.ALL) and 0 < len(r["code"]) <= 12 for r in a)
    assert len({len(r["code"]) for r in a}) > 1
    still = synth.coded_strings(spark, N=200, l=12, CN=10, sigma=0.0, seed=1)
    assert still.select("code").distinct().count() == 10


def test_data_source(spark):
    synth.register(spark)
    got = spark.read.format("coded_strings").option("N", 50).option("l", 8).option("CN", 5).option("partitions", 3).load()
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, synth.coded_strings(spark, N=50, l=8, CN=5).collect()))


def test_data_source_as_stream(spark):
    synth.register(spark)
    live = spark.readStream.format("coded_strings").option("N", 50).option("l", 8).option("CN", 5).option("rowsPerBatch", 20).load()
    got = drained(live, "coded")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, synth.coded_strings(spark, N=50, l=8, CN=5).collect()))


@pytest.mark.parametrize("fmt", ["csv", "json", "text", "parquet"])
def test_code_lists(spark, tmp_path, fmt):
    df = spark.createDataFrame([("SL410",), ("a,b\"c",), ("ü-1",)], "code string")
    path = str(tmp_path / fmt)
    (df.write.option("header", True).option("escape", "\\") if fmt == "csv" else df.write).format(fmt).save(path)
    assert sorted(r[0] for r in io.read_codes(spark, path, fmt).collect()) == sorted(["SL410", "a,b\"c", "ü-1"])


def test_catalog_and_members(spark, sf, tmp_path):
    df = relation(spark, sf, "nation_code")
    tree = learn_tree(dedupe(df), tie="gap_early")
    found = discover(df, "code", ["n_regionkey"], tree, Thresholds(10, 0.9, 5, 2))
    io.write_catalog(found, str(tmp_path / "rules"), 1)
    io.write_catalog(found.limit(1), str(tmp_path / "rules"), 2)
    assert io.read_catalog(spark, str(tmp_path / "rules")).count() == 1
    assert io.read_catalog(spark, str(tmp_path / "rules"), 1).select(*found.columns).exceptAll(found).count() == 0


def test_denominators(spark, sf):
    """Gap keys are no claims, so on late ties the root's rule counts 15 of 25 tuples."""
    df = relation(spark, sf, "nation_code")
    tree = learn_tree(dedupe(df))
    for denominator, confidence in (("claims", 1.0), ("tuples", 0.6)):
        found = discover(df, "code", ["n_regionkey"], tree, Thresholds(10, 0.5, 5, 2), denominator=denominator).where("card = 25")
        assert [(r["support"], r["confidence"]) for r in found.where("support = 15").collect()] == [(15, confidence)]


def test_gap_as_key(spark):
    """Where a gap tells a value, it may be a key."""
    df = spark.createDataFrame([(f"A{k}" + ("U" if k % 2 else ""), "big" if k % 2 else "small") for k in range(10)], "code string, size string")
    tree = learn_tree(dedupe(df))
    t = Thresholds(10, 0.9, 2, 5)
    assert discover(df, "code", ["size"], tree, t).count() == 0
    assert {r["col_ix"] for r in discover(df, "code", ["size"], tree, t, gap_as_key=True).collect()} == {3}


def test_support_equal_to_the_threshold(spark):
    df = spark.createDataFrame([(f"K{'ab'[k % 2]}", "xy"[k % 2]) for k in range(10)], "code string, v string")
    found = discover(df, "code", ["v"], learn_tree(dedupe(df)), Thresholds(10, 0.9, 2, 5))
    assert [(r["support"], r["tuples"]) for r in found.collect()] == [(10, 10)]


def test_rounds_give_the_same_tree(spark):
    codes = dedupe(synth.coded_strings(spark, N=60, l=8, CN=4, sigma=0.15, seed=3))
    a, b = learn_tree(codes, algorithm="pair"), learn_tree(codes, algorithm="rounds", finish=1)
    assert relational.tree_of  # both trees by the same names
    cols = ["rep", "card", "weight", "cost_u", "pattern", "left_rep", "left_card", "right_rep", "right_card"]
    assert a.nodes.select(*cols).exceptAll(b.nodes.select(*cols)).count() == 0 and a.nodes.count() == b.nodes.count()
    assert 1 < b.counters.first()["rounds"] < 30 and b.counters.first()["fuse_evals"] < a.counters.first()["fuse_evals"]


def test_rounds_with_cost_limit_and_blocks(spark, sf):
    codes = block_by(dedupe(relation(spark, sf, "nation_code")), "signature")
    a, b = (learn_tree(codes, algorithm=x, max_cost=1.0, tie="gap_early", finish=1) for x in ("pair", "rounds"))
    assert a.nodes.select("rep", "card", "cost_u").exceptAll(b.nodes.select("rep", "card", "cost_u")).count() == 0


def test_large_blocks_go_on_in_rounds(spark):
    """Blocks above the limit and below it, in one call; the baseline, which can't be split, is refused."""
    codes = dedupe(synth.coded_strings(spark, N=60, l=8, CN=4)).withColumn("block", F.when(F.col("code") < "c", "low").otherwise("high"))
    sizes = {r["block"]: r["count"] for r in codes.groupBy("block").count().collect()}
    assert min(sizes.values()) < max(sizes.values())
    cols = ["block", "rep", "card", "weight", "cost_u", "pattern", "left_rep", "left_card", "right_rep", "right_card"]
    a, b = learn_tree(codes, algorithm="pair"), learn_tree(codes, max_block=min(sizes.values()), finish=4)
    assert a.nodes.select(*cols).exceptAll(b.nodes.select(*cols)).count() == 0 and a.nodes.count() == b.nodes.count()
    assert {r["block"]: (r["n"], r["fuse_done"]) for r in b.counters.collect()} == {k: (n, n - 1) for k, n in sizes.items()}
    with pytest.raises(Exception, match="rounds"):
        learn_tree(codes, algorithm="pair", max_block=10)


def test_scratch_needs_a_shared_folder():
    from alignforge.plans import scratch

    def session(master: str, folder: str | None):
        conf = type("Conf", (), {"get": lambda self, key, default=None: folder or default})()
        return type("Session", (), {"conf": conf, "sparkContext": type("Context", (), {"master": master})()})()

    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        scratch.shared_dir(session("spark://far:7077", None))
    with pytest.raises(ValueError, match="spark.checkpoint.dir"):
        scratch.shared_dir(session("local-cluster[2,1,512]", None))
    assert scratch.shared_dir(session("spark://far:7077", "s3a://b/c/")) == "s3a://b/c"
    assert scratch.shared_dir(session("local[4]", None)).startswith("file:")


def test_members_of_chosen_nodes_only(spark, sf):
    tree = learn_tree(dedupe(relation(spark, sf, "nation_code")), tie="gap_early")
    some = tree.nodes.where("card in (2, 3)")
    got = tree.members(only=some)
    assert got.select("rep", "card").distinct().count() == some.count()
    assert got.exceptAll(tree.members()).count() == 0 and {r["card"] for r in got.select("card").distinct().collect()} == {2, 3}


def test_rules_as_json_are_all_there(spark):
    import json

    rows = [(k, f"p{k}") for k in range(1500)]
    found = [json.loads(r["rule"]) for r in rules.rules_json(spark.createDataFrame(rows, "card long, pattern string")).collect()]
    assert sorted((x["card"], x["pattern"]) for x in found) == rows


def test_the_largest_step_of_costs_parts_clusters(spark):
    tree = learn_tree(dedupe(spark.createDataFrame([(c,) for c in ("aaa1", "aaa2", "aaa3", "99-99x", "99-98x", "99-97x")], "code string")))
    cut = tree.cut(max_cost=tree.largest_step())
    assert sorted((r["rep"], r["card"]) for r in cut.select("rep", "card").collect()) == [("99-97x", 3), ("aaa1", 3)]


def test_unseen_codes_meet_templates_by_length_and_lead(spark):
    """Codes that the tree does not hold, with and without the optional parts, and one that no template matches."""
    df = spark.createDataFrame([(f"{h}K{d}{t}", f"v{d}") for h in ("", "S") for d in range(4) for t in ("x", "y", "z")], "code string, v string")
    tree = learn_tree(dedupe(df))
    own = discover(df, "code", ["v"], tree, Thresholds(10, 0.9, 2, 2)).join(tree.roots().select("rep", "card"), ["rep", "card"], "left_semi")
    new = spark.createDataFrame([("K1w",), ("SK3x",), ("QQ-99999",), ("K2z",)], "code string")
    near = new.where("code <> 'K1w'").union(spark.createDataFrame([("SK2y",)], "code string"))
    keys = {(r["code"], r["key"]) for r in clean.code_keys(near, own, tree).collect()}
    assert {k for k, _ in keys} == {"SK3x", "K2z", "SK2y"} and ("SK3x", "3") in keys
    less = learn_tree(dedupe(df.where("code not in ('SK3x', 'K2z')")))
    own = discover(df, "code", ["v"], less, Thresholds(10, 0.9, 2, 2)).join(less.roots().select("rep", "card"), ["rep", "card"], "left_semi")
    keys = {(r["code"], r["key"]) for r in clean.code_keys(new, own, less).collect()}
    assert keys == {("SK3x", "3"), ("K2z", "2")}


def test_cleaning_of_unseen_codes(spark):
    """A code that the tree never saw is filled through the pattern it matches."""
    df = spark.createDataFrame([(f"P{d}-{k}", "abcdef"[d]) for d in range(6) for k in range(5)], "code string, v string")
    tree = learn_tree(dedupe(df))
    own = discover(df, "code", ["v"], tree, Thresholds(10, 0.9, 5, 5)).join(tree.roots().select("rep", "card"), ["rep", "card"], "left_semi")
    maps = rules.rule_map(df, "code", own, tree, ["v"])
    new = spark.createDataFrame([("P3-4", None), ("P9-9", None), ("P30-4", None), (None, None)], "code string, v string")
    seen = df.where("code <> 'P3-4'")
    tree2 = learn_tree(dedupe(seen))
    own2 = discover(seen, "code", ["v"], tree2, Thresholds(10, 0.9, 5, 4)).join(tree2.roots().select("rep", "card"), ["rep", "card"], "left_semi")
    maps2 = rules.rule_map(seen, "code", own2, tree2, ["v"])
    for t, o, m in ((tree, own, maps), (tree2, own2, maps2)):
        for resolve in ("vote", "best"):
            p = clean.predictions(clean.code_keys(new.select("code"), o, t), o, m, resolve)
            assert {r["code"]: r["v_filled"] for r in clean.impute(new, "code", "v", p).collect()} == {"P3-4": "d", "P9-9": None, "P30-4": None, None: None}


def test_sql_names(spark):
    names.register(spark)
    assert spark.sql("SELECT align_cost('ab1c', 'ab9c')").first()[0] == 0.5
    assert spark.sql("SELECT align_cost(NULL, 'a')").first()[0] is None
    assert spark.sql("SELECT align_show('T520i', 'T560')").first()[0] == "T520i|T560_"
    assert spark.sql("SELECT code_key('TL510i', '{ST}[L]{45}{126}0[i]', 3)").first()[0] == "5"
    assert [tuple(r) for r in spark.sql("SELECT * FROM align_columns('S41', '{ST}[L]{45}1')").collect()] == [(1, "S"), (2, None), (3, "4"), (4, "1")]
    assert spark.sql("SELECT column_spread(c) FROM VALUES ('1'), ('2'), (NULL) t(c)").first()[0] == 1.0
    assert spark.sql("SELECT column_pattern(c) FROM VALUES ('1'), ('2'), ('3'), (NULL) t(c)").first()[0] == "[1-3]"
    assert len(spark.sql("SELECT * FROM tree_edges('{\"left_rep\": \"a\", \"left_card\": 1, \"right_rep\": \"b\", \"right_card\": 2}')").collect()) == 2


def test_negative_control_whole_values(spark, sf):
    """A unique code decides everything and repeats nothing: the fourth measure tells."""
    from alignforge.operators.baselines import fd_measures

    r = fd_measures(relation(spark, sf, "customer_code"), "code", "c_mktsegment").first()
    assert r["confidence"] == 1.0 and r["inner_support"] == 1
