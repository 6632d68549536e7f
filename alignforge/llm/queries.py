"""Registered queries of the ten operators and their DuckDB SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import cotrain, licenses, pii, warc
from .common import table
from .decontaminate import leaks
from .language import identify
from .mixing import GOLDEN, MAX_EPOCHS, N_SLOTS, SHARE, TOLERANCE, mix
from .sharding import shard_rows
from .simhash import near_duplicates
from .topk import top_k


def op1_cotrained_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cotrain.score(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_hyperdim_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(table(spark, sf_dir, "documents"))


def op3_trie_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def op7_string_tiling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_maxscore_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings"))


def op4_warc_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(table(spark, sf_dir, "pages"))


def op8_boosted_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = pii.detect(table(spark, sf_dir, "documents"))
    base = F.filter("found", lambda x: x["base"])
    joined = lambda a: F.array_join(F.transform(a, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    count = lambda kind: F.size(F.filter(base, lambda x: x["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return found.select("doc_id", *map(count, pii.KINDS), F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("found")).alias("spans"))


def op9_license_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def op5_slot_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_rows(table(spark, sf_dir, "documents"))


def op6_golden_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents"))


QUERIES = {
    "op1_cotrained_quality": op1_cotrained_quality,
    "op2_hyperdim_language": op2_hyperdim_language,
    "op3_trie_simhash": op3_trie_simhash,
    "op7_string_tiling": op7_string_tiling,
    "op10_maxscore_topk": op10_maxscore_topk,
    "op4_warc_merge": op4_warc_merge,
    "op5_slot_shards": op5_slot_shards,
    "op6_golden_mix": op6_golden_mix,
    "op8_boosted_pii": op8_boosted_pii,
    "op9_license_signatures": op9_license_signatures,
}

OP6_SQL = f"""
WITH rows AS (
  SELECT doc_id, source, coalesce(len(regexp_extract_all(text, '[^\\x20\\x09-\\x0D]+')), 0)::BIGINT AS size,
         md5('mix|' || coalesce(doc_id::VARCHAR, '')) AS key
  FROM documents),
per AS (SELECT source, sum(size)::BIGINT AS source_size FROM rows GROUP BY source),
weighed AS (
  SELECT *, [5.0, 2.0, 1.0][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3]::DOUBLE AS weight,
         (sum(source_size) OVER ())::DOUBLE * {SHARE} AS budget, source_size * {MAX_EPOCHS}::DOUBLE AS cap FROM per),
levels AS (
  SELECT *, (budget - coalesce(sum(cap) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
         / sum(weight) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM weighed),
goals AS (
  SELECT source, source_size, budget,
         round(least(cap, weight * coalesce(first_value(CASE WHEN level <= cap / weight THEN level END IGNORE NULLS) OVER (ORDER BY cap / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING), 'infinity'::DOUBLE)), 6) AS target FROM levels),
spans AS (
  SELECT source, greatest(1, ceil(budget / {N_SLOTS}))::BIGINT AS b, budget,
         sum(target) OVER (ORDER BY source NULLS LAST) / sum(target) OVER () AS hi, lead(source) OVER (ORDER BY source NULLS LAST) AS nx,
         row_number() OVER (ORDER BY source NULLS LAST) AS k, count(*) OVER () AS n
  FROM goals WHERE target > 0),
edges AS (
  SELECT source, b, budget, coalesce(lag(hi) OVER (ORDER BY k), 0) AS lo, CASE WHEN k = n THEN 2.0 ELSE hi END AS hi FROM spans),
points AS (SELECT range AS slot, range * {GOLDEN}::DOUBLE + 0.5 - floor(range * {GOLDEN}::DOUBLE + 0.5) AS u FROM range({N_SLOTS})),
ranks AS (
  SELECT e.source, b, p.slot, row_number() OVER (PARTITION BY e.source ORDER BY p.slot) - 1 AS block FROM points p JOIN edges e ON p.u >= e.lo AND p.u < e.hi
  WHERE p.slot < ceil(e.budget / e.b)),
blocks AS (SELECT source, count(*) * any_value(b) AS given FROM ranks GROUP BY source),
plan AS (
  SELECT g.source, source_size, target, greatest(1, ceil(budget / {N_SLOTS}))::BIGINT AS b,
         least(CASE WHEN abs(coalesce(given, 0) - target) > target * {TOLERANCE} THEN round(target)::BIGINT ELSE coalesce(given, 0) END, source_size * {MAX_EPOCHS})::BIGINT AS given
  FROM goals g LEFT JOIN blocks b ON g.source IS NOT DISTINCT FROM b.source),
placed AS (
  SELECT *, coalesce(sum(size) OVER (PARTITION BY source ORDER BY key, doc_id, size ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS start FROM rows)
SELECT p.doc_id, p.source, p.size, q.source_size, q.target,
       (greatest(0, least(size, given - start)) + greatest(0, least(size, given - start - source_size)))::BIGINT AS taken,
       ((given > start + size // 2)::INT + (given > start + source_size + size // 2)::INT)::INT AS copies,
       CASE WHEN given > start THEN coalesce(r.slot, {N_SLOTS}) END::BIGINT AS slot
FROM placed p JOIN plan q ON p.source IS NOT DISTINCT FROM q.source
LEFT JOIN ranks r ON r.source IS NOT DISTINCT FROM p.source AND r.block = start // q.b
"""

OP10_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * x::DOUBLE)::BIGINT) AS c FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
pairs AS (
  SELECT q.vec_id AS query_id, d.vec_id, list_sum(list_transform(list_zip(q.c, d.c), lambda z: coalesce(z[1] * z[2], 0)))::BIGINT AS score
  FROM v q JOIN v d ON q.vec_id <> d.vec_id WHERE q.vec_id % 100 = 0)
SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id)::INT AS rank, vec_id, score FROM pairs
QUALIFY rank <= 10
"""

OP4_SQL = """
WITH p AS (SELECT page_id, coalesce(html, '') AS body, octet_length(encode(coalesce(html, '')))::BIGINT AS n FROM pages),
d AS (SELECT page_id, n, sha256(body) AS h, min(page_id) OVER (PARTITION BY body) AS f FROM p)
SELECT page_id, n AS payload_bytes, h AS payload_digest, CASE WHEN n < 100 OR page_id = f THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN n < 100 OR page_id = f THEN NULL ELSE f END AS refers_to
FROM d
"""

ORACLES = {
    "op4_warc_merge": OP4_SQL,
    "op10_maxscore_topk": OP10_SQL,
    "op6_golden_mix": OP6_SQL,
}
