"""The registered queries of the operators, with production parameters, over whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_chunks, debruijn, decontaminate, exact_dedup, langid, pii, sharding, simhash, suffix_dedup, token_counts
from .common import documents

WORD_VOCABULARY, BYTE_VOCABULARY = "word_bpe_49k.json", "byte_bpe_50k.json"
SHARDS, TABLE_SIZE = [f"shard-{i:02d}" for i in range(16)], 2039
PII_KEY = "replace-this-key"


def vocabulary(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeated_bytes(documents(spark, sf_dir))


def op2_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_groups(documents(spark, sf_dir), shingle=4, radius=4, blocks=7, choose=3)


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.place(documents(spark, sf_dir).select("doc_id"), F.col("doc_id"), SHARDS, TABLE_SIZE)


def op4_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(documents(spark, sf_dir))


def op5_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.replace_entities(documents(spark, sf_dir).select("doc_id", "text"), PII_KEY)


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return debruijn.remove_repeated_words(documents(spark, sf_dir))


def op7_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(documents(spark, sf_dir))


def op8_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(documents(spark, sf_dir), vocabulary(WORD_VOCABULARY))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def op10_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_chunks.encode_digest(documents(spark, sf_dir), vocabulary(BYTE_VOCABULARY))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    ops = [op1_suffix_array_dedup, op2_simhash_near_dedup, op3_sharding, op4_language_id, op5_pii_surrogates, op6_substring_dedup, op7_exact_dedup, op8_token_counts, op9_decontamination, op10_bpe]
    return {f.__name__: f for f in ops} | {"pipeline": pipeline}


_EXACT = r"""
WITH n AS (SELECT doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') AS t FROM documents),
g AS (SELECT t, min(doc_id) AS keep_id, count(*) AS group_size FROM n GROUP BY t)
SELECT n.doc_id, g.keep_id, g.group_size, n.doc_id = g.keep_id AS kept, sha256(n.t) AS text_sha256
FROM n JOIN g ON n.t = g.t
"""

_SPANS = r"""
WITH w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
p AS (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 18, 1))) AS i FROM w),
s AS (SELECT doc_id, i, row_number() OVER (PARTITION BY array_to_string(ws[i:i + 19], ' ') ORDER BY doc_id, i) AS nth FROM p),
c AS (SELECT DISTINCT doc_id, unnest(range(i, i + 20)) AS j FROM s WHERE nth > 1),
r AS (SELECT doc_id, list(j) AS js FROM c GROUP BY doc_id)
SELECT w.doc_id, CAST(len(ws) AS BIGINT) AS n_words, CAST(len(coalesce(js, [])) AS BIGINT) AS n_removed,
  sha256(coalesce(array_to_string(list_filter(ws, lambda x, k: NOT list_contains(coalesce(js, []), k)), ' '), '')) AS kept_sha256
FROM w LEFT JOIN r ON w.doc_id = r.doc_id
"""


def sharding_sql(shards: int = len(SHARDS), size: int = TABLE_SIZE) -> str:
    """The turns of the shards as a recursion over a list of slots."""
    return f"""
WITH RECURSIVE o AS (
  SELECT list(CAST('0x' || substr(md5('offset:' || n), 1, 15) AS BIGINT) % {size} ORDER BY n) AS offs,
    list(CAST('0x' || substr(md5('stride:' || n), 1, 15) AS BIGINT) % {size - 1} + 1 ORDER BY n) AS strides
  FROM (SELECT 'shard-' || lpad(CAST(i AS VARCHAR), 2, '0') AS n FROM range({shards}) t(i))),
f AS (
  SELECT 0 AS k, list_transform(range({size}), lambda x: -1) AS slots, CAST(NULL AS BIGINT) AS slot
  UNION ALL
  SELECT k + 1, list_transform(slots, lambda v, i: CASE WHEN i - 1 = pick THEN k % {shards} ELSE v END), pick
  FROM (SELECT k, slots, (offs[k % {shards} + 1] + strides[k % {shards} + 1] *
      list_filter(range({size}), lambda j: slots[(offs[k % {shards} + 1] + j * strides[k % {shards} + 1]) % {size} + 1] = -1)[1]) % {size} AS pick
    FROM f, o WHERE k < {size}) x),
m AS (SELECT slot, CAST((k - 1) % {shards} AS INTEGER) AS shard FROM f WHERE k > 0)
SELECT d.doc_id, CAST(m.slot AS INTEGER) AS slot, m.shard
FROM (SELECT doc_id, CAST('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), '')), 1, 15) AS BIGINT) % {size} AS s FROM documents) d
JOIN m ON d.s = m.slot
"""


def oracle_sql() -> dict[str, str]:
    return {"op3_sharding": sharding_sql(), "op6_substring_dedup": _SPANS, "op7_exact_dedup": _EXACT}
