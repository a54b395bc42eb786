"""The registered queries of the operators: thin digests of what the operators return."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, brown, chat, html_wrappers, lines, packing, quality, sharding, simhash, topk
from .common import documents

#: Most bytes of text in a shard.
SHARD_BYTES = 64 << 20
#: Documents that the language model is tested on.
HELD_OUT = "crc32(cast(doc_id as string)) % 7 = 2"

Query = Callable[[SparkSession, str], DataFrame]


def op1_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_wrappers.extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    model = quality.fit_labelled(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return quality.judge(docs, model)


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.round_trip(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op4_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), "vec_id % 100 = 0", 10)


def op5_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash.near_duplicates(documents(spark, sf_dir), width=3, k=3)
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def op6_fuzzy_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lines.dedup(documents(spark, sf_dir)).select("doc_id", "text", "n_lines", "n_removed")


def op7_class_model(spark: SparkSession, sf_dir: str) -> DataFrame:
    return brown.score(documents(spark, sf_dir), HELD_OUT)


def op8_extendible_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign(documents(spark, sf_dir), SHARD_BYTES)


def shards_of_256k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign(documents(spark, sf_dir), 256 << 10)


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op10_role_repair(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.repair(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


def queries() -> dict[str, Query]:
    return {
        "op1_main_text": op1_main_text,
        "op2_quality_rules": op2_quality_rules,
        "op3_byte_bpe": op3_byte_bpe,
        "op4_top_k": op4_top_k,
        "op5_simhash": op5_simhash,
        "op6_fuzzy_lines": op6_fuzzy_lines,
        "op7_class_model": op7_class_model,
        "op8_extendible_shards": op8_extendible_shards,
        "op9_packing": op9_packing,
        "op10_role_repair": op10_role_repair,
        "shards_of_256k": shards_of_256k,
    }


def _shards_sql(limit: int) -> str:
    return f"""
WITH keyed AS (
  SELECT doc_id, coalesce(strlen(text), 0) AS n_bytes,
         ('0x' || substr(md5(coalesce(CAST(doc_id AS VARCHAR), text, '')), 1, 15))::BIGINT AS k
  FROM documents),
depths AS (SELECT unnest(range(0, 61)) AS d),
sums AS (
  SELECT d, k >> (60 - d) AS p, CAST(sum(n_bytes) AS BIGINT) AS total
  FROM keyed, depths GROUP BY 1, 2 HAVING sum(n_bytes) <= {limit}),
own AS (
  SELECT doc_id, n_bytes, k, min(d) AS d
  FROM keyed, sums WHERE k >> (60 - d) = p GROUP BY 1, 2, 3)
SELECT doc_id, n_bytes, CASE WHEN own.d = 0 THEN '' ELSE lpad(bin(p), CAST(own.d AS INTEGER), '0') END AS shard,
       total AS shard_bytes, FALSE AS oversized
FROM own JOIN sums ON sums.d = own.d AND sums.p = k >> (60 - own.d)
"""


def oracle_sql() -> dict[str, str]:
    return {
        "op4_top_k": """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(1024 * CAST(x AS DOUBLE))) AS e FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_inner_product(q.e, c.e) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id),
r AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s)
SELECT * FROM r WHERE rank <= 10
""",
        "op8_extendible_shards": _shards_sql(SHARD_BYTES),
        "shards_of_256k": _shards_sql(256 << 10),
    }
