"""The registered queries of this subpackage: each applies one operator to its whole table."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from eqmat.llm import byte_bpe, chat, language, packing, personal, quality, sharding, simhash, toxicity, vectors
from eqmat.storage import table

#: Bytes of text in a shard: small enough that the given tables make many shards.
SHARD_BYTES = 1 << 20


def _fold(column: str, parts: int):
    """crc32 of an id as text, modulo parts."""
    return F.pmod(F.crc32(F.col(column).cast("string").cast("binary")), F.lit(parts))


def surrogate_key(spark: SparkSession) -> str:
    """The secret of the session; without one, a fixed word that serves for the synthetic tables only."""
    return spark.conf.get("spark.eqmat.surrogateKey", None) or "not a secret: synthetic tables only"


def op1_extendible_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.assign_shards(table(spark, sf_dir, "documents"), SHARD_BYTES)


def op2_simhash_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op3_personal_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal.replace_personal(table(spark, sf_dir, "documents").select("doc_id", "text"), surrogate_key(spark))


def op4_toxicity_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.train(docs, labels.where(_fold("doc_id", 5) != 0))
    scored = toxicity.score(docs, model)
    return scored.select("doc_id", (_fold("doc_id", 5) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = language.train(docs.where(_fold("doc_id", 4) != 2))
    return language.predict(docs.select("doc_id", "text"), model).select("doc_id", (_fold("doc_id", 4) == 2).alias("held_out"), "lang_pred", "score")


def op6_byte_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return byte_bpe.round_trip(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op7_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.assess(table(spark, sf_dir, "documents")).drop("d2")


def op8_embedding_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors.near_duplicates(table(spark, sf_dir, "embeddings"))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))


def op10_chat_transcripts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.format_conversations(table(spark, sf_dir, "conversations"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_extendible_shards, op2_simhash_near_duplicates, op3_personal_surrogates, op4_toxicity_scores, op5_language_id, op6_byte_bpe_round_trip, op7_quality_rules, op8_embedding_near_duplicates, op9_best_fit_packing, op10_chat_transcripts)
    return {f.__name__: f for f in own}


#: h, shards and pages as in sharding.py; a bucket splits as long as its bytes pass the limit.
_OP1 = f"""
WITH RECURSIVE sized AS (
  SELECT doc_id, coalesce(strlen(text), 0)::BIGINT AS n_bytes,
         right(lpad(bin(('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null')), 1, 15))::BIGINT), 60, '0'), 60) AS bits
  FROM documents),
depths AS (SELECT unnest(range(0, 21))::INT AS depth),
levels AS (SELECT depth, left(bits, depth) AS shard, sum(n_bytes)::BIGINT AS shard_bytes FROM sized, depths GROUP BY 1, 2)
SELECT s.doc_id, s.n_bytes, l.shard, l.depth, l.shard_bytes
FROM sized s JOIN levels l ON l.shard = left(s.bits, l.depth)
WHERE l.shard_bytes <= {SHARD_BYTES}
  AND (l.depth = 0 OR EXISTS (SELECT 1 FROM levels u WHERE u.depth = l.depth - 1 AND u.shard = left(s.bits, l.depth - 1) AND u.shard_bytes > {SHARD_BYTES}))
"""


_OP8 = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS e, sqrt(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[])) AS n FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL),
link AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id
         WHERE a.n > 0 AND b.n > 0 AND list_dot_product(a.e, b.e) / (a.n * b.n) >= 0.93),
reach AS (SELECT a, b FROM link UNION SELECT r.a, l.b FROM reach r JOIN link l ON r.b = l.a),
least AS (SELECT a, min(b) AS m FROM reach GROUP BY a), degree AS (SELECT a, count(*) AS n FROM link GROUP BY a)
SELECT e.vec_id, coalesce(d.n, 0)::BIGINT AS n_links, least(e.vec_id, coalesce(l.m, e.vec_id)) AS component_id,
       e.vec_id <= coalesce(l.m, e.vec_id) AS kept
FROM embeddings e LEFT JOIN degree d ON d.a = e.vec_id LEFT JOIN least l ON l.a = e.vec_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_extendible_shards": _OP1, "op8_embedding_near_duplicates": _OP8}
