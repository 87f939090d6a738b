"""Driver queries of the operators and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpecount, common, decontam, langid, mixing, neardup, pii, sharding, tokenout, topk, toxicity


def vocab_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op2_bit_sliced_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = topk.quantised(common.table(spark, sf_dir, "embeddings"), 64)
    return topk.top_k(vectors.where(F.col("vec_id") % 20 == 0), vectors, 20)


def op3_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokenout.token_output(common.table(spark, sf_dir, "documents"), vocab_path("word_bpe_49k.json"))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpecount.count_tokens(common.table(spark, sf_dir, "documents"), vocab_path("byte_bpe_50k.json"))


def op8_bottom_k_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(common.table(spark, sf_dir, "documents"))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    return langid.identify(docs, langid.train(docs))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.train(docs, common.table(spark, sf_dir, "labels")))


def op9_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontam.contaminated(common.table(spark, sf_dir, "documents"), common.table(spark, sf_dir, "benchmark"))


#: The mix of the query and the pipeline: three domains by the number in a source's name.
MIX = {"domain": {"d0": 0.5, "d1": 0.3, "d2": 0.2}, "lang": {"en": 0.55, "de": 0.15, "fr": 0.15, "es": 0.15}, "source": {None: 1.0}}
MIX_SHARE, MIX_SEED = 0.6, 17
DOMAIN_SQL = "'d' || (CAST(coalesce(nullif(regexp_extract(source, '([0-9]{1,9})$', 1), ''), '0') AS BIGINT) % 3)"


def mix_domain():
    number = F.coalesce(F.nullif(F.regexp_extract("source", r"([0-9]{1,9})$", 1), F.lit("")), F.lit("0")).cast("long")
    return F.when(F.col("source").isNotNull(), F.concat(F.lit("d"), (number % 3).cast("string")))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(common.table(spark, sf_dir, "documents"), MIX, MIX_SHARE, mix_domain(), epochs=2, seed=MIX_SEED)


def op1_pii_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The key comes from whoever owns the corpus; this one is for these synthetic tables."""
    return pii.checked(common.table(spark, sf_dir, "documents"), b"latticecube synthetic tables")


ARRIVALS = 8


def op5_size_tiered_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents arrive in eight parts, are compacted, and are read from the last version.

    ``compacted`` says that merges took place, that each was one commit after the arrivals', that fewer shards are left, and that no tier has a run to merge.
    """
    store, arrived, merges = sharding.sharded(common.table(spark, sf_dir, "documents"), common.scratch(spark, "shards"), ARRIVALS, target_bytes=64 << 20, smallest=1 << 20)
    shards = store.manifest()["shards"]
    done = merges > 0 and store.version() == ARRIVALS + merges and len(shards) < arrived and not store.plan(shards)
    return store.read().select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.md5(F.col("text").cast("binary")).alias("text_md5"), "lang", "source", F.lit(done).alias("compacted"))


SQL_SHARDS = "SELECT doc_id, CAST(strlen(text) AS BIGINT) AS n_bytes, md5(text) AS text_md5, lang, source, true AS compacted FROM documents"

SQL_TOPK = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS DOUBLE)) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), scored AS (
  SELECT q.vec_id AS query_id, c.vec_id, CAST(list_dot_product(q.v, c.v) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v)
  WHERE q.vec_id % 20 = 0
), placed AS (
  SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM scored
)
SELECT query_id, rank, vec_id, score FROM placed WHERE rank <= 20
"""


def queries() -> dict:
    made = (op1_pii_surrogates, op5_size_tiered_shards, op2_bit_sliced_topk, op3_token_output, op4_mixing, op6_token_counts, op7_toxicity, op8_bottom_k_near_duplicates, op9_decontamination, op10_language_id)
    return {f.__name__: f for f in made}


def oracle_sql() -> dict[str, str]:
    return {"op2_bit_sliced_topk": SQL_TOPK, "op5_size_tiered_shards": SQL_SHARDS, "op4_mixing": mixing.oracle(MIX, MIX_SHARE, DOMAIN_SQL, 2, MIX_SEED), "op9_decontamination": decontam.oracle()}
