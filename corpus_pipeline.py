"""The corpus pipeline: five stages, each written as Parquet and read again as the next one's documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from latticecube.llm import common, decontam, entries, langid, mixing, neardup, tokenout

#: No SQL expresses the learned and hashed stages; the tests hold each stage against brute force.
ORACLE_SQL = None


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without a letter, or null, have no language and go; other predictions reject nothing, as clean documents stay.

    An id that several rows share rejects only those of them that have no letter.
    """
    found = langid.identify(docs, langid.train(docs)).where(F.col("lang_pred") == langid.UNKNOWN)
    own = common.free_name(docs, "rejected")
    gone = common.written(found.select(F.col("doc_id").alias(own)).distinct(), "rejected")
    blank = ~F.coalesce(docs["text"].cast("string"), F.lit("")).rlike(r"\p{L}")
    return docs.join(common.small_side(gone), docs["doc_id"].eqNullSafe(gone[own]) & blank, "left_anti")


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of texts stays, the one of the smallest id; texts of a repeated id are judged as texts, so none is lost by its id."""
    return neardup.survivors(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.clean(docs, common.table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of the mix, one epoch at most; the document at a leaf's budget stays whole."""
    taken = mixing.mix(docs, entries.MIX, entries.MIX_SHARE, entries.mix_domain(), epochs=1, seed=entries.MIX_SEED)
    own = common.free_name(docs, "taken")
    ids = common.written(taken.select(F.col("doc_id").alias(own)).distinct(), "taken")
    return docs.join(common.small_side(ids), docs["doc_id"].eqNullSafe(ids[own]), "left_semi").where(mixing.tokens(F.col("text")) > 0)


def write_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return tokenout.token_output(docs, entries.vocab_path("word_bpe_49k.json"))


STAGES = [
    ("language_id", identify_language),
    ("near_duplicates", drop_near_duplicates),
    ("decontamination", decontaminate),
    ("mixing", mix_sources),
    ("token_output", write_ids),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        out = stage(spark, docs, sf_dir)
        docs = common.written(out, f"pipeline-{name}")
    return docs
