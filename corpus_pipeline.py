"""A corpus pipeline of five stages: language ID, quality, near duplicates, decontamination, tokens.

Each stage takes (spark, docs, sf_dir) and works on all that the one before kept. All but the last return the columns of
documents. `run` writes what a stage returns to the shared folder and reads it back for the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from rankspark import shipping
from rankspark.llm import bpe, decontamination, langid, neardup, quality
from rankspark.llm.common import stored, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the language model takes for one of its languages."""
    shipping.ensure(spark)
    tagged = langid.predict(docs, langid.train(docs), COLUMNS)
    return tagged.where("accepted").select(*COLUMNS)


def good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose quality score is 0.3 or more. The labels' own texts come from the whole table."""
    shipping.ensure(spark)
    model = quality.train(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    rated = quality.rated(docs, model, COLUMNS)
    return rated.where("predicted = 1").select(*COLUMNS)


def distinct(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group that shares 0.8 of its 5-word shingles."""
    shipping.ensure(spark)
    return neardup.deduplicated(docs, k=5, percent=80).select(*COLUMNS)


def uncontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a window of the benchmark."""
    return decontamination.clean(docs, table(spark, sf_dir, "benchmark")).select(*COLUMNS)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document (bytes of little-endian 32-bit integers), with digests of ids and decoded text."""
    import public_tokenizers

    shipping.ensure(spark)
    return bpe.encoded(docs, public_tokenizers.path("word_bpe_49k.json"), ["doc_id", "lang", "source"], with_ids=True)


STAGES = [("language_id", language), ("quality", good), ("near_duplicates", distinct), ("decontamination", uncontaminated), ("bpe", tokens)]

#: No SQL: models and tokens have no SQL form. Tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
