"""A training-data pipeline of five corpus operators. Each stage works on all that the one before kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from graphmoves.llm import decontaminate, langid, neardup, packing, suffix_repeats
from graphmoves.llm.common import drop_snapshot, read_table, small_batches, snapshot

#: Repeats of so many bytes, and passages of over 50 words even if their words are short (51 take 101 bytes at least).
PASSAGE_BYTES = 256
PASSAGE_WORDS = 51


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without letters and those of no learned language."""
    small_batches(spark)
    return langid.keep_known_language(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Leaves one document of each group of near copies (five-word shingles, similarity of 0.8 or more)."""
    small_batches(spark)
    return neardup.one_of_each(docs)


def suffix_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts passages out that occur more than once; a document that nothing is left of stays, with empty text."""
    small_batches(spark)
    return suffix_repeats.without_repeats(docs, PASSAGE_BYTES, words=PASSAGE_WORDS)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item."""
    small_batches(spark)
    return decontaminate.decontaminated(docs, read_table(spark, sf_dir, "benchmark"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of 2048 tokens, as records of pieces."""
    small_batches(spark)
    return packing.pack_documents(docs)


STAGES = [("language_id", language_id), ("near_dedup", near_dedup), ("suffix_dedup", suffix_dedup), ("decontamination", decontamination), ("packing", pack)]

#: SQL can't express the trained network and the tokenizer; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    old = None
    for i, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if i == len(STAGES) - 1:
            return out
        docs = snapshot(out)
        if old is not None:
            drop_snapshot(old)
        old = docs
    return docs
