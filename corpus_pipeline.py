"""A training corpus from `documents`: language ID, line dedup, near-dedup, decontamination, BPE encoding.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before kept; its result is written as Parquet and read
again. All but the last return the columns of `documents`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordwork.llm import bpe_codec, decontaminate, language_id, line_dedup, near_dedup
from ordwork.llm.common import Scratch, table
from ordwork.llm.queries import tokenizer_path

NEAR_WORDS, NEAR_SIMILARITY = 5, 0.8


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language can't be told (null or no letter) go; labels are only used for fitting."""
    model = language_id.fit(docs.where(~language_id.held_out()))
    return language_id.select_known(docs, model)


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines under later occurrences of three-line windows go, and documents of which nothing is left."""
    done = line_dedup.dedup_lines(docs)
    left = done.where((F.col("n_removed") == 0) | (F.col("n_removed") < F.col("n_lines")))
    return left.withColumn("n_chars", F.char_length("text").cast("long")).select(*docs.columns)


def dedup_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each near-duplicate group stays.

    Texts link if their five-word shingles have Jaccard similarity NEAR_SIMILARITY or more. SimHash finds candidates that are verified by
    their texts; an exact search finds what it misses, so all such pairs are found or joined by others.
    """
    return near_dedup.keep_one(docs, width=NEAR_WORDS, similarity=NEAR_SIMILARITY)


def decontaminate_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of ten words of a benchmark item go."""
    return decontaminate.remove_documents(docs, table(spark, sf_dir, "benchmark"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each text, their number, and whether decoding gives the text back."""
    return bpe_codec.encode(docs, tokenizer_path())


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", dedup_lines),
    ("near_dedup", dedup_near),
    ("decontamination", decontaminate_documents),
    ("bpe_encoding", encode),
]

#: Language models, fingerprints' probes and tokenisation are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, scratch = table(spark, sf_dir, "documents"), Scratch(spark, "pipeline")
    for name, stage in STAGES:
        docs = scratch.save(stage(spark, docs, sf_dir), name)
    return docs
