"""A corpus pipeline of training-data operators: each stage works on all that the stage before it kept."""

from __future__ import annotations

import functools
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from duelspark.llm import bpe, langid, mixing, pii, setsketch
from duelspark.llm.common import materialise, small_batches, table, unmaterialise


Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


def _frugal(stage: Stage) -> Stage:
    """The stages share their executors, whose heaps are full grown by the second one; so batches for Python workers are small."""

    @functools.wraps(stage)
    def run(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        small_batches(spark)
        return stage(spark, docs, sf_dir)

    return run


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a letter, or whose language scores below an even guess, go."""
    return langid.accepted(docs, langid.train(docs))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates the document with the smallest doc_id stays."""
    return setsketch.without_copies(docs)


def pseudonymise(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Personal data in the texts become pseudonyms of the same format."""
    return pii.pseudonymise(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents are taken as often as the rates say that bring the domains' tokens to their target shares."""
    return mixing.resampled(docs, table(spark, sf_dir, "labels"))


def encode_bytes(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every document, checked by decoding them: counts and digests."""
    import public_tokenizers

    return bpe.round_trip(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES: list[tuple[str, Stage]] = [
    ("language", _frugal(identify_language)),
    ("near_duplicates", _frugal(drop_near_duplicates)),
    ("pii", _frugal(pseudonymise)),
    ("mixing", _frugal(mix_sources)),
    ("byte_bpe", _frugal(encode_bytes)),
]

#: The stages train a classifier, sketch sets and permute numbers by keyed hashes, which SQL cannot express; tests hold them against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages on documents; each stage's result is written and read again, and goes when the next one's is there.

    An empty table gives an empty result; null texts go with the language stage, which finds no letter in them; repeated rows of a
    doc_id stay or go together; columns beyond those of documents are carried to the last stage.
    """
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        done = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            done = materialise(done, f"pipeline-{name}")
            if k:
                unmaterialise(docs)
        docs = done
    return docs
