"""A corpus pipeline of five stages; each takes the documents its predecessor kept.

All stages but the last return the columns of ``documents``.  Null ids, repeated rows, empty tables and
very long texts are handled as the operators' docstrings say.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erblock.llm import byte_bpe, mixing, ngram_join, quality_rules, suffix_dedup

#: A mix, tokens and bytes of repeats have no SQL of the same rows here: the stages are tested against
#: brute force instead.
ORACLE_SQL = None


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the production policy keeps."""
    return quality_rules.kept_rows(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class."""
    return ngram_join.keep_one(docs)


def repeats(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without the byte strings of 200 that occur elsewhere; a character that a cut goes through goes whole,
    a document with nothing left goes, and n_chars follows a text that was cut.  Other texts stay as they are, null too."""
    cut = suffix_dedup.remove_repeats(docs, with_text=True)
    was_cut = F.col("n_removed") > 0
    kept = cut.where(~was_cut | (F.length("kept_text") > 0))
    n_chars = F.when(was_cut, F.length("kept_text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("row.n_chars"))
    changed = {"text": F.col("kept_text"), "n_chars": n_chars}
    return kept.select(*[changed[c].alias(c) if c in changed else F.col("row")[c].alias(c) for c in docs.columns])


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """As many copies of each document as the mix takes."""
    return mixing.repeated(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of ids and decoded bytes of every document."""
    return byte_bpe.digests(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [("quality_rules", quality), ("ngram_jaccard_join", near_duplicates), ("suffix_array_dedup", repeats), ("mixing", mix), ("byte_bpe", encode)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
    return docs


def queries() -> dict:
    return {"pipeline": run}


def oracle_sql() -> dict[str, str]:
    return {}
