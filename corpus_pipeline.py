"""Corpus pipeline: language ID, line dedup, near-duplicate removal, mixing and tokenization of documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadsample.llm import bpe, jaccard, langid, linededup, mixing
from spreadsample.llm.common import parked, table
from spreadsample.llm.queries import vocabulary_file


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose text has a language by its likelihoods; texts without a letter, and longer ones that fit no language, go."""
    return langid.with_language(docs, vocabulary_file("piece_bpe_32k.model"))


def remove_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without later copies of repeated line runs; n_chars follows the text."""
    return linededup.dedup_lines(docs).withColumn("n_chars", F.length("text").cast("long")).select(*docs.columns)


def remove_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of five-word SimHash near duplicates, confirmed by a Jaccard similarity of 4/5 or more: that of the
    smallest id."""
    return jaccard.deduplicate(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of sources takes them, in the order of its schedule."""
    return mixing.mixed(docs)


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids of every document, and the text that they decode to."""
    return bpe.encode_and_decode(docs, vocabulary_file("byte_bpe_50k.json"))


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", remove_repeated_lines),
    ("simhash_near_dedup", remove_near_duplicates),
    ("mix_sources", mix_sources),
    ("bpe", tokenize),
]

#: SQL has not the models; tests hold the rows of run() against plain code for all stages.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each stage's rows are a Parquet table before the next one reads them."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = parked(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
