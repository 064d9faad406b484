"""A training-corpus pipeline of the operators in skewjoin.llm: documents in, token ids out.

Every stage takes and, but for the last, returns the columns of documents, others that docs has included, and
works on all rows that its predecessor kept, whatever their number: an empty table gives an empty one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from skewjoin.llm import langid, mixing, neardup, sptok, substr
from skewjoin.llm.common import stage
from skewjoin.llm.sampling import crc_mod

LEAST_LANGUAGE = 0.5


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language the network determines; `und` and unsure ones go.

    Null, empty and letterless texts are `und`.  Rows that share an id are judged one by one; null languages
    are not learned from.  Without labelled rows nothing is determined, and nothing stays.
    """
    return langid.keep_identified(docs, langid.fit(docs.where(crc_mod("doc_id", 5) != 0)), LEAST_LANGUAGE)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates (five-word shingles, similarity 0.8), the one of the smallest id.

    Texts that are null or without words are like no other and stay; of rows that share an id one stays; rows
    without an id take no part and stay.
    """
    return neardup.drop_near_duplicates(docs, 5, 80)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without passages that a document of smaller id has; n_chars follows the text.

    A text may become empty, its row stays.  Null texts stay null; rows without an id are neither cut nor looked at.
    """
    cut = substr.remove_repeats(docs)
    return cut.withColumn("n_chars", F.char_length("text").cast("long")) if "n_chars" in docs.columns else cut


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row per copy that the mixture takes, in order of training position, ties by id.

    Texts that are null or without words are not taken.  A null source is a source; rows without an id are drawn
    together, as are rows that share one.
    """
    return mixing.mixture(docs)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every row: (doc_id, n_pieces, ids). A null or empty text has none; a null id is kept."""
    ids = sptok.encode(docs, sptok.load())
    return ids.select("doc_id", F.size("ids").cast("long").alias("n_pieces"), "ids")


STAGES = [
    ("language_id", identify_language),
    ("near_dedup", drop_near_duplicates),
    ("substring_dedup", drop_repeated_passages),
    ("mixing", mix_sources),
    ("sentencepiece", encode),
]

#: The first stage is a trained network, which SQL can't express; tests/llm holds the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages one after the other over the documents table, each written and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
