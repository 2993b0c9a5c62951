"""From raw documents to token ids: quality, boilerplate lines, near duplicates, source mix, byte-level BPE.

Each stage reads what its predecessor wrote and returns the columns of
documents, but for the last, which returns the encoded documents. Texts that a
stage changes get their n_chars anew. An empty table passes every stage.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from callweave.llm import bpe, linededup, mixing, nearcopies, quality
from callweave.llm.common import cut, table
from callweave.llm.queries import MIX, domain_of

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier accepts; it learns from the labelled documents among them."""
    return quality.drop_low_quality(docs, table(spark, sf_dir, "labels"))


def strip_boilerplate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without the boilerplate lines of their source."""
    cleaned = linededup.drop_boilerplate(docs)
    length = F.when(F.col("n_dropped") > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))
    return cleaned.withColumn("n_chars", length).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The document with the smallest id of each group of near duplicates: fingerprints within 2 bits, or five-word shingles alike at 0.8."""
    return nearcopies.drop_near_copies(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents taken for the target weights, each once at most."""
    return mixing.mix(docs, domain_of(F.col("source")), **{**MIX, "max_epochs": 1}, tell=False)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, with counts and digests of ids and of the decoded bytes."""
    import public_tokenizers

    return bpe.encode_texts(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [
    ("quality classifier", keep_quality),
    ("line dedup", strip_boilerplate),
    ("simhash near-dedup", drop_near_copies),
    ("source mixing", mix_sources),
    ("byte-level bpe", encode),
]

#: Learning, fingerprints and tokenisation are beyond SQL; tests hold each stage against a plain version instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; each result but the last is written and read again."""
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
