"""The corpus pipeline: language, near-duplicates, benchmark passages, private data, packing.

Every stage works on all rows that the one before kept; all but the last keep the columns of ``documents``. An empty
table goes through all stages and gives no rows; further columns are kept, whatever their names; ties and repeated rows are
said at each stage."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spanweave.llm import decontamination, language_id, near_duplicates, packing, pii
from spanweave.session import stored

#: A document's language is taken as known if at least this share of its letters agrees.
LEAST_SHARE = 0.4


def keep_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with letters of which at least ``LEAST_SHARE`` is in one language; that language becomes ``lang``.

    Null texts, empty ones and those without letters go; null ``lang`` is not learned from; repeated rows are judged alike;
    very long texts are read in windows."""
    return language_id.keep_known(docs, LEAST_SHARE)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates, the least doc_id; of rows with one doc_id and one text, one.

    Texts without words and rows without doc_id stay."""
    return near_duplicates.first_of_each(docs)


def drop_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a benchmark passage; null and empty texts have none, repeated rows are judged alike."""
    return decontamination.clean(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def hide_private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, private values replaced by pseudonyms (equal values alike); ``n_chars`` follows the text, null for null."""
    return pii.rewrite(docs).withColumn("n_chars", F.length("text").cast("long"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in sequences; a null text counts as empty (its end mark alone), repeated rows are packed each."""
    return packing.pack(docs)


STAGES = [
    ("language", keep_language),
    ("near_duplicates", drop_near_duplicates),
    ("benchmark", drop_benchmark),
    ("private", hide_private),
    ("packing", pack),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = stored(docs, name)
    return docs
