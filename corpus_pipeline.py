"""Training-corpus pipeline: language ID, line dedup, near-duplicate removal, suffix-array dedup, packing.

STAGES lists (name, function); each function takes (spark, docs, sf_dir) and returns a DataFrame that is written as
Parquet and read again as the next one's docs.  All but the last return the columns of documents.  run() chains them over
the documents of sf_dir with tables in the shared scratch folder in between.

All stages: extra columns pass through up to the last, whatever their names; an empty table stays empty; texts of any
length are read whole; rows without doc_id take no part in comparisons and stay.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pullgraph.llm import language, lines, minhash, packing, suffixes
from pullgraph.session import materialize, release

#: Words per shingle of the near-duplicate stage.
SHINGLE = 5


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drop documents without an identified language; the network learns from the labelled rows of docs.

    Null texts and texts without a letter go, and those whose best probability is hardly above an even guess; everything
    goes if no row is labelled.  A null lang is filled in.  Rows that repeat are judged alike.
    """
    return language.keep_identified(docs, language.fit(docs))


def dedup_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Take out lines that repeat, exactly or nearly, a line of an earlier place by (doc_id, line number).

    A document of which nothing is left goes; null and empty texts and texts without a word stay.  Rows that repeat a
    doc_id share the places of their lines, so neither loses its only copy.
    """
    return lines.drop_lines(docs, lines.line_classes(docs))


def dedup_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keep the document with the smallest doc_id of each group of near-duplicates.

    Null and empty texts and texts without a word have no duplicates and stay.  Rows that repeat the kept doc_id stay.
    """
    groups = minhash.near_duplicates(docs, SHINGLE)
    gone = groups.filter(~F.col("kept")).select("doc_id").distinct()
    return docs.join(gone.hint("shuffle_hash"), "doc_id", "left_anti").select(*docs.columns)


def dedup_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cut passages of 50 words that stand in a document with a smaller doc_id too.

    A document of which no word is left goes; null, empty and short texts stay as they are.  Rows that repeat a doc_id are
    one document and are cut alike.
    """
    return suffixes.cut_passages(docs, suffixes.repeated_passages(docs))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token windows of all documents that are left; a null or empty text is its end id alone, rows that repeat are
    packed as often as they occur."""
    import public_tokenizers

    return packing.pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("language_id", identify_language),
    ("line_dedup", dedup_lines),
    ("minhash_near_dedup", dedup_near),
    ("suffix_array_dedup", dedup_passages),
    ("packing", pack),
]

#: No SQL: a trained network, components and packing cannot be stated in it.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    before = None
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
        release(before)
        before = docs
    return STAGES[-1][1](spark, docs, sf_dir)
