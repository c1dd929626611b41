"""Corpus pipeline: quality filter, exact dedup, near dedup, mixing, tokenisation.

Every stage reads all that the one before it kept.  All but the last return the
columns of ``documents``; the last returns one row of piece ids per document.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from entlink.llm import exact_dedup, piece_transducer, quality_ftrl, raking_mix, simhash_trie
from entlink.llm.queries import tokenizer_path
from entlink.storage import bounded_batches, materialize, table

TOKEN_SHARE = 0.8


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier does not reject; null and empty texts are scored as texts without words, repeated rows alike."""
    bounded_batches(spark)
    weights = quality_ftrl.fit(docs, table(spark, sf_dir, "labels"))
    rows = docs.select(F.struct("*").alias("row"), F.col("text").alias("text"))
    return quality_ftrl.with_score(rows, weights).where("score >= 0.5").select("row.*")


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the one with the smallest identifier; null counts as empty, and of repeated rows one stays."""
    return exact_dedup.survivors(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of documents with similar sets of five-word shingles (0.8 or more) the one with the smallest identifier.

    Rows without identifier stay, texts without words are one class, and a repeated identifier goes or stays with all its rows.
    """
    bounded_batches(spark)
    classes = simhash_trie.similar_classes(docs)
    gone = materialize(classes.where("doc_id > component_id").select("doc_id").distinct(), "near-gone")
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A sample of ``TOKEN_SHARE`` of all tokens with tempered source, language and topic shares; null source or language is a category."""
    bounded_batches(spark)
    return raking_mix.sampled(docs, budget=TOKEN_SHARE)


def pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece identifiers of every document, none for null and empty texts."""
    bounded_batches(spark)
    found = piece_transducer.encode_documents(docs, tokenizer_path("piece_bpe_32k.model"))
    return found.select(F.col("id").alias("doc_id"), "n_pieces", "ids_crc32", "round_trip", "ids")


STAGES = [("quality", quality), ("exact_dedup", exact), ("near_dedup", near), ("mixing", mix), ("sentencepiece", pieces)]

#: Training, components and raking have no SQL form; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return docs
