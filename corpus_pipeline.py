"""The corpus pipeline: stages over documents, each written as Parquet and read again by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from catalog_dedup.llm import language_id, lattice, mixing, near_copies, quality_rules
from catalog_dedup.llm.common import stash
from catalog_dedup.llm.queries import piece_table


#: Least language score of a document that stays; documents without a letter (und) always go.
LEAST_LANGUAGE_SCORE = 0.3


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents in no learned language. The model learns from the labels outside its held-out fold."""
    told = language_id.identify(docs, docs.columns)
    return told.filter((told["lang_pred"] != "und") & (told["score"] >= LEAST_LANGUAGE_SCORE)).select(*docs.columns)


def rules_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that fail the base rules or lie beyond the fences of their language and source."""
    return quality_rules.apply_rules(docs, docs.columns).filter("kept").select(*docs.columns)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document stays of each group linked by a Jaccard similarity of 0.8 or more between sets of five-word shingles."""
    return near_copies.one_of_each(docs)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row per epoch of each document that the mix takes."""
    return mixing.mix(docs)


def sentencepiece_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Ids of every document, checked by decoding them."""
    return lattice.encode(docs, piece_table(), ["doc_id", "lang", "source"])


STAGES = [
    ("language ID", language_stage),
    ("quality rules", rules_stage),
    ("SimHash near-dedup", near_dedup_stage),
    ("mixing sources to target weights", mixing_stage),
    ("SentencePiece encoding", sentencepiece_stage),
]

#: Language ID, fingerprints and the lattice are beyond SQL; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = stash(docs, "stage-" + name.replace(" ", "-"))
    return docs
