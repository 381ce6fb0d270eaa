"""The queries opN_<name> and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pyspark.sql import functions as F

from . import language_id, lattice, mixing, nn_descent, pieces, quality_classifier, quality_rules, simhash, token_counts, token_output, url_filters
from .common import remainder
from .oracles import SQL


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = quality_classifier.fit(docs, table(spark, sf_dir, "labels"))
    held_out = (remainder(F.col("doc_id"), quality_classifier.FOLDS) == quality_classifier.HELD_OUT).alias("held_out")
    return quality_classifier.score(docs, model, ["doc_id"]).select("doc_id", held_out, "score", "predicted")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.apply_rules(table(spark, sf_dir, "documents"), ["doc_id"])


def op3_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.duplicate_classes(table(spark, sf_dir, "documents"))


def op4_nearest_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nn_descent.neighbours(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"))


def piece_table() -> pieces.PieceTable:
    import public_tokenizers

    return pieces.load(public_tokenizers.path("piece_bpe_32k.model"))


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), piece_table(), ["doc_id"])


def op6_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lattice.encode(table(spark, sf_dir, "documents"), piece_table(), ["doc_id"])


def op7_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_sizes(table(spark, sf_dir, "documents"))


def op8_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    manifest = token_output.write_shards(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json"))
    return token_output.read_shards(manifest, digest=True)


def op9_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    held_out = (remainder(F.col("doc_id"), language_id.FOLDS) == language_id.HELD_OUT).alias("held_out")
    return language_id.identify(table(spark, sf_dir, "documents"), ["doc_id"]).select("doc_id", held_out, "lang_pred", "score")


#: The rules that op10 applies, as host, path, verdict.
URL_RULES = [("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block")]

#: The URLs that op10 blocks where no rule fits; roots stand for their sites.
LISTED_URLS = ["https://ads-track.example.org/", "http://cheap-pills.example.net:80", "https://Free-Bets.example.org/?", "https://cheap-pills.example.org"]


def op10_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    rules = spark.createDataFrame(URL_RULES, "host string, path string, verdict string")
    listed = spark.createDataFrame([(u,) for u in LISTED_URLS], "url string")
    return url_filters.judge(table(spark, sf_dir, "pages").select("page_id", "url"), rules, ["page_id"], listed=listed)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_quality_classifier, op2_quality_rules, op3_simhash_near_dedup, op4_nearest_neighbours, op5_token_counts, op6_sentencepiece, op7_mix_sources, op8_token_output, op9_language_id, op10_url_filters)}
ORACLES: dict[str, str] = {k: v for k, v in SQL.items() if k in QUERIES}
