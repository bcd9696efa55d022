"""The registered queries of the text operators, with production parameters over whole tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fingerprints, hidden_markov, jaccard_join, language_id, mixing, multi_index, piece_dropout, suffix_dedup, token_counts, token_records
from .common import documents


def vocabulary(name: str) -> str:
    """Where a public tokenizer's file is."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir).select("doc_id", "text", "lang")
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % 5 == 0, F.lit(False))
    model = language_id.fit(language_id.sample(docs.filter(~held), "text", "lang", "doc_id"))
    named = language_id.predict(docs.select("doc_id", held.alias("held_out"), "text"), model)
    return named.select("doc_id", "held_out", "lang_pred", "score")


def op2_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.compare_with_successor(documents(spark, sf_dir))


def op3_token_records(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_records.tokenize_to_files(documents(spark, sf_dir), vocabulary("word_bpe_49k.json"), end_id=2)


def op4_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multi_index.link(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), threshold=0.95)


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(documents(spark, sf_dir), vocabulary("byte_bpe_50k.json"))


def op6_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.classes(documents(spark, sf_dir), k=4, percent=85)


def op7_hidden_markov(spark: SparkSession, sf_dir: str) -> DataFrame:
    held = F.crc32(F.col("doc_id").cast("string")) % 7 == 2
    return hidden_markov.score(documents(spark, sf_dir).select("doc_id", "text"), held)


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(documents(spark, sf_dir).select("doc_id", "text"), digest=True)


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir), weights=(1, 2, 3)).drop("copies", "source")


def op10_piece_dropout(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_dropout.encode(documents(spark, sf_dir), vocabulary("piece_bpe_32k.model"), dropout=0.1, seed=7, digest=True)


QUERIES = {f.__name__: f for f in (op1_language_id, op2_fingerprints, op3_token_records, op4_multi_index, op5_token_counts, op6_jaccard_join, op7_hidden_markov, op8_suffix_dedup, op9_mixing, op10_piece_dropout)}
ORACLES: dict[str, str] = {}
