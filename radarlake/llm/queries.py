"""The registered queries of the ten operators, each over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from radarlake.llm import decontaminate, flac, language, near_dup, ngram, packing, pii, suffixes, token_orc, warc
from radarlake.llm.common import documents


def vocabulary(name: str) -> str:
    """Place of a public vocabulary file."""
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_flac(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flac.round_trip(documents(spark, sf_dir))


def op2_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.digest(documents(spark, sf_dir))


def op3_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.classify(documents(spark, sf_dir), vocabulary("piece_bpe_32k.model"))


def op4_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(documents(spark, sf_dir, "pages"), least=0).drop("record_id", "chunks")


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffixes.remove_repeats(documents(spark, sf_dir))


def op6_orc_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_orc.round_trip(documents(spark, sf_dir), vocabulary("word_bpe_49k.json"), 2)


def op7_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dup.groups(documents(spark, sf_dir), n=3, percent=85)


def op8_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(documents(spark, sf_dir), vocabulary("byte_bpe_50k.json"), 0)


def op9_spaced_seeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find(documents(spark, sf_dir), documents(spark, sf_dir, "benchmark"))


def op10_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram.fit_and_score(documents(spark, sf_dir))


QUERIES = {f.__name__: f for f in (op1_flac, op2_pii, op3_language, op4_warc, op5_suffix_dedup, op6_orc_tokens, op7_minhash, op8_packing, op9_spaced_seeds, op10_kneser_ney)}
