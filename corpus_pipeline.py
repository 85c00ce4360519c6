"""The corpus pipeline: language, near duplicates, benchmark passages, personal data, packing.

Each stage takes (spark, docs, sf_dir) and returns what it keeps; all but the last keep
the columns of `documents`. `run` writes each stage's result to the shared folder and
reads it as the next one's documents. Stages on shingles take five words and a
similarity of 0.8.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from radarlake.llm import decontaminate, language, near_dup, packing, pii
from radarlake.llm.common import documents, release, stored
from radarlake.llm.queries import vocabulary


def identified(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops rows without a language: null or empty text, no letter, or no learned language above an even chance. The others stay as they are, null and repeated ids too; without a row to learn from none has a language."""
    return language.keep(docs, vocabulary("piece_bpe_32k.model"), least=0.5)


def distinct_texts(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps of each group of near duplicates the row with the smallest id, null ids last. Rows equal in id and text count once; different texts under one id are documents of their own; null, empty and wordless texts have no duplicates but equal rows."""
    return near_dup.keep_one(docs, n=5, percent=80)


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops each row whose text holds a benchmark passage; null and empty texts hold none, and rows with one id are judged one by one."""
    return decontaminate.remove(docs, documents(spark, sf_dir, "benchmark")).select(docs.columns)


def redacted(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data by its kind in brackets and counts the characters anew; every row stays, and a null text stays null with null characters."""
    return pii.redact(docs).withColumn("n_chars", F.length("text").cast("long")).select(docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of the token windows: each row's tokens and an end id, once. A null or empty text is its end id alone; repeated and null ids are packed as they come."""
    return packing.pack(docs, vocabulary("byte_bpe_50k.json"), 0)


STAGES = [
    ("language", identified),
    ("near_duplicates", distinct_texts),
    ("decontamination", decontaminated),
    ("personal_data", redacted),
    ("packing", packed),
]

#: Fitted language models and token ids are beyond SQL; the tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last stage's rows over `documents`."""
    docs, before = documents(spark, sf_dir), None
    for name, stage in STAGES[:-1]:
        docs = stored(stage(spark, docs, sf_dir), name)
        if before is not None:
            release(before)
        before = docs
    return STAGES[-1][1](spark, docs, sf_dir)
