"""A training-data pipeline over `documents`: language, near duplicates, benchmark, personal data, packing.

Each stage is (name, function of spark, docs, sf_dir). Stages before the last return the columns of documents and work on all
that their predecessor kept. Columns are read by name and cast; others are dropped, whatever their names. An empty table stays empty.

1. language: texts without letters, or whose language is not recognised, go;
2. near_duplicates: of each group of documents linked by 4-word shingles at 0.85 the one with the smallest doc_id stays;
3. benchmark: documents that hold a window of 10 consecutive benchmark words go;
4. personal_data: spans of the patterns and of the skip-chain field become [KIND], n_chars follows the text;
5. packing: the texts become sequences of at most 2048 tokens.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from intervalrules.llm import decontam, langid, packing, pii, setjoin
from intervalrules.llm.common import Scratch, table, tidy

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")
LEAST_LIFT = 1.2  # of the score over an even spread of probability on the learned languages


def _columns(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), F.col("n_chars").cast("long").alias("n_chars"))


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text has a language among the learned ones, with a score above chance by LEAST_LIFT; a missing lang is filled in.

    Null, empty and letterless texts go. Without any labelled row nothing is learned, and every row with a letter stays. Repeated rows, and rows that share or lack a
    doc_id, are judged one by one; very long texts are read whole.
    """
    docs = _columns(docs)
    net = langid.train(docs)
    if net is None:
        return docs.filter(F.col("text").rlike(r"\p{L}"))
    least = min(0.5, LEAST_LIFT / len(net.labels))
    return docs.mapInArrow(tidy(langid.known_only(net, least)), docs.schema)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of linked texts: that of the smallest doc_id (a null is the smallest; of several texts under it, one).

    Copies are linked, so one row of them stays; rows that share a doc_id are judged by their texts. Null and blank texts are linked with nothing and stay.
    """
    return setjoin.one_of_each(_columns(docs))


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose text holds no window of an item. Null and empty texts hold none; an empty benchmark removes nothing; repeated rows go or stay together."""
    return decontam.without_benchmark(_columns(docs), table(spark, sf_dir, "benchmark"))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, their personal data replaced. A null text stays null, with a null n_chars; repeated rows are changed alike."""
    docs = _columns(docs)
    field = pii.train(docs)
    kind = "doc_id long, lang string, source string, n_chars long, text string"
    out = docs.mapInArrow(tidy(pii.finder(field, 0.9, True)), kind)
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all rows with their places in sequences. A null text is an empty one: its end token alone; repeated rows are packed one by one."""
    return packing.best_fit(docs, packing.tokenizer_path())


STAGES = [("language", language), ("near_duplicates", near_duplicates), ("benchmark", benchmark), ("personal_data", personal_data), ("packing", pack)]

# The byte network and the random field are learned models, which SQL cannot express; tests compare with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch = Scratch(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = scratch.table(name, stage(spark, docs, sf_dir))
    return docs
