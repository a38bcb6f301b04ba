"""The stages that turn `documents` into a training corpus.

A stage gets the documents that the one before it kept and returns those that it keeps, with the columns of
`documents`; the last one returns them as the mix takes them, with the number of the copy in mix_copy.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from bedvoids.llm import decontaminate, minhash_dedup, mixing, suffix_dedup, toxicity
from bedvoids.llm.store import drop, fresh_path, scratch, table


def without_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return toxicity.without_toxic(docs, table(spark, sf_dir, "labels"))


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return minhash_dedup.one_of_each(docs)


def without_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return suffix_dedup.without_repeats(docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontaminate.without_matches(docs, table(spark, sf_dir, "benchmark"))


def mixed_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mixed(docs)


STAGES = [
    ("toxicity", without_toxic),
    ("minhash_dedup", one_of_each_group),
    ("suffix_dedup", without_repeated_passages),
    ("decontamination", without_benchmark),
    ("mixing", mixed_sources),
]

#: A trained classifier, MinHash and suffix sorting have no form in SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in a row. A stage's intermediate tables, and its input, are removed once its result is written."""
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        path = fresh_path(spark, f"stage-{name}")
        with scratch(spark):
            made = stage(spark, docs, sf_dir)
            made.write.parquet(path)
            schema = made.schema
        if before:
            drop(spark, before)
        docs, before = spark.read.schema(schema).parquet(path), path
    return docs
