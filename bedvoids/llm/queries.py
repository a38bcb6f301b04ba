"""The queries opN_<name> and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import cover_tree, decontaminate, html_text, language, minhash_dedup, mixing, suffix_dedup, toxicity, warc, word_lm
from .store import table


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(table(spark, sf_dir, "documents"))


def op2_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op3_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_minhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash_dedup.groups(table(spark, sf_dir, "documents"), k=2, percent=80)


def op6_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url")


def op7_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op8_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.identify(table(spark, sf_dir, "documents"))


def op9_cover_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cover_tree.links(table(spark, sf_dir, "embeddings"), cosine=0.9)


def op10_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return word_lm.scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels").where("quality = 1"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f for f in (op1_suffix_dedup, op2_source_mix, op3_html_text, op4_toxicity, op5_minhash_dedup, op6_warc_round_trip, op7_decontaminate, op8_language, op9_cover_tree, op10_lm_score)
}

SQL: dict[str, str] = {
    "op2_source_mix": mixing.SQL,
    "op5_minhash_dedup": minhash_dedup.SQL,
    "op6_warc_round_trip": warc.SQL,
    "op9_cover_tree": cover_tree.SQL,
}
