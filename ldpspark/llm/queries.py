"""The dealt operators on the given tables: one query each, with production parameters, and SQL where it can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ldpspark.llm import chat_format, decontamination, exact_dedup, jaccard_join, mixing, quality, sharding, substring_dedup, url_filter, warc


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.similar_classes(table(spark, sf_dir, "documents"), count_links=True)


def op2_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    said = r"\### Assistant: </turn> ok"
    more = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text").unionByName(more)
    return chat_format.digests(chat_format.formatted(turns))


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.quality_scores(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.repeated_spans(table(spark, sf_dir, "documents"))


def op5_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.document_shards(table(spark, sf_dir, "documents"))


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixed(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.digested(decontamination.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), proximity=True))


def op8_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    outcomes = url_filter.outcomes_from_labels(table(spark, sf_dir, "labels"))
    return url_filter.judged(table(spark, sf_dir, "pages"), outcomes).drop("bad_chance")


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(table(spark, sf_dir, "documents"))


def op10_warc_derivatives(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.digest_rows(warc.derivatives(table(spark, sf_dir, "pages")))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_ngram_jaccard_join": op1_ngram_jaccard_join,
    "op2_chat_formatting": op2_chat_formatting,
    "op3_quality_classifier": op3_quality_classifier,
    "op4_substring_dedup": op4_substring_dedup,
    "op5_sharding": op5_sharding,
    "op6_mixing": op6_mixing,
    "op7_decontamination": op7_decontamination,
    "op8_url_filters": op8_url_filters,
    "op9_exact_dedup": op9_exact_dedup,
    "op10_warc_derivatives": op10_warc_derivatives,
}

ORACLES: dict[str, str] = {
    "op2_chat_formatting": chat_format.ORACLE,
    "op6_mixing": mixing.ORACLE,
    "op7_decontamination": decontamination.ORACLE,
    "op8_url_filters": url_filter.ORACLE,
    "op9_exact_dedup": exact_dedup.ORACLE,
}
