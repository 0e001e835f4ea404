"""The operators applied to their whole tables, for __spark_entry__."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagesketch.llm import cotraining, exact_dedup, language_id, license_scan, mixing, packing, ppm, quality, superminhash, url_filter
from pagesketch.llm.common import table


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents have no path: source, language and id stand for directories and file name."""
    path = F.concat_ws("/", "source", "lang", F.col("doc_id").cast("string"))
    return license_scan.scan(table(spark, sf_dir, "documents"), path)


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.identify(table(spark, sf_dir, "documents"))


def op3_superminhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return superminhash.near_groups(table(spark, sf_dir, "documents"), width=4, percent=80)


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.Judge(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).verdicts()


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), tokenizer_path())


def op7_cotraining(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cotraining.score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.exact_groups(table(spark, sf_dir, "documents"))


def op9_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge_urls(table(spark, sf_dir, "pages"))


def op10_ppm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ppm.held_out_scores(table(spark, sf_dir, "documents"))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_license_scan,
        op2_language_id,
        op3_superminhash,
        op4_quality_rules,
        op5_mixing,
        op6_packing,
        op7_cotraining,
        op8_exact_dedup,
        op9_url_filters,
        op10_ppm,
    )
}
