"""The corpus pipeline: quality rules, exact dedup, near dedup, mixing and packing, each stage over all rows it gets."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from pagesketch.llm import exact_dedup, mixing, packing, quality, superminhash
from pagesketch.llm.common import cut, durable_dir, table
from pagesketch.llm.queries import tokenizer_path


def stage_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    return quality.Judge(docs, table(spark, sf_dir, "labels")).kept_rows()


def stage_exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts."""
    return exact_dedup.keep_one(docs)


def stage_near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates (five words, similarity 0.8 or more)."""
    return superminhash.keep_one(docs)


def stage_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents chosen for the target weights, the last of each leaf up to its last chosen word; one epoch, so that no document repeats."""
    return mixing.Mix(docs, max_epochs=1).texts()


def stage_pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the packed sequences."""
    return packing.pack(docs, tokenizer_path())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality_rules", stage_quality),
    ("exact_dedup", stage_exact),
    ("near_dedup", stage_near),
    ("mixing", stage_mix),
    ("packing", stage_pack),
]

#: Signatures, tokenizer ids and ratio models have no SQL form; tests hold the stages against brute force.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, each written to the shared folder and read again."""
    durable_dir(spark)
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = cut(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
