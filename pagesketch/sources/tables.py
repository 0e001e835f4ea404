"""Sources: tables of a folder, operation logs, generated keys, CSV and JSON."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pagesketch.functions import hashing as H

OPLOG_SCHEMA = "seq bigint, op string, item_key bigint, weight bigint"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def stream_of(df: DataFrame, key: Column | str, weight: Column | str | None = None, **policies: str) -> DataFrame:
    from pagesketch.operators.sketch import items

    return items(df, key, weight, **policies)


def whole(number: str) -> Column:
    """A DOUBLE rounded to a BIGINT, halves to even, as the SQL's cast does it; Spark's own cast cuts the fraction off."""
    return F.rint(number).cast("bigint")


def oplog(events: DataFrame) -> DataFrame:
    """(seq, op, item_key, weight) of events in the order of their ids: views and clicks ask for the user, other events insert."""
    op = F.when(F.col("event_type").isin("view", "click"), "estimate").otherwise("insert")
    return events.select(F.col("event_id").alias("seq"), op.alias("op"), F.col("user_id").alias("item_key"), F.lit(1).cast("bigint").alias("weight"))


def uniform_keys(spark: SparkSession, n: int, seed: str = "keys-1") -> DataFrame:
    """(i, item_key): n keys that behave as uniform random 60-bit integers, the same in every run and engine."""
    return spark.range(n).select(F.col("id").alias("i"), H.fingerprint(F.concat(F.lit(f"{seed}:"), F.col("id").cast("string"))).alias("item_key"))


def read_oplog(spark: SparkSession, path: str, kind: str) -> DataFrame:
    """An operation log from CSV or JSON files, with its schema given."""
    return spark.read.schema(OPLOG_SCHEMA).option("header", "true").format(kind).load(path)


def write_oplog(log: DataFrame, path: str, kind: str) -> None:
    log.write.mode("overwrite").option("header", "true").format(kind).save(path)
