"""Accuracy measures: overestimates, failure shares, page loads, row errors."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry


def overestimates(exact: DataFrame, estimates: DataFrame) -> DataFrame:
    """(item_key, true_count, est, over) of every inserted item."""
    return exact.join(estimates, "item_key", "left").select("item_key", "true_count", F.coalesce("est", F.lit(0)).alias("est"), (F.coalesce("est", F.lit(0)) - F.col("true_count")).cast("bigint").alias("over"))


def summary(over: DataFrame) -> DataFrame:
    """One row: items, n, maximum and averages of the overestimate per element of the multiset and per item, undershoots."""
    return over.agg(
        F.count("*").cast("bigint").alias("items"),
        F.sum("true_count").cast("bigint").alias("n"),
        F.max("over").cast("bigint").alias("max_over"),
        F.round(F.sum(F.col("over") * F.col("true_count")) / F.sum("true_count"), 6).alias("avg_per_element"),
        F.round(F.sum("over") / F.count("*"), 6).alias("avg_per_item"),
        F.count_if(F.col("over") < 0).cast("bigint").alias("undershoots"),
    )


def failure_share(over: DataFrame, error: float) -> DataFrame:
    return over.agg(
        F.count("*").cast("bigint").alias("items"),
        F.count_if(F.col("over") >= F.lit(float(error))).cast("bigint").alias("failures"),
        F.round(F.avg((F.col("over") >= F.lit(float(error))).cast("double")), 6).alias("failure_share"),
    )


def quantiles(over: DataFrame) -> DataFrame:
    return over.agg(*(F.expr(f"percentile(over, {q})").alias(f"p{round(q * 100)}") for q in (0.5, 0.9, 0.99)), F.max("over").alias("p100"))


def page_loads(cells: DataFrame) -> DataFrame:
    """(page, load): the weight of all items of a page, which each of its rows adds up to."""
    return cells.where("row = 0").groupBy("page").agg(F.sum("cnt").cast("bigint").alias("load"))


def page_load_summary(loads: DataFrame, pages: int) -> DataFrame:
    """Smallest, mean and largest load; pages without items count with 0."""
    out = loads.agg(F.count("*").alias("used"), F.min("load").alias("least"), F.max("load").alias("max_load"), F.sum("load").alias("n"))
    least = F.when(F.col("used") < pages, 0).otherwise(F.col("least")).cast("bigint")
    return out.select(F.lit(pages).cast("bigint").alias("pages"), least.alias("min_load"), F.round(F.col("n") / pages, 6).alias("avg_load"), F.col("max_load").cast("bigint").alias("max_load"))


def row_error(loads: DataFrame, geom: PageGeometry) -> DataFrame:
    """(page, load, expected_error): the expected error of one row for an item of the page."""
    return loads.select("page", "load", F.round(F.col("load") / F.lit(geom.columns), 6).alias("expected_error"))


def row_errors(exact: DataFrame, probes: DataFrame) -> DataFrame:
    """(item_key, err0, err1): errors in the first two rows, from probes (item_key, row, cnt)."""
    two = probes.where("row < 2").groupBy("item_key").agg(*(F.max(F.when(F.col("row") == r, F.col("cnt"))).alias(f"c{r}") for r in (0, 1)))
    return exact.join(two, "item_key").select("item_key", *((F.col(f"c{r}") - F.col("true_count")).alias(f"err{r}") for r in (0, 1)))


def compare(named: dict[str, DataFrame]) -> DataFrame:
    """One row per method with its summary."""
    parts = [summary(over).withColumn("method", F.lit(name)) for name, over in named.items()]
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out
