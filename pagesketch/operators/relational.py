"""Total orders, carried values, salted joins and bounded candidates without single-task windows."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Rows of one group of carry(); no window there is longer.
WIDTH = 1000
#: Bits of monotonically_increasing_id that number the rows of one partition.
PLACE_BITS = 33


def with_positions(spark: SparkSession, rows: DataFrame, path: str, *order: Column) -> DataFrame:
    """Adds pos, the place of each row in a total order, from 0.

    Rows are cut into ranges, sorted and numbered in each, and written once to path; a range starts after the sizes of those before it, of which
    there is one a partition. Ties in the order are placed in any way.
    """
    ranged = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    place = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << PLACE_BITS) - 1))
    ranged.withColumn("part", F.spark_partition_id()).withColumn("place", place).write.parquet(path)
    kept = spark.read.parquet(path)
    sizes = kept.groupBy("part").agg(F.count("*").alias("size"))
    earlier = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("part", F.coalesce(F.sum("size").over(earlier), F.lit(0)).alias("start"))
    return kept.join(F.broadcast(starts), "part").withColumn("pos", F.col("place") + F.col("start")).drop("part", "place", "start")


def carry(ends: DataFrame, top: int, by: tuple[str, ...] = (), backwards: bool = False) -> DataFrame:
    """(by..., block, carried): the last end that is not null in earlier blocks, or with backwards the first in later ones.

    ends has one row a block, with (by..., block, end) and blocks from 0 to top. Blocks are grouped by WIDTH, level over level, so that no window is
    longer than that. No row is lost; carried is null where nothing lies before.
    """
    up = F.floor(F.col("block") / WIDTH)
    toward = F.desc("block") if backwards else F.asc("block")
    earlier = Window.partitionBy(*by, "up").orderBy(toward).rowsBetween(Window.unboundedPreceding, -1)
    own = ends.withColumn("up", up).withColumn("own", F.last("end", ignorenulls=True).over(earlier))
    if top < WIDTH:
        return own.select(*by, "block", F.col("own").alias("carried"))
    pick = F.min_by if backwards else F.max_by
    above = ends.groupBy(*by, up.alias("block")).agg(pick("end", F.when(F.col("end").isNotNull(), F.col("block"))).alias("end"))
    higher = carry(above, top // WIDTH, by, backwards).withColumnRenamed("block", "up")
    return own.join(higher, [*by, "up"], "left").select(*by, "block", F.coalesce("own", "carried").alias("carried"))


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """Inner join by key, with each key's rows of the left side dealt over that many tasks and the right side, the smaller one, repeated as often."""
    dealt = left.withColumn("salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    repeated = right.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return dealt.join(repeated, [key, "salt"]).drop("salt")


def frequent_candidates(rows: DataFrame, item: str, k: int) -> DataFrame:
    """(item), a superset of the items with at least 1/k of all rows, from one pass with k counters a task.

    An item with that share of all rows has it in some task, where counters that are lowered together cannot lose it. Nulls are no items.
    """

    def run(batches) -> Iterator:
        import pandas as pd

        kept = pd.Series(dtype="int64")
        for pdf in batches:
            kept = kept.add(pdf[item].value_counts(), fill_value=0).astype("int64")
            if len(kept) > k:
                kept = kept - kept.nlargest(k + 1).iloc[-1]
                kept = kept[kept > 0]
        yield pd.DataFrame({item: kept.index.astype(object)})

    one = rows.select(item).where(F.col(item).isNotNull())
    return one.mapInPandas(run, one.schema).distinct()
