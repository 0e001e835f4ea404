"""Logical I/O accounting over operation logs: exact, and independent of the hardware."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pagesketch.config import BufferPlan, PageGeometry, SketchConfig
from pagesketch.functions import hashing as H


def _distinct(blocks: list[Column]) -> Column:
    return F.size(F.array_distinct(F.array(*blocks)))


def flat_blocks(ops: DataFrame, cfg: SketchConfig, layout: str, cells: int = 512) -> DataFrame:
    """(item_key, n_ops, blocks): distinct blocks that one operation on the key touches."""
    cols = H.flat_columns(F.col("item_key"), cfg)
    blocks = [H.block_of(H.address(F.lit(i).cast("bigint"), c, layout, cfg.width, cfg.depth), cells) for i, c in enumerate(cols)]
    return ops.groupBy("item_key").agg(F.count("*").alias("n_ops")).select("item_key", "n_ops", _distinct(blocks).alias("blocks"))


def io_summary(per_key: DataFrame) -> DataFrame:
    return per_key.agg(
        F.sum("n_ops").cast("bigint").alias("ops"),
        F.sum(F.col("n_ops") * F.col("blocks")).cast("bigint").alias("ios"),
        F.round(F.sum(F.col("n_ops") * F.col("blocks")) / F.sum("n_ops"), 6).alias("io_per_op"),
        F.max("blocks").cast("bigint").alias("most"),
    )


def flat_cached(ops: DataFrame, cfg: SketchConfig, ratios: tuple[int, ...]) -> DataFrame:
    """(ratio, ops, ios, faults_per_op) of a flat sketch, rows first, under a page cache with its size over ratio as RAM: each block
    that an operation touches is expected to be absent with probability 1 - 1/ratio."""
    caches = ops.sparkSession.createDataFrame([(r,) for r in ratios], "ratio bigint")
    out = io_summary(flat_blocks(ops, cfg, "row")).crossJoin(F.broadcast(caches))
    faults = F.col("ios") / F.col("ops") * (F.lit(1.0) - F.lit(1.0) / F.col("ratio"))
    return out.select("ratio", "ops", "ios", F.round(faults, 6).alias("faults_per_op"))


def flat_blocks_early(probes: DataFrame, cfg: SketchConfig, cells: int = 512) -> DataFrame:
    """Blocks of a flat estimate that stops at the first zero cell, from probes (item_key, row, col, cnt), rows first."""
    stop = F.coalesce(F.min(F.when(F.col("cnt") == 0, F.col("row"))).over(Window.partitionBy("item_key")), F.lit(cfg.depth - 1))
    block = H.block_of(H.address(F.col("row").cast("bigint"), F.col("col"), "row", cfg.width, cfg.depth), cells)
    read = probes.withColumn("stop", stop).where("row <= stop").withColumn("block", block)
    return read.groupBy("item_key").agg(F.lit(1).cast("bigint").alias("n_ops"), F.countDistinct("block").alias("blocks"))


def paged_blocks(ops: DataFrame, geom: PageGeometry) -> DataFrame:
    """Blocks that one unbuffered operation touches: one for aligned pages, at most two for straddling ones."""
    page = H.page_of(F.col("item_key"), geom)
    located = ops.groupBy("item_key").agg(F.count("*").alias("n_ops")).withColumn("page", page)
    cols = H.page_columns(F.col("item_key"), F.col("page"), geom)
    blocks = [H.block_of(H.page_address(F.col("page"), F.lit(i).cast("bigint"), c, geom), geom) for i, c in enumerate(cols)]
    return located.select("item_key", "n_ops", _distinct(blocks).alias("blocks"))


def page_ops(ops: DataFrame, geom: PageGeometry) -> DataFrame:
    return ops.withColumn("page", H.page_of(F.col("item_key"), geom))


def paged_inserts(ops: DataFrame, geom: PageGeometry, capacities: DataFrame | int, unit: str = "transfer") -> DataFrame:
    """Flushes of buffered inserts by capacity: full ones, final drains, their sum, and I/O per insert.

    unit 'transfer' counts a flush once, 'rw' its read and its write.
    """
    per_page = page_ops(ops, geom).groupBy("page").agg(F.count("*").alias("u"))
    if isinstance(capacities, int):
        capacities = ops.sparkSession.range(1).select(F.lit(capacities).cast("bigint").alias("capacity"))
    grown = per_page.crossJoin(F.broadcast(capacities))
    out = grown.groupBy(*capacities.columns).agg(
        F.sum("u").cast("bigint").alias("ops"),
        F.sum(F.floor(F.col("u") / F.col("capacity"))).cast("bigint").alias("full_flushes"),
        F.count_if(F.col("u") % F.col("capacity") > 0).cast("bigint").alias("drains"),
    )
    each = 2 if unit == "rw" else 1
    out = out.withColumn("ios", ((F.col("full_flushes") + F.col("drains")) * each).cast("bigint"))
    return out.withColumn("io_per_op", F.round(F.col("ios") / F.col("ops"), 6))


def ram_sweep(ops: DataFrame, geom: PageGeometry, ratios: tuple[int, ...]) -> DataFrame:
    """Buffered insert cost at each ratio of sketch to RAM, beside the formula and the flat sketch under a page cache."""
    rows = [(r, BufferPlan.oversubscribed(geom, r).capacity, BufferPlan.oversubscribed(geom, r).raw_update_io) for r in ratios]
    table = ops.sparkSession.createDataFrame(rows, "ratio bigint, capacity bigint, formula double")
    depth = geom.cfg.depth
    out = paged_inserts(ops, geom, table.withColumn("formula", F.round("formula", 6)))
    return out.withColumn("flat_cached", F.round(F.lit(depth) * (F.lit(1.0) - F.lit(1.0) / F.col("ratio")), 6))


def flush_schedule(ops: DataFrame, geom: PageGeometry, capacity: int) -> DataFrame:
    """(page, seq, item_key, flush_no): the flush in which each insert reaches its page."""
    order = Window.partitionBy("page").orderBy("seq")
    number = F.floor((F.row_number().over(order) - 1) / F.lit(capacity)).cast("bigint")
    return page_ops(ops, geom).select("page", "seq", "item_key", number.alias("flush_no"))


def flush_summary(schedule: DataFrame, capacity: int) -> DataFrame:
    per = schedule.groupBy("page", "flush_no").agg(F.count("*").alias("n"))
    return per.groupBy("page").agg(F.count_if(F.col("n") == capacity).cast("bigint").alias("full_flushes"), F.count_if(F.col("n") < capacity).cast("bigint").alias("drains"), F.sum("n").cast("bigint").alias("applied"))


def mixed_estimates(oplog: DataFrame, geom: PageGeometry) -> DataFrame:
    """(seq, item_key, est) of every estimate in a log (seq, op, item_key, weight) of inserts and estimates.

    Probes join the inserts' cells with weight 0; a running sum per cell then gives what each probe reads.
    """
    located = page_ops(oplog, geom)
    cols = F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))
    weight = F.when(F.col("op") == "insert", F.col("weight")).otherwise(0)
    cells = located.select("seq", "op", "item_key", "page", weight.alias("w"), F.posexplode(cols).alias("row", "col"))
    order = Window.partitionBy("page", "row", "col").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    read = cells.withColumn("value", F.sum("w").over(order)).where("op = 'estimate'")
    return read.groupBy("seq", "item_key").agg(F.min("value").cast("bigint").alias("est"))


def mixed_flushes(oplog: DataFrame, geom: PageGeometry, capacity: int) -> DataFrame:
    """(page, estimates, full_flushes, early_drains, final_drains): an estimate drains what its page has pending."""
    order = Window.partitionBy("page").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    is_estimate = (F.col("op") == "estimate").cast("int")
    seg = F.coalesce(F.sum(is_estimate).over(order), F.lit(0))
    per = page_ops(oplog, geom).withColumn("seg", seg).groupBy("page", "seg").agg(F.count_if(F.col("op") == "insert").alias("u"), F.max(is_estimate).alias("closed"))
    pending = F.col("u") % capacity > 0
    return per.groupBy("page").agg(
        F.sum("closed").cast("bigint").alias("estimates"),
        F.sum(F.floor(F.col("u") / capacity)).cast("bigint").alias("full_flushes"),
        F.count_if(pending & (F.col("closed") == 1)).cast("bigint").alias("early_drains"),
        F.count_if(pending & (F.col("closed") == 0)).cast("bigint").alias("final_drains"),
    )


def mixed_io(flushes: DataFrame) -> DataFrame:
    """Reads and writes of a mixed log when a page is written back only if it changed, and always."""
    out = flushes.agg(*(F.sum(c).alias(c) for c in ("estimates", "full_flushes", "early_drains", "final_drains")))
    inserts = F.col("full_flushes") + F.col("final_drains")
    return out.select(
        (inserts + F.col("estimates")).cast("bigint").alias("transfers"),
        (2 * inserts + F.col("estimates") + F.col("early_drains")).cast("bigint").alias("rw_dirty"),
        (2 * inserts + 2 * F.col("estimates")).cast("bigint").alias("rw_always"),
    )


def lru_replay(ops: DataFrame, cfg: SketchConfig, cache_blocks: int, cells: int = 512) -> DataFrame:
    """Faults of a flat sketch under a least-recently-used cache; one sequential replay, for small logs."""
    cols = H.flat_columns(F.col("item_key"), cfg)
    blocks = [H.block_of(H.address(F.lit(i).cast("bigint"), c, "row", cfg.width, cfg.depth), cells) for i, c in enumerate(cols)]
    log = ops.select(F.lit(0).alias("g"), "seq", F.array(*blocks).alias("blocks"))

    def run(pdf):
        import collections

        import pandas as pd

        cache: collections.OrderedDict = collections.OrderedDict()
        faults = 0
        for row in pdf.sort_values("seq")["blocks"]:
            for b in row:
                if b in cache:
                    cache.move_to_end(b)
                else:
                    faults += 1
                    cache[b] = True
                    if len(cache) > cache_blocks:
                        cache.popitem(last=False)
        return pd.DataFrame({"ops": [len(pdf)], "faults": [faults]})

    return log.groupBy("g").applyInPandas(run, "ops bigint, faults bigint")
