"""Flat and paged sketches: building, layouts, merging and estimates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry, SketchConfig
from pagesketch.functions import hashing as H
from pagesketch.plans.choose import combine_plan


def items(df: DataFrame, key: Column | str, weight: Column | str | None = None, null_policy: str = "drop", on_negative: str = "error", null_weight: str = "zero") -> DataFrame:
    """(item_key, weight) of a stream; null keys dropped or, with null_policy 'item', one item; negative weights refused.

    A null weight counts as 0 or, with null_weight 'keep', stays null, so that an item without any known weight has a null sum.
    """
    key = F.col(key) if isinstance(key, str) else key
    weight = F.lit(1) if weight is None else F.col(weight) if isinstance(weight, str) else weight
    weight = weight.cast("bigint")
    if null_weight == "zero":
        weight = F.coalesce(weight, F.lit(0)).cast("bigint")
    elif null_weight != "keep":
        raise ValueError(f"unknown null_weight: {null_weight}")
    out = df.select(key.cast("bigint").alias("item_key"), weight.alias("weight"))
    if null_policy == "drop":
        out = out.where(F.col("item_key").isNotNull())
    else:
        out = out.withColumn("item_key", F.coalesce("item_key", F.lit(-(1 << 62) - 1)))
    if on_negative == "error":
        refuse = F.raise_error(F.lit("a weight is negative")).cast("bigint")
        out = out.withColumn("weight", F.when(F.col("weight") < 0, refuse).otherwise(F.col("weight")))
    return out


def exact_counts(stream: DataFrame) -> DataFrame:
    """(item_key, true_count): the multiset's own counts."""
    return stream.groupBy("item_key").agg(F.sum("weight").cast("bigint").alias("true_count"))


def flat_build(stream: DataFrame, cfg: SketchConfig) -> DataFrame:
    """(row, col, cnt) of a flat sketch: keys are combined, then one record per row is shuffled."""
    counts = stream.groupBy("item_key").agg(F.sum("weight").alias("weight"))
    cells = counts.select("weight", F.posexplode(F.array(*H.flat_columns(F.col("item_key"), cfg))).alias("row", "col"))
    return cells.groupBy("row", "col").agg(F.sum("weight").cast("bigint").alias("cnt"))


def sorted_cells(at: Column, cnt: Column) -> Column:
    """Aggregate: (at, cnt) pairs in the order of their places."""
    return F.array_sort(F.collect_list(F.struct(at.cast("bigint").alias("at"), cnt.cast("bigint").alias("cnt"))))


def dense(found: str, size: int) -> Column:
    """Counters as an array of that size from a column of sorted pairs, zeros where no pair has the place; in one pass."""

    def zeros(n: Column) -> Column:
        return F.array_repeat(F.lit(0).cast("bigint"), n.cast("int"))

    def with_gap(x: Column, i: Column) -> Column:
        before = F.when(i > 0, F.get(F.col(found), i - 1)["at"]).otherwise(F.lit(-1))
        return F.concat(zeros(x["at"] - before - 1), F.array(x["cnt"]))

    return F.concat(F.flatten(F.transform(F.col(found), with_gap)), zeros(F.lit(size - 1) - F.element_at(F.col(found), -1)["at"]))


def flat_dense(cells: DataFrame, cfg: SketchConfig) -> DataFrame:
    """(row, cells): each row of the sketch as an array, rows first. For sketches of a bounded width."""
    return cells.groupBy("row").agg(sorted_cells(F.col("col"), F.col("cnt")).alias("found")).select("row", dense("found", cfg.width).alias("cells"))


def flat_probes(queries: DataFrame, cfg: SketchConfig) -> DataFrame:
    return queries.select("item_key", F.posexplode(F.array(*H.flat_columns(F.col("item_key"), cfg))).alias("row", "col"))


def flat_estimate(cells: DataFrame, queries: DataFrame, cfg: SketchConfig, early_exit: bool = False, strategy: str = "auto") -> DataFrame:
    """(item_key, est) of distinct queried keys; with early_exit also probes_used, rows read up to the first zero.

    strategy is 'auto' or a join hint, as for paged_estimate.
    """
    cells = cells if strategy == "auto" else cells.hint(strategy)
    probes = flat_probes(queries.select("item_key").distinct(), cfg).join(cells, ["row", "col"], "left")
    probes = probes.withColumn("cnt", F.coalesce("cnt", F.lit(0)))
    measures = [F.min("cnt").cast("bigint").alias("est")]
    if early_exit:
        first_zero = F.min(F.when(F.col("cnt") == 0, F.col("row")))
        measures.append(F.coalesce(first_zero + 1, F.lit(cfg.depth)).cast("int").alias("probes_used"))
    return probes.groupBy("item_key").agg(*measures)


def route(stream: DataFrame, geom: PageGeometry, combine: str = "two_step", partitions: int | None = None) -> DataFrame:
    """(page, item_key, weight) with all records of a page in one partition: one record per key, not per row.

    combine: 'direct' shuffles every record once, 'two_step' combines by key first, 'arrow' combines batches before one shuffle.
    """
    located = stream.select(H.page_of(F.col("item_key"), geom).alias("page"), "item_key", "weight")
    if combine == "two_step":
        located = located.groupBy("page", "item_key").agg(F.sum("weight").alias("weight"))
    elif combine == "arrow":
        located = located.mapInPandas(_combine_batches, "page bigint, item_key bigint, weight bigint")
    elif combine != "direct":
        raise ValueError(f"unknown way to combine: {combine}")
    return located.repartition("page") if partitions is None else located.repartition(partitions, "page")


def _combine_batches(batches):
    for pdf in batches:
        yield pdf.groupby(["page", "item_key"], as_index=False)["weight"].sum()


def paged_build(stream: DataFrame, geom: PageGeometry, combine: str | None = None, partitions: int | None = None) -> DataFrame:
    """(page, row, col, cnt) of a paged sketch. The rows are laid out after the shuffle by page, which the last aggregation reuses."""
    routed = route(stream, geom, combine or combine_plan(stream), partitions)
    cols = F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))
    cells = routed.select("page", "weight", F.posexplode(cols).alias("row", "col"))
    return cells.groupBy("page", "row", "col").agg(F.sum("weight").cast("bigint").alias("cnt"))


def paged_pack(cells: DataFrame, geom: PageGeometry, how: str = "native") -> DataFrame:
    """(page, load, cells): one array per page, columns first; load is the weight of the page's items.

    how: 'native' sorts each page's counters as an array and fills the gaps by expressions; 'arrow' sorts the partition by page and
    writes counters to their places, a batch at a time, in less than half the time.
    """
    if how == "arrow":
        return _pack_batches(cells, geom)
    if how != "native":
        raise ValueError(f"unknown way to pack: {how}")
    depth = geom.cfg.depth
    packed = cells.groupBy("page").agg(
        F.sum(F.when(F.col("row") == 0, F.col("cnt"))).cast("bigint").alias("load"),
        sorted_cells(F.col("col") * depth + F.col("row"), F.col("cnt")).alias("found"),
    )
    return packed.select("page", "load", dense("found", geom.cells).alias("cells"))


def _pack_batches(cells: DataFrame, geom: PageGeometry) -> DataFrame:
    import numpy as np
    import pyarrow as pa

    size, depth = geom.cells, geom.cfg.depth

    def pages_of(page, at, cnt, load):
        found, begin, place = np.unique(page, return_index=True, return_inverse=True)
        out = np.zeros((len(found), size), np.int64)
        out[place, at] = cnt
        ends = pa.array(np.arange(len(found) + 1, dtype=np.int32) * size)
        return pa.RecordBatch.from_arrays([pa.array(found), pa.array(load[begin]), pa.ListArray.from_arrays(ends, pa.array(out.ravel()))], ["page", "load", "cells"])

    def run(batches):
        held = [np.empty(0, np.int64)] * 4
        for batch in batches:
            held = [np.concatenate((h, batch.column(i).to_numpy(zero_copy_only=False))) for i, h in enumerate(held)]
            whole = np.searchsorted(held[0], held[0][-1]) if len(held[0]) else 0
            if whole:
                yield pages_of(*(h[:whole] for h in held))
                held = [h[whole:] for h in held]
        if len(held[0]):
            yield pages_of(*held)

    at = (F.col("col") * depth + F.col("row")).cast("bigint").alias("at")
    # the window brings the rows of a page together, in order, and shuffles only cells that are not yet partitioned by page
    load = F.sum(F.when(F.col("row") == 0, F.col("cnt"))).over(Window.partitionBy("page")).cast("bigint").alias("load")
    return cells.select("page", at, F.col("cnt").cast("bigint"), load).mapInArrow(run, "page bigint, load bigint, cells array<bigint>")


def paged_ask(stream: DataFrame, geom: PageGeometry, queries: DataFrame | None = None, combine: str = "direct") -> DataFrame:
    """(item_key, est) of distinct queried keys, or of all keys of the stream, from a sketch that is built and asked at once.

    Items and queries meet on their pages by one shuffle of a record a key, and every counter is summed where its readers are:
    neither counters nor probes are shuffled, and no page is packed. For sketches that are asked once. combine 'two_step' adds up the
    records of a key before they meet, for streams with hot keys.
    """
    if combine not in ("direct", "two_step"):
        raise ValueError(f"unknown way to combine: {combine}")
    records = stream.select("item_key", "weight", F.lit(queries is None).alias("asked"))
    if queries is not None:
        records = records.unionByName(queries.select("item_key", F.lit(0).cast("bigint").alias("weight"), F.lit(True).alias("asked")))
    located = records.withColumn("page", H.page_of(F.col("item_key"), geom))
    combined = [F.sum("weight").alias("weight"), F.max("asked").alias("asked")]
    if combine == "two_step":
        located = located.groupBy("page", "item_key").agg(*combined)
    routed = located.repartition("page")
    keys = routed.groupBy("page", "item_key").agg(*combined)
    cells = keys.select("page", "item_key", "weight", "asked", F.posexplode(F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))).alias("row", "col"))
    cells = cells.withColumn("cnt", F.sum("weight").over(Window.partitionBy("page", "row", "col")))
    return cells.where("asked").groupBy("page", "item_key").agg(F.min("cnt").cast("bigint").alias("est")).select("item_key", "est")


def paged_estimate(pages: DataFrame, queries: DataFrame, geom: PageGeometry, strategy: str = "auto") -> DataFrame:
    """(item_key, est) of distinct queried keys from packed pages: one page a query, no matter how many rows.

    strategy: 'auto' leaves the join to the optimizer, 'broadcast' sends the pages to all tasks if their size is checked
    to be small, 'merge' and 'shuffle_hash' move the queries to their pages.
    """
    from pagesketch.plans.choose import broadcast_if_small

    asked = queries.select("item_key").distinct().withColumn("page", H.page_of(F.col("item_key"), geom))
    side = pages.select("page", "cells")
    if strategy == "broadcast":
        side = broadcast_if_small(side, geom.size_bytes)
    elif strategy != "auto":
        side = side.hint(strategy)
    joined = asked.join(side, "page", "left")
    cols = H.page_columns(F.col("item_key"), F.col("page"), geom)
    reads = [F.element_at("cells", (c * geom.cfg.depth + i + 1).cast("int")) for i, c in enumerate(cols)]
    return joined.select("item_key", F.coalesce(F.array_min(F.array(*reads)), F.lit(0)).cast("bigint").alias("est"))


def paged_estimate_cells(cells: DataFrame, queries: DataFrame, geom: PageGeometry) -> DataFrame:
    """The same from the cell form, without packing."""
    asked = queries.select("item_key").distinct().withColumn("page", H.page_of(F.col("item_key"), geom))
    probes = asked.select("item_key", "page", F.posexplode(F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))).alias("row", "col"))
    joined = probes.join(cells, ["page", "row", "col"], "left")
    return joined.groupBy("item_key").agg(F.min(F.coalesce("cnt", F.lit(0))).cast("bigint").alias("est"))


def merge(left: DataFrame, right: DataFrame) -> DataFrame:
    """Cells of the union of two streams; both sketches must have one configuration."""
    keys = [c for c in left.columns if c != "cnt"]
    return left.unionByName(right).groupBy(*keys).agg(F.sum("cnt").cast("bigint").alias("cnt"))


def paged_encode(pages: DataFrame, cell_bytes: int = 8) -> DataFrame:
    """(page, load, body): the store form, counters as little-endian integers; a counter that does not fit is an error."""
    import numpy as np
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            lists = batch.column("cells")
            out = []
            for row in lists:
                own = row.values.to_numpy(zero_copy_only=False)
                if cell_bytes == 4 and len(own) and own.max() >= 1 << 32:
                    raise OverflowError("a counter needs more than 4 bytes")
                out.append(own.astype("<u4" if cell_bytes == 4 else "<i8").tobytes())
            yield pa.RecordBatch.from_arrays([batch.column("page"), batch.column("load"), pa.array(out, pa.binary())], ["page", "load", "body"])

    return pages.select("page", "load", "cells").mapInArrow(run, "page bigint, load bigint, body binary")


def paged_decode(store: DataFrame, cell_bytes: int = 8) -> DataFrame:
    import numpy as np
    import pyarrow as pa

    def run(batches):
        for batch in batches:
            own = [np.frombuffer(x.as_py(), "<u4" if cell_bytes == 4 else "<i8").astype(np.int64) for x in batch.column("body")]
            yield pa.RecordBatch.from_arrays([batch.column("page"), batch.column("load"), pa.array(own, pa.list_(pa.int64()))], ["page", "load", "cells"])

    return store.mapInArrow(run, "page bigint, load bigint, cells array<bigint>")
