"""Sketches of streams: micro-batches into a page store, page state in the engine, windows."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQuery
from pyspark.sql.types import LongType, StructField, StructType

from pagesketch.config import PageGeometry
from pagesketch.functions import hashing as H
from pagesketch.operators import sketch as S
from pagesketch.sources.store import PageStore

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Event files of a folder as a stream, with the schema given."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def item_stream(events: DataFrame, key: str = "user_id") -> DataFrame:
    return events.select("ts", F.col(key).cast("bigint").alias("item_key"), F.lit(1).cast("bigint").alias("weight"))


def ingest(stream: DataFrame, store: PageStore, checkpoint: str, capacity: int | None = None, most_deltas: int = 64) -> StreamingQuery:
    """Append each micro-batch as a delta, at most once by its id, and fold the buckets whose sub-buffers are full, or all beyond so many deltas."""

    def one(batch: DataFrame, batch_id: int) -> None:
        store.append_delta(batch.select("item_key", "weight"), batch_id)
        if len(store.state["batches"]) > most_deltas:
            store.compact()
        elif capacity is not None:
            store.compact(store.due(capacity))

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


class PageProcessor(StatefulProcessor):
    """One page in the state store: its counters and its pending elements.

    Elements wait in the sub-buffer and are applied when it is full; every batch reports the page's load, pending elements and flushes.
    """

    def __init__(self, depth: int, columns: int, capacity: int):
        self.depth, self.columns, self.capacity = depth, columns, capacity

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.cells = handle.getMapState("cells", StructType([StructField("at", LongType())]), StructType([StructField("cnt", LongType())]))
        self.pending = handle.getListState("pending", StructType([StructField("at", LongType()), StructField("weight", LongType())]))
        self.totals = handle.getValueState("totals", StructType([StructField("load", LongType()), StructField("flushes", LongType())]))

    def handleInputRows(self, key, rows, timer_values) -> Iterator:
        import pandas as pd

        waiting = list(self.pending.get()) if self.pending.exists() else []
        load, flushes = self.totals.get() if self.totals.exists() else (0, 0)
        for pdf in rows:
            for cols, weight in pdf[["cols", "weight"]].itertuples(index=False):
                waiting += [(int(c) * self.depth + i, int(weight)) for i, c in enumerate(cols)]
                load += int(weight)
                if len(waiting) >= self.capacity * self.depth:
                    self._apply(waiting)
                    waiting, flushes = [], flushes + 1
        self.pending.put(waiting) if waiting else self.pending.clear()
        self.totals.update((load, flushes))
        yield pd.DataFrame({"page": [key[0]], "load": [load], "pending": [len(waiting) // self.depth], "flushes": [flushes]})

    def _apply(self, waiting: list[tuple[int, int]]) -> None:
        for at, weight in waiting:
            old = self.cells.getValue((at,))[0] if self.cells.containsKey((at,)) else 0
            self.cells.updateValue((at,), (old + weight,))

    def close(self) -> None:
        pass


def page_states(stream: DataFrame, geom: PageGeometry, capacity: int) -> DataFrame:
    """(page, load, pending, flushes) of every page that a batch touched, state kept by page. Needs the RocksDB state store."""
    page = H.page_of(F.col("item_key"), geom)
    cols = F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))
    located = stream.withColumn("page", page).select("page", "weight", cols.alias("cols"))
    processor = PageProcessor(geom.cfg.depth, geom.columns, capacity)
    return located.groupBy("page").transformWithStateInPandas(statefulProcessor=processor, outputStructType="page bigint, load bigint, pending bigint, flushes bigint", outputMode="Update", timeMode="None")


def windowed_build(stream: DataFrame, geom: PageGeometry, window: str = "1 hour", slide: str | None = None, watermark: str = "1 hour") -> DataFrame:
    """(start, page, row, col, cnt): a sketch for every time window, late rows dropped behind the watermark. Batch or stream."""
    seen = stream.withWatermark("ts", watermark) if stream.isStreaming else stream
    located = seen.withColumn("page", H.page_of(F.col("item_key"), geom))
    cols = F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))
    cells = located.select("ts", "page", "weight", F.posexplode(cols).alias("row", "col"))
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return cells.groupBy(span, "page", "row", "col").agg(F.sum("weight").cast("bigint").alias("cnt")).select(F.col("window.start").alias("start"), "page", "row", "col", "cnt")


def estimate_stream(queries: DataFrame, pages: DataFrame, geom: PageGeometry) -> DataFrame:
    """Estimates for a stream of keys against packed pages that stand still: one page a key."""
    asked = queries.withColumn("page", H.page_of(F.col("item_key"), geom))
    joined = asked.join(pages.select("page", "cells"), "page", "left")
    cols = H.page_columns(F.col("item_key"), F.col("page"), geom)
    reads = [F.element_at("cells", (c * geom.cfg.depth + i + 1).cast("int")) for i, c in enumerate(cols)]
    return joined.select(*queries.columns, F.coalesce(F.array_min(F.array(*reads)), F.lit(0)).cast("bigint").alias("est"))


def first_only(stream: DataFrame, key: str, watermark: str = "1 hour") -> DataFrame:
    """Rows whose key was not seen within the watermark."""
    return stream.withWatermark("ts", watermark).dropDuplicatesWithinWatermark([key])


def final_pages(spark: SparkSession, store: PageStore) -> DataFrame:
    return S.paged_pack(store.read(), store.geom)


def soak_source(spark: SparkSession, rows_per_second: int = 1000, keys: int = 10_000) -> DataFrame:
    """An endless stream of items for soak runs: keys of a bounded range, the smaller ones more often."""
    rate = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    skewed = F.floor(F.lit(keys) * F.pow(F.pmod(F.xxhash64("value"), F.lit(1 << 20)) / float(1 << 20), 3)).cast("bigint")
    return rate.select(F.col("timestamp").alias("ts"), skewed.alias("item_key"), F.lit(1).cast("bigint").alias("weight"))
