"""The buffered paged sketch as a sequential model, and its replay by page."""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagesketch.config import BufferPlan, PageGeometry
from pagesketch.functions import hashing as H


class BufferedModel:
    """Pages on a store, a sub-buffer for each in memory; located elements go in, estimates come out.

    An element is (page, columns); the caller hashes. Counts block reads and writes. For tests and small logs.
    """

    def __init__(self, geom: PageGeometry, capacity: int, write_policy: str = "dirty"):
        self.geom, self.capacity, self.write_policy = geom, capacity, write_policy
        self.pages: dict[int, dict[tuple[int, int], int]] = defaultdict(lambda: defaultdict(int))
        self.pending: dict[int, list[tuple[tuple[int, ...], int]]] = defaultdict(list)
        self.reads = self.writes = self.full_flushes = self.drains = 0

    @classmethod
    def planned(cls, geom: PageGeometry, plan: BufferPlan, **more) -> BufferedModel:
        return cls(geom, plan.capacity, **more)

    def _apply(self, page: int) -> bool:
        todo, self.pending[page] = self.pending[page], []
        for columns, weight in todo:
            for row, col in enumerate(columns):
                self.pages[page][row, col] += weight
        return bool(todo)

    def update(self, page: int, columns: tuple[int, ...], weight: int = 1) -> None:
        self.pending[page].append((columns, weight))
        if len(self.pending[page]) >= self.capacity:
            self._apply(page)
            self.full_flushes += 1
            self.reads += 1
            self.writes += 1

    def estimate(self, page: int, columns: tuple[int, ...]) -> int:
        self.reads += 1
        if self._apply(page):
            self.drains += 1
            self.writes += 1
        elif self.write_policy == "always":
            self.writes += 1
        return min(self.pages[page][row, col] for row, col in enumerate(columns))

    def close(self) -> None:
        for page in list(self.pending):
            if self._apply(page):
                self.drains += 1
                self.reads += 1
                self.writes += 1


def buffered_replay(ops: DataFrame, geom: PageGeometry, capacity: int) -> DataFrame:
    """(page, updates, full_flushes, drains, load) of the sequential model, run for each page by itself.

    A page's log is one group: for logs whose pages have a bounded share.
    """
    cols = F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))
    log = ops.withColumn("page", H.page_of(F.col("item_key"), geom)).select("page", "seq", "weight", cols.alias("cols"))

    def run(pdf):
        import pandas as pd

        page = int(pdf["page"].iloc[0])
        model = BufferedModel(geom, capacity)
        for columns, weight in pdf.sort_values("seq")[["cols", "weight"]].itertuples(index=False):
            model.update(page, tuple(columns), int(weight))
        model.close()
        load = sum(v for (row, _), v in model.pages[page].items() if row == 0)
        return pd.DataFrame({"page": [page], "updates": [len(pdf)], "full_flushes": [model.full_flushes], "drains": [model.drains], "load": [load]})

    return log.groupBy("page").applyInPandas(run, "page bigint, updates bigint, full_flushes bigint, drains bigint, load bigint")
