"""Sketches as objects: cells with their configuration, so that only like sketches meet."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry, SketchConfig
from pagesketch.functions import hashing as H
from pagesketch.operators import sketch as S


def config_df(spark: SparkSession, cfg: SketchConfig, geom: PageGeometry | None = None) -> DataFrame:
    """A configuration as one row, for joins and for keeping."""
    row = asdict(cfg) | {"size_bytes": cfg.size_bytes, "fingerprint": (geom or cfg).fingerprint()}
    if geom is not None:
        row |= {"pages": geom.pages, "columns": geom.columns, "block_bytes": geom.block_bytes, "mode": geom.mode}
    return spark.createDataFrame([row])


@dataclass(frozen=True)
class FlatSketch:
    """Cells (row, col, cnt) of a flat sketch."""

    cells: DataFrame
    cfg: SketchConfig

    @classmethod
    def build(cls, stream: DataFrame, cfg: SketchConfig) -> FlatSketch:
        return cls(S.flat_build(stream, cfg), cfg)

    def merge(self, other: FlatSketch) -> FlatSketch:
        if self.cfg.fingerprint() != other.cfg.fingerprint():
            raise ValueError("sketches of different configurations cannot be merged")
        return FlatSketch(S.merge(self.cells, other.cells), self.cfg)

    def estimate(self, queries: DataFrame, **more) -> DataFrame:
        return S.flat_estimate(self.cells, queries, self.cfg, **more)


@dataclass(frozen=True)
class PagedSketch:
    """Cells (page, row, col, cnt) of a paged sketch."""

    cells: DataFrame
    geom: PageGeometry

    @classmethod
    def build(cls, stream: DataFrame, geom: PageGeometry, combine: str | None = None) -> PagedSketch:
        return cls(S.paged_build(stream, geom, combine), geom)

    def merge(self, other: PagedSketch) -> PagedSketch:
        if self.geom.fingerprint() != other.geom.fingerprint():
            raise ValueError("sketches of different configurations cannot be merged")
        return PagedSketch(S.merge(self.cells, other.cells), self.geom)

    def pages(self) -> DataFrame:
        return S.paged_pack(self.cells, self.geom)

    def estimate(self, queries: DataFrame, strategy: str = "auto") -> DataFrame:
        """Aligned pages are asked packed, one record each; straddling ones cell by cell."""
        if self.geom.mode != "aligned":
            return S.paged_estimate_cells(self.cells, queries, self.geom)
        return S.paged_estimate(self.pages(), queries, self.geom, strategy)

    def write(self, path: str, buckets: int = 64) -> None:
        """Cells by page bucket, sorted by page, and the configuration beside them."""
        bucket = F.floor(F.col("page") * F.lit(buckets) / F.lit(self.geom.pages)).cast("int")
        rows = self.cells.withColumn("page_bucket", bucket).repartition("page_bucket").sortWithinPartitions("page_bucket", "page")
        rows.write.mode("overwrite").partitionBy("page_bucket").parquet(f"{path}/cells")
        state = {"config": asdict(self.geom.cfg), "block_bytes": self.geom.block_bytes, "mode": self.geom.mode, "buckets": buckets}
        self.cells.sparkSession.createDataFrame([(json.dumps(state),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/config")

    @classmethod
    def read(cls, spark: SparkSession, path: str) -> PagedSketch:
        state = json.loads(spark.read.text(f"{path}/config").first()[0])
        geom = PageGeometry.of(SketchConfig(**state["config"]), state["block_bytes"], state["mode"])
        cells = spark.read.schema("page bigint, row int, col bigint, cnt bigint, page_bucket int").parquet(f"{path}/cells")
        return cls(cells.drop("page_bucket"), geom)

    def lookup(self, key: int) -> int:
        """Estimate of one key; the page is a literal in the scan, so that files and row groups prune."""
        spark = self.cells.sparkSession
        one = spark.range(1).select(F.lit(key).cast("bigint").alias("item_key"))
        page = one.select(H.page_of(F.col("item_key"), self.geom)).first()[0]
        return S.paged_estimate_cells(self.cells.where(F.col("page") == page), one, self.geom).first()["est"]
