"""A page store: a base of page buckets and deltas beside it, under a manifest.

root/gen=<g>/page_bucket=<b>/ holds cells sorted by page; root/delta/batch=<id>/page_bucket=<b>/ holds what came since. The manifest
names, for each bucket, the generation it is in and the last batch folded into it, and the batches that still have pending cells. It is written as a
new version and found as the last one, so that a reader always sees one whole state. Files are written and listed by Spark and Hadoop alone, so that
the root may lie in any store. Batch ids grow; one that is not above the last is a retry.
"""

from __future__ import annotations

import json
import tempfile
import uuid
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry
from pagesketch.functions import hashing as H
from pagesketch.operators import sketch as S

CELLS = "page bigint, row int, col bigint, cnt bigint"


def scratch_dir(spark: SparkSession) -> str:
    """A new path in the folder that the cluster shares, or in a local one where none is named."""
    base = spark.conf.get("spark.checkpoint.dir", "") or tempfile.gettempdir()
    return f"{base.rstrip('/')}/pagesketch-{uuid.uuid4().hex}"


@dataclass
class PageStore:
    spark: SparkSession
    root: str
    geom: PageGeometry
    buckets: int
    state: dict = field(default_factory=dict)

    @classmethod
    def create(cls, spark: SparkSession, root: str, geom: PageGeometry, buckets: int = 64) -> PageStore:
        store = cls(spark, root, geom, buckets)
        store._save({"version": 0, "generations": {}, "folded_to": {}, "batches": [], "last": -1, "geometry": geom.fingerprint(), "buckets": buckets, "n": 0})
        return store

    @classmethod
    def open(cls, spark: SparkSession, root: str, geom: PageGeometry) -> PageStore:
        store = cls(spark, root, geom, 0)
        store.refresh()
        if store.state["geometry"] != geom.fingerprint():
            raise ValueError("the store has another configuration")
        store.buckets = store.state["buckets"]
        return store

    def refresh(self) -> None:
        """Reads the newest version alone; its name is found without opening the others."""
        kept = self.spark.read.schema("value string, v bigint").text(f"{self.root}/manifest")
        newest = kept.agg(F.max("v")).first()[0]
        self.state = json.loads(kept.where(F.col("v") == newest).first()["value"])

    def _save(self, state: dict) -> None:
        rows = self.spark.createDataFrame([(json.dumps(state),)], "value string").coalesce(1)
        rows.write.mode("errorifexists").text(f"{self.root}/manifest/v={state['version']}")
        self.state = state

    def bucket_of(self, page):
        """Contiguous page ranges, so that the pages of a bucket's files prune by minimum and maximum."""
        return F.floor(page * F.lit(self.buckets) / F.lit(self.geom.pages)).cast("int")

    def _write(self, cells: DataFrame, path: str) -> None:
        rows = cells.withColumn("page_bucket", self.bucket_of(F.col("page"))).repartition("page_bucket").sortWithinPartitions("page_bucket", "page")
        rows.write.mode("overwrite").partitionBy("page_bucket").parquet(path)

    def _delta(self, batch_id: int) -> DataFrame:
        return self.spark.read.schema(CELLS + ", page_bucket int").parquet(f"{self.root}/delta/batch={batch_id}")

    def append_delta(self, stream: DataFrame, batch_id: int) -> bool:
        """Add a batch's items as a delta, evaluating them once; a batch id that is there already is ignored, so that retries add nothing."""
        if batch_id <= self.state["last"]:
            return False
        self._write(S.paged_build(stream, self.geom), f"{self.root}/delta/batch={batch_id}")
        n = self._delta(batch_id).where("row = 0").agg(F.coalesce(F.sum("cnt"), F.lit(0))).first()[0]
        self._save({**self.state, "version": self.state["version"] + 1, "batches": [*self.state["batches"], batch_id], "last": batch_id, "n": self.state["n"] + n})
        return True

    def _pending(self) -> list[DataFrame]:
        """The deltas, each without the buckets that it is already folded into."""
        out = []
        for batch in self.state["batches"]:
            done = [int(b) for b, last in self.state["folded_to"].items() if last >= batch]
            out.append(self._delta(batch).where(~F.col("page_bucket").isin(done)) if done else self._delta(batch))
        return out

    def raw(self, buckets: list[int] | None = None) -> DataFrame:
        """Cells of base and deltas, not added up; only the wanted buckets are read."""
        by_generation: dict[int, list[int]] = {}
        for bucket, g in self.state["generations"].items():
            if buckets is None or int(bucket) in buckets:
                by_generation.setdefault(g, []).append(int(bucket))
        out = self.spark.createDataFrame([], CELLS + ", page_bucket int")
        for g, own in by_generation.items():
            base = self.spark.read.schema(CELLS + ", page_bucket int").parquet(f"{self.root}/gen={g}")
            out = out.unionByName(base.where(F.col("page_bucket").isin(own)))
        for rows in self._pending():
            out = out.unionByName(rows if buckets is None else rows.where(F.col("page_bucket").isin(buckets)))
        return out

    def read(self, buckets: list[int] | None = None) -> DataFrame:
        """(page, row, col, cnt) with all deltas applied."""
        return self.raw(buckets).groupBy("page", "row", "col").agg(F.sum("cnt").cast("bigint").alias("cnt"))

    def estimate(self, queries: DataFrame) -> DataFrame:
        """(item_key, est) of distinct queried keys; only buckets of their pages are read. The driver sees one row a bucket."""
        page = H.page_of(F.col("item_key"), self.geom)
        asked = sorted(r[0] for r in queries.select(self.bucket_of(page)).distinct().collect() if r[0] is not None)
        return S.paged_estimate_cells(self.read(None if len(asked) == self.buckets else asked), queries, self.geom)

    def lookup(self, key: int) -> int:
        """Estimate of one key: its page is computed first, so that only that page's bucket and row groups are read."""
        one = self.spark.range(1).select(F.lit(key).cast("bigint").alias("item_key"))
        page = one.select(H.page_of(F.col("item_key"), self.geom)).first()[0]
        bucket = page * self.buckets // self.geom.pages
        cells = self.raw([bucket]).where(F.col("page") == page).groupBy("page", "row", "col").agg(F.sum("cnt").alias("cnt"))
        return S.paged_estimate_cells(cells, one, self.geom).first()["est"]

    def _all_pending(self) -> DataFrame:
        out = self.spark.createDataFrame([], CELLS + ", page_bucket int")
        for rows in self._pending():
            out = out.unionByName(rows)
        return out

    def due(self, capacity: int) -> list[int]:
        """Buckets whose pending cells reach the capacity of their pages' sub-buffers."""
        pages = -(-self.geom.pages // self.buckets)
        rows = self._all_pending().where("row = 0").groupBy("page_bucket").agg(F.sum("cnt").alias("n")).where(F.col("n") >= capacity * pages)
        return sorted(r["page_bucket"] for r in rows.collect())

    def compact(self, buckets: list[int] | None = None) -> None:
        """Fold the pending cells of the named buckets, or of all, into a new generation; all others stay where they are."""
        if not self.state["batches"]:
            return
        pending = self._all_pending().select("page_bucket").distinct()
        touched = sorted(r["page_bucket"] for r in pending.collect())
        own = touched if buckets is None else [b for b in touched if b in buckets]
        if buckets is not None and not own:
            return
        g = self.state["version"] + 1
        if own:
            self._write(self.read(own), f"{self.root}/gen={g}")
        whole = own == touched
        folded_to = {} if whole else {**self.state["folded_to"], **{str(b): self.state["last"] for b in own}}
        generations = {**self.state["generations"], **{str(b): g for b in own}}
        self._save({**self.state, "version": g, "generations": generations, "folded_to": folded_to, "batches": [] if whole else self.state["batches"]})

    def vacuum(self) -> int:
        """Remove generations, deltas and manifest versions that the newest state does not name, and count them. No older state may be in use."""
        self.refresh()
        hadoop = self.spark.sparkContext._jvm.org.apache.hadoop.fs
        kept = {f"gen={g}" for g in self.state["generations"].values()} | {f"batch={b}" for b in self.state["batches"]} | {f"v={self.state['version']}"}
        removed = 0
        for folder, kind in ((self.root, "gen="), (f"{self.root}/delta", "batch="), (f"{self.root}/manifest", "v=")):
            path = hadoop.Path(folder)
            fs = path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
            for status in fs.listStatus(path) if fs.exists(path) else ():
                name = status.getPath().getName()
                if name.startswith(kind) and name not in kept:
                    removed += bool(fs.delete(status.getPath(), True))
        return removed
