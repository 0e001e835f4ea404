"""SQL functions, a table function and grouped functions over pages."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry
from pagesketch.functions import hashing as H


def register(spark: SparkSession, geom: PageGeometry) -> None:
    """sketch_page(key) and sketch_cells(key) for a geometry, as native temporary SQL functions: no Python runs."""
    if geom.mode != "aligned" or geom.family != "murmur32":
        raise ValueError("SQL functions are made for aligned pages of the murmur32 family")
    base = geom.cfg.seed_base
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_page(k BIGINT) RETURNS BIGINT RETURN pmod(hash({base}, k), {geom.pages}L)")
    cols = ", ".join(f"pmod(hash({base + 1 + i}, k), {geom.columns}L)" for i in range(geom.cfg.depth))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION sketch_cells(k BIGINT) RETURNS TABLE (page BIGINT, row INT, col BIGINT) RETURN SELECT pmod(hash({base}, k), {geom.pages}L), pos, c FROM (SELECT posexplode(array({cols})) AS (pos, c))")


def pages_by_group(stream: DataFrame, geom: PageGeometry) -> DataFrame:
    """(page, total, most) of pages that a Pandas function adds up, one group a page."""
    cols = F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))
    located = stream.groupBy("item_key").agg(F.sum("weight").alias("weight")).withColumn("page", H.page_of(F.col("item_key"), geom)).select("page", "weight", cols.alias("cols"))
    depth, cells = geom.cfg.depth, geom.cells

    def run(pdf):
        import numpy as np
        import pandas as pd

        page = np.zeros(cells, np.int64)
        at = np.stack(pdf["cols"].to_numpy()) * depth + np.arange(depth)
        np.add.at(page, at, pdf["weight"].to_numpy()[:, None])
        return pd.DataFrame({"page": [int(pdf["page"].iloc[0])], "total": [int(page.sum())], "most": [int(page.max())]})

    return located.groupBy("page").applyInPandas(run, "page bigint, total bigint, most bigint")


def decoded(sketch: DataFrame) -> DataFrame:
    """depth, width, n and most of sketches (s) in the serialized form of Spark's count_min_sketch."""

    def run(batches):
        import numpy as np
        import pandas as pd

        for pdf in batches:
            rows = []
            for raw in pdf["s"]:
                total, depth, width = int.from_bytes(raw[4:12], "big"), int.from_bytes(raw[12:16], "big"), int.from_bytes(raw[16:20], "big")
                cells = np.frombuffer(raw, ">i8", offset=20 + 8 * depth)
                rows.append((depth, width, total, int(cells.max())))
            yield pd.DataFrame(rows, columns=["depth", "width", "n", "most"])

    return sketch.mapInPandas(run, "depth bigint, width bigint, n bigint, most bigint")
