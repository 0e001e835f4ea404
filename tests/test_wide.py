"""Sketches of heavy streams: a flat width from 2^24 on while the pages are few, against the SQL."""

import duckdb
import pytest
from pyspark.sql import functions as F

from pagesketch import oracles as O
from pagesketch import queries_apps as A
from pagesketch import queries_core as C
from pagesketch.config import PageGeometry, SketchConfig

HEAVY = 10_000_000


def same(df, con, sql):
    cols = ", ".join(f'"{c}"' for c in df.columns)
    want = con.sql(f"SELECT {cols} FROM ({sql})").fetchall()
    assert sorted(map(tuple, df.collect())) == sorted(want) and want


@pytest.fixture(scope="module")
def heavy_lines(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("heavy"))
    rows = [(i % 9, float(HEAVY + i)) for i in range(12)]
    spark.createDataFrame(rows, "l_partkey bigint, l_quantity double").write.parquet(f"{path}/lineitem.parquet")
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{path}/lineitem.parquet/*.parquet'")
    return path, con


def test_pairs_of_many_words(spark, tmp_path, monkeypatch):
    texts = ["a b c d", "b c d", "x y x y"]
    spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    counted = A.doc_pair_counts
    monkeypatch.setattr(A, "doc_pair_counts", lambda docs: counted(docs).withColumn("n", F.col("n") * HEAVY))
    est, c = A.doc_pair_estimates(spark, spark.read.parquet(f"{tmp_path}/documents.parquet"))
    assert c.cfg.width >= 1 << 24 > c.geom.pages
    con = duckdb.connect()
    con.execute(f"create view documents as select * from '{tmp_path}/documents.parquet/*.parquet'")
    ctes = f"WITH {A.DOC_PAIRS}, {O.sketch_ctes(A.PAIR_ITEMS.replace('1 AS weight', f'{HEAVY} AS weight'))}"
    same(c.paged(), con, f"{ctes} SELECT * FROM pcells")
    same(est, con, f'{ctes} SELECT "left", "right", est FROM (SELECT DISTINCT "left", "right", {A.PAIR_KEY} AS item_key FROM pairs) JOIN pest USING (item_key)')


def test_candidates_of_heavy_parts(spark, heavy_lines):
    path, con = heavy_lines
    same(A.hh_page_candidates(spark, path), con, A.SQL["hh_page_candidates"])


def test_cells_of_heavy_parts(spark, heavy_lines):
    path, con = heavy_lines
    same(C.paged_weighted(spark, path), con, C.SQL["paged_weighted"])


def test_family_by_what_is_hashed_to():
    cfg = SketchConfig.from_stream(100_000_000)
    assert cfg.width >= 1 << 24 and cfg.flat_family == "xx64" and PageGeometry.of(cfg).family == "murmur32"
    assert PageGeometry.of(cfg, 64).family == "xx64" and PageGeometry.of(cfg, 1 << 31).family == "xx64"
    given = SketchConfig.from_stream(100_000_000, family="xx64")
    assert given.flat_family == PageGeometry.of(given).family == "xx64"
    small = SketchConfig.from_stream(60_000)
    assert small.family == small.flat_family == PageGeometry.of(small).family == "murmur32"
