"""Fractional, missing and very large quantities of lineitem, against the SQL."""

import duckdb
import pytest
from pyspark.sql import functions as F

from pagesketch import queries_apps as A
from pagesketch import queries_core as C
from pagesketch.config import PageGeometry, SketchConfig
from pagesketch.functions import hashing as H
from pagesketch.operators import sketch as S

#: Halves on both sides of even numbers, fractions that a cast would cut off, a part without any quantity, and one with some.
LINES = [(1, 2.5), (1, 3.5), (2, 0.7), (3, None), (3, None), (4, None), (4, 4.0), (None, 9.0), (6, 0.0), (7, 0.5), (8, 10_000.0)]
#: About one part a page, so that parts without a quantity are alone on some pages and come after others on some.
LINES += [(i, None if i % 3 == 0 else i % 7 + 0.5) for i in range(100, 130)]


#: Weights whose pages number 2^24 and more, and 2^32 and more.
LARGE = {"pages_24": 5e8, "pages_32": 5e12}


def lines_of(spark, path, rows):
    spark.createDataFrame(rows, "l_partkey bigint, l_quantity double").write.parquet(f"{path}/lineitem.parquet")
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{path}/lineitem.parquet/*.parquet'")
    return path, con


@pytest.fixture(scope="module")
def odd_lines(spark, tmp_path_factory):
    return lines_of(spark, str(tmp_path_factory.mktemp("odd")), LINES)


@pytest.fixture(scope="module", params=list(LARGE))
def large_lines(spark, tmp_path_factory, request):
    rows = [(i % 9, LARGE[request.param] + i) for i in range(12)]
    assert PageGeometry.of(SketchConfig.from_stream(int(sum(q for _, q in rows)))).pages >= 1 << int(request.param[-2:])
    return lines_of(spark, str(tmp_path_factory.mktemp(request.param)), rows)


def same(df, con, sql):
    cols = ", ".join(f'"{c}"' for c in df.columns)
    want = con.sql(f"SELECT {cols} FROM ({sql})").fetchall()
    assert sorted(map(tuple, df.collect()), key=repr) == sorted(want, key=repr) and want
    return want


def test_candidates_of_odd_quantities(spark, odd_lines):
    path, con = odd_lines
    want = same(A.hh_page_candidates(spark, path), con, A.SQL["hh_page_candidates"])
    found = {item: n for _, item, n, _ in want}
    assert found[1] == 6 and found[2] == 1 and found[3] is None and found[4] == 4
    assert {1, 2} <= {place for _, _, n, place in want if n is None}


def test_candidates_of_large_quantities(spark, large_lines):
    path, con = large_lines
    same(A.hh_page_candidates(spark, path), con, A.SQL["hh_page_candidates"])


def test_cells_of_odd_quantities(spark, odd_lines):
    path, con = odd_lines
    want = same(C.paged_weighted(spark, path), con, C.SQL["paged_weighted"])
    assert any(cnt is None for *_, cnt in want) and any(cnt == 6 for *_, cnt in want)


def test_cells_of_large_quantities(spark, large_lines):
    path, con = large_lines
    same(C.paged_weighted(spark, path), con, C.SQL["paged_weighted"])


def test_portable_family_is_the_32_bit_one(spark):
    keys = spark.range(50).withColumn("a", H.hash_cell(F.col("id"), 3, 1000, "murmur32")).withColumn("b", H.hash_cell(F.col("id"), 3, 1000, "portable"))
    assert keys.where("a <> b").count() == 0
    cfg = SketchConfig.from_stream(6_000_000_000, family="portable")
    assert cfg.flat_family == PageGeometry.of(cfg).family == "portable" and PageGeometry.of(cfg).pages >= 1 << 24
    with pytest.raises(ValueError):
        cfg.with_(family="murmur32")


def test_null_weights_are_zeros_unless_kept(spark):
    df = spark.createDataFrame([(1, None), (1, 2), (2, None)], "k bigint, w bigint")
    assert sorted(map(tuple, S.exact_counts(S.items(df, "k", "w")).collect())) == [(1, 2), (2, 0)]
    assert sorted(map(tuple, S.exact_counts(S.items(df, "k", "w", null_weight="keep")).collect())) == [(1, 2), (2, None)]
    with pytest.raises(ValueError):
        S.items(df, "k", "w", null_weight="drop")
