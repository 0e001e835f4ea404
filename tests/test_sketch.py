import collections

import pytest
from pyspark.sql import functions as F

from pagesketch import bounds
from pagesketch.config import PageGeometry, SketchConfig
from pagesketch.functions import hashing as H
from pagesketch.operators import measures
from pagesketch.operators import sketch as S
from pagesketch.queries_core import Case, uniform_stream
from pagesketch.sources.tables import stream_of, table, uniform_keys


@pytest.fixture(scope="module")
def small(spark, sf):
    return Case(stream_of(table(spark, sf, "lineitem"), "l_orderkey"))


def rows(df):
    return sorted(map(tuple, df.select(sorted(df.columns)).collect()))


def test_against_a_sketch_in_plain_python(spark, small):
    """Cells and estimates from a dictionary, with the engine's hash values as input."""
    cols = F.array(*H.page_columns(F.col("item_key"), F.col("page"), small.geom))
    located = small.exact.withColumn("page", H.page_of(F.col("item_key"), small.geom)).select("item_key", "true_count", "page", cols.alias("cols")).collect()
    cells = collections.Counter()
    for r in located:
        for i, c in enumerate(r["cols"]):
            cells[r["page"], i, c] += r["true_count"]
    assert {(r["page"], r["row"], r["col"]): r["cnt"] for r in small.paged().collect()} == dict(cells)
    want = sorted((min(cells[r["page"], i, c] for i, c in enumerate(r["cols"])), r["item_key"]) for r in located)
    assert rows(S.paged_estimate(small.packed(), small.exact, small.geom)) == want
    assert rows(S.paged_estimate_cells(small.paged(), small.exact, small.geom)) == want


def test_row_sums_and_page_loads(small):
    sums = small.flat().groupBy("row").agg(F.sum("cnt").alias("n")).collect()
    assert {r["n"] for r in sums} == {small.n} and len(sums) == small.cfg.depth
    per = small.paged().groupBy("page", "row").agg(F.sum("cnt").alias("n")).groupBy("page").agg(F.countDistinct("n").alias("d"))
    assert per.where("d > 1").count() == 0
    assert small.paged().where(f"col >= {small.geom.columns} or page >= {small.geom.pages}").count() == 0


def test_one_page_equals_a_flat_sketch(spark, small):
    cfg = SketchConfig(0.02, 0.01, 5, 100)
    geom = PageGeometry.of(cfg, block_bytes=100 * 5 * 8)
    assert geom.pages == 1
    flat = S.flat_build(small.stream, cfg)
    assert rows(S.paged_build(small.stream, geom).drop("page")) == rows(flat)


def test_merge_and_ways_to_combine(spark, small):
    want = rows(small.paged())
    odd, even = small.stream.where("item_key % 2 = 1"), small.stream.where("item_key % 2 = 0")
    assert rows(S.merge(S.paged_build(odd, small.geom), S.paged_build(even, small.geom))) == want
    for way in ("direct", "arrow"):
        assert rows(S.paged_build(small.stream.repartition(7), small.geom, combine=way)) == want


@pytest.mark.parametrize("family", ["xx64", "affine"])
def test_other_families_never_undershoot(small, family):
    c = Case(small.stream, family=family)
    for over in (c.flat_over(), c.paged_over()):
        assert over.where("over < 0").count() == 0


def test_edges(spark):
    empty = spark.createDataFrame([], "k bigint, w bigint")
    cfg = SketchConfig.from_stream(100)
    geom = PageGeometry.of(cfg)
    assert S.paged_build(stream_of(empty, "k"), geom).count() == 0
    asked = spark.createDataFrame([(5,), (5,), (9,)], "item_key bigint")
    pages = S.paged_pack(S.paged_build(stream_of(empty, "k"), geom), geom)
    assert rows(S.paged_estimate(pages, asked, geom)) == [(0, 5), (0, 9)]
    data = spark.createDataFrame([(1, 2), (None, 3), (1, None)], "k bigint, w bigint")
    assert rows(S.exact_counts(S.items(data, "k", "w"))) == [(1, 2)]
    assert S.exact_counts(S.items(data, "k", "w", null_policy="item")).count() == 2
    with pytest.raises(Exception, match="negative"):
        S.items(spark.createDataFrame([(1, -2)], "k bigint, w bigint"), "k", "w").collect()


def test_item_keys(spark):
    df = spark.createDataFrame([(1, 0.0, "a", "b"), (2, -0.0, "ab", "")], "i int, d double, s string, t string")
    assert df.select(F.countDistinct(H.item_key(df, "d"))).first()[0] == 1
    assert df.select(F.countDistinct(H.item_key(df, "s", "t"))).first()[0] == 2
    two = spark.createDataFrame([("a", "bc"), ("ab", "c")], "s string, t string")
    assert two.select(F.countDistinct(H.item_key(two, "s", "t"))).first()[0] == 2
    with pytest.raises(TypeError):
        maps = spark.sql("select map(1, 2) as m")
        H.item_key(maps, "m")


def test_unique_keys_meet_the_model_and_the_bounds(spark, sf):
    """Ten draws: loads within the lemma's bound, both sketches' averages close to each other and to the model."""
    n, broken = 6000, 0
    for seed in range(10):
        c = Case(uniform_keys(spark, n, f"draw-{seed}").select("item_key", F.lit(1).cast("bigint").alias("weight")))
        most = measures.page_loads(c.paged()).agg(F.max("load")).first()[0]
        broken += most > bounds.page_load(n, c.geom.pages)["load"]
    assert broken <= 2
    c = Case(uniform_stream(spark, sf))
    flat, paged = (measures.summary(o).first() for o in (c.flat_over(), c.paged_over()))
    assert flat["undershoots"] == paged["undershoots"] == 0
    assert abs(flat["avg_per_item"] - bounds.predicted_flat(c.n, c.cfg.width, 5)["avg_over"]) < 0.08
    assert abs(paged["avg_per_item"] / flat["avg_per_item"] - 1) < 0.1
    assert measures.failure_share(c.paged_over(), bounds.paged(c.geom, c.n)["error"]).first()["failure_share"] <= bounds.paged(c.geom, c.n)["failure"]


def test_plan_of_the_paged_build(small, capsys):
    """One shuffle by page after keys are combined; no Python on the way."""
    S.paged_build(small.stream, small.geom).explain("formatted")
    plan = capsys.readouterr().out
    assert plan.count("hashpartitioning(page") <= 4 and "Python" not in plan and "Pandas" not in plan
    shuffles = S.paged_build(small.stream, small.geom)._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")
    assert shuffles == 2
    assert S.paged_build(small.stream, small.geom, "direct")._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning") == 1


@pytest.mark.parametrize("mode", ["aligned", "straddling"])
@pytest.mark.parametrize("combine", ["direct", "two_step"])
def test_asking_at_once_against_packed_pages(spark, mode, combine):
    stream = spark.range(3000).select((F.col("id") % 700).alias("item_key"), F.when(F.col("id") % 7 > 0, F.col("id") % 5).cast("bigint").alias("weight"))
    stream = stream.na.fill(0)
    queries = spark.range(500, 900).union(spark.range(500, 510)).select(F.col("id").alias("item_key"))
    geom = PageGeometry.of(SketchConfig.from_stream(1500, 8, 0.01), 1024, mode)
    cells = S.paged_build(stream, geom)
    want = {tuple(r) for r in S.paged_estimate_cells(cells, queries, geom).collect()}
    got = [tuple(r) for r in S.paged_ask(stream, geom, queries, combine).collect()]
    assert len(got) == 400 and set(got) == want
    everything = S.paged_ask(stream, geom, combine=combine)
    assert {tuple(r) for r in everything.collect()} == {tuple(r) for r in S.paged_estimate_cells(cells, stream, geom).collect()}
    assert S.paged_ask(stream.limit(0), geom, combine=combine).count() == 0


def test_asking_at_once_shuffles_a_record_a_key_once(spark):
    stream = spark.range(1000).select(F.col("id").alias("item_key"), F.lit(1).cast("bigint").alias("weight"))
    geom = PageGeometry.of(SketchConfig.from_stream(1000))
    plan = S.paged_ask(stream, geom, stream)._jdf.queryExecution().sparkPlan().toString()
    executed = S.paged_ask(stream, geom, stream)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Join") == 0 and executed.count("Exchange") == 1


def test_packing_batches_whose_pages_cross(spark):
    stream = spark.range(2000).select(F.col("id").alias("item_key"), (F.col("id") % 3).alias("weight"))
    geom = PageGeometry.of(SketchConfig.from_stream(2000), 1024)
    cells = S.paged_build(stream, geom)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "7")
    try:
        got = S.paged_pack(cells, geom, how="arrow").collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert sorted(got) == sorted(S.paged_pack(cells, geom).collect())
    assert S.paged_pack(cells.limit(0), geom, how="arrow").count() == 0
    built = S.paged_build(stream, geom, combine="direct")
    plan = S.paged_pack(built, geom, how="arrow")._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1
