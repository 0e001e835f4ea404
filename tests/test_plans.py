from pyspark.sql import functions as F

from pagesketch.functions import sqlapi
from pagesketch.operators import heavy
from pagesketch.operators import sketch as S
from pagesketch.plans import choose
from pagesketch.plans.metrics import shuffle_cost
from pagesketch.queries_core import Case, uniform_stream
from pagesketch.sources.tables import stream_of, table


def test_one_shuffled_record_an_update_instead_of_one_a_row(spark, sf):
    c = Case(uniform_stream(spark, sf))
    paged = shuffle_cost(S.paged_build(c.stream, c.geom, combine="direct"))
    flat = shuffle_cost(c.flat())
    assert paged["exchanges"] == 1 and paged["records"] == c.n
    assert flat["records"] > 2 * c.n


def test_broadcast_only_within_the_limit(spark):
    side = spark.range(10)
    assert choose.broadcast_if_small(side, 10, limit=5) is side
    assert "broadcast" in choose.broadcast_if_small(side, 5, limit=5)._jdf.queryExecution().logical().toString().lower()
    assert choose.choose_plan(1 << 40) == "page_join" and choose.choose_plan(1 << 10) == "broadcast"


def test_choice_of_combining(spark, sf):
    unique, skewed = uniform_stream(spark, sf), stream_of(table(spark, sf, "lineitem"), "l_suppkey")
    assert choose.combine_plan(unique, choose.distinct_share(unique)) == "direct"
    assert choose.combine_plan(skewed, choose.distinct_share(skewed)) == "two_step"


def test_scan_reads_two_columns(spark, sf, capsys):
    stream_of(table(spark, sf, "lineitem").where("l_quantity > 40"), "l_partkey", "l_quantity").explain("formatted")
    plan = capsys.readouterr().out
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,40.0)" in plan
    assert "ReadSchema: struct<l_partkey:bigint,l_quantity:double>" in plan


def test_words_and_pairs_of_odd_texts(spark):
    docs = spark.createDataFrame([(1, "A b\n\na"), (2, None), (3, ""), (4, "one"), (5, " \t ")], "doc_id bigint, text string")
    assert sorted(r["word"] for r in heavy.words(docs).collect()) == ["a", "a", "b", "one"]
    pairs = sorted((r["left"], r["right"]) for r in heavy.pair_stream(docs).collect())
    assert pairs == [("a", "a"), ("a", "b"), ("b", "a")]


def test_heavy_hitters_have_no_false_negatives(spark, sf):
    c = Case(stream_of(table(spark, sf, "lineitem"), "l_partkey"))
    est = S.paged_estimate(c.packed(), c.exact, c.geom)
    for k in (50, 150, 400):
        exact, strict, relaxed = heavy.hh_exact(c.stream, k), heavy.hh_sketch(est, c.n, k), heavy.hh_sketch(est, c.n, k, "relaxed", c.cfg.eps)
        assert exact.join(strict, "item_key", "left_anti").count() == 0
        assert strict.join(relaxed, "item_key", "left_anti").count() == 0


def test_majority(spark):
    stream = spark.createDataFrame([(1, 3), (2, 1), (3, 1)], "item_key bigint, weight bigint")
    assert [tuple(r) for r in heavy.majority(stream).collect()] == [(1, 3)]
    assert heavy.majority(stream.where("item_key > 1")).count() == 0
    assert heavy.majority(stream.where("false")).count() == 0


def test_sql_functions_refuse_other_geometries(spark, sf):
    import pytest

    c = Case(uniform_stream(spark, sf), mode="straddling")
    with pytest.raises(ValueError):
        sqlapi.register(spark, c.geom)


def test_top_list_breaks_ties_by_key(spark):
    est = spark.createDataFrame([(3, 5), (1, 5), (2, 9)], "item_key bigint, est bigint")
    assert [r["item_key"] for r in heavy.topk(est, 2).collect()] == [2, 1]
    assert est.agg(F.count("*")).first()[0] == 3
