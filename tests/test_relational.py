import collections
import random

import pytest
from pyspark.sql import functions as F

from pagesketch.operators import relational


def test_positions_are_a_total_order(spark, tmp_path):
    rows = spark.range(0, 5000, 1, 7).select((F.col("id") * 7919 % 5000).alias("v"))
    placed = relational.with_positions(spark, rows, str(tmp_path / "p"), F.desc("v")).collect()
    assert sorted((r["pos"], r["v"]) for r in placed) == [(i, 4999 - i) for i in range(5000)]


def test_positions_of_nothing_and_of_ties(spark, tmp_path):
    none = spark.createDataFrame([], "v bigint")
    assert relational.with_positions(spark, none, str(tmp_path / "a"), F.col("v")).count() == 0
    same = spark.range(100).select(F.lit(None).cast("bigint").alias("v"))
    assert sorted(r["pos"] for r in relational.with_positions(spark, same, str(tmp_path / "b"), F.col("v")).collect()) == list(range(100))


@pytest.mark.parametrize("backwards", [False, True])
def test_carry_over_three_levels(spark, monkeypatch, backwards):
    monkeypatch.setattr(relational, "WIDTH", 5)
    rng = random.Random(3)
    rows = [(k, b, rng.choice([None, None, None, b * 10])) for k in "xy" for b in range(120) if rng.random() < 0.7]
    ends = spark.createDataFrame(rows, "k string, block bigint, end bigint")
    got = {(r["k"], r["block"]): r["carried"] for r in relational.carry(ends, 119, ("k",), backwards).collect()}
    want = {}
    for k in "xy":
        last = None
        for _, b, end in sorted((r for r in rows if r[0] == k), key=lambda r: r[1], reverse=backwards):
            want[k, b] = last
            last = last if end is None else end
    assert got == want


def test_salted_join_keeps_every_pair(spark):
    left = spark.createDataFrame([(i, "hot" if i % 10 else "cold") for i in range(300)] + [(999, None)], "i int, k string")
    right = spark.createDataFrame([("hot", 1), ("hot", 2), ("cold", 3), ("none", 4), (None, 5)], "k string, v int")
    want = left.join(right, "k").select("i", "v")
    got = relational.salted_join(left, right, "k", 5).select("i", "v")
    assert got.exceptAll(want).count() == 0 and want.exceptAll(got).count() == 0


def test_candidates_hold_every_frequent_item(spark):
    rng = random.Random(5)
    items = [f"w{int(rng.paretovariate(1))}" for _ in range(20_000)] + [None] * 50
    rows = spark.createDataFrame([(x,) for x in items], "w string").repartition(4)
    counts = collections.Counter(x for x in items if x)
    for k in (5, 20):
        found = {r["w"] for r in relational.frequent_candidates(rows, "w", k).collect()}
        assert {x for x, n in counts.items() if n * k >= len(items)} <= found and len(found) <= 4 * k
    assert relational.frequent_candidates(rows.where("false"), "w", 5).count() == 0
