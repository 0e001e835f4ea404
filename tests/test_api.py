import time

import pytest
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry, SketchConfig
from pagesketch.operators.api import FlatSketch, PagedSketch, config_df
from pagesketch.queries_core import Case
from pagesketch.sources.tables import stream_of, table
from pagesketch.streaming.ingest import soak_source


@pytest.fixture(scope="module")
def c(spark, sf):
    return Case(stream_of(table(spark, sf, "orders"), "o_custkey"))


def answers(df):
    return {r["item_key"]: r["est"] for r in df.collect()}


def test_write_read_merge_and_ask(spark, c, tmp_path):
    whole = PagedSketch.build(c.stream, c.geom)
    halves = [PagedSketch.build(c.stream.where(f"item_key % 2 = {k}"), c.geom) for k in (0, 1)]
    want = answers(whole.estimate(c.exact))
    assert answers(halves[0].merge(halves[1]).estimate(c.exact)) == want
    whole.write(str(tmp_path / "s"), buckets=4)
    again = PagedSketch.read(spark, str(tmp_path / "s"))
    assert again.geom == c.geom and answers(again.estimate(c.exact)) == want
    key = max(want, key=want.get)
    assert again.lookup(key) == want[key] and again.lookup(-5) >= 0
    true = {r["item_key"]: r["true_count"] for r in c.exact.collect()}
    assert all(want[k] >= n for k, n in true.items())


def test_only_like_sketches_meet(c):
    other = PageGeometry.of(SketchConfig.from_stream(7))
    with pytest.raises(ValueError):
        PagedSketch.build(c.stream, c.geom).merge(PagedSketch.build(c.stream, other))
    with pytest.raises(ValueError):
        FlatSketch.build(c.stream, c.cfg).merge(FlatSketch.build(c.stream, other.cfg))
    both = FlatSketch.build(c.stream, c.cfg).merge(FlatSketch.build(c.stream, c.cfg))
    once = answers(FlatSketch.build(c.stream, c.cfg).estimate(c.exact))
    assert answers(both.estimate(c.exact)) == {k: 2 * v for k, v in once.items()}


def test_straddling_pages(c):
    geom = PageGeometry.of(c.cfg, mode="straddling")
    over = PagedSketch.build(c.stream, geom).estimate(c.exact).join(c.exact, "item_key").where("est < true_count")
    assert over.count() == 0


def test_configuration_rows(spark, c):
    row = config_df(spark, c.cfg, c.geom).first()
    assert row["depth"] == 5 and row["pages"] == c.geom.pages and row["fingerprint"] == c.geom.fingerprint()
    assert config_df(spark, c.cfg).first()["size_bytes"] == c.cfg.size_bytes


def test_soak_source(spark, tmp_path):
    query = soak_source(spark, 200, 50).writeStream.format("memory").queryName("soak").option("checkpointLocation", str(tmp_path)).start()
    try:
        for _ in range(60):
            time.sleep(0.5)
            if spark.table("soak").count() > 100:
                break
    finally:
        query.stop()
    assert spark.table("soak").where("item_key < 0 or item_key >= 50").count() == 0
    assert spark.table("soak").agg(F.count("*")).first()[0] > 100
