import pytest
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry, SketchConfig
from pagesketch.functions import hashing as H
from pagesketch.operators import iosim
from pagesketch.operators import sketch as S
from pagesketch.operators.buffer import BufferedModel
from pagesketch.queries_core import log_case
from pagesketch.sources.store import PageStore
from pagesketch.sources.tables import oplog, stream_of, table
from pagesketch.streaming import ingest


@pytest.fixture(scope="module")
def log(spark, sf):
    return log_case(spark, sf)


def located(log):
    events, geom = log
    cols = F.array(*H.page_columns(F.col("item_key"), F.col("page"), geom))
    return events.withColumn("page", H.page_of(F.col("item_key"), geom)).select("seq", "op", "item_key", "page", "weight", cols.alias("cols")).orderBy("seq").collect()


@pytest.mark.parametrize("capacity", [1, 7])
@pytest.mark.parametrize("policy", ["dirty", "always"])
def test_mixed_log_equals_the_sequential_model(log, capacity, policy):
    events, geom = log
    model, want = BufferedModel(geom, capacity, policy), {}
    for r in located(log):
        if r["op"] == "insert":
            model.update(r["page"], tuple(r["cols"]))
        else:
            want[r["seq"]] = model.estimate(r["page"], tuple(r["cols"]))
    model.close()
    assert {r["seq"]: r["est"] for r in iosim.mixed_estimates(events, geom).collect()} == want
    flushes = iosim.mixed_flushes(events, geom, capacity)
    total = flushes.agg(*(F.sum(c) for c in ("full_flushes", "early_drains", "final_drains"))).first()
    assert total[0] == model.full_flushes and total[1] + total[2] == model.drains
    assert iosim.mixed_io(flushes).first()[f"rw_{policy}"] == model.reads + model.writes


def test_a_buffer_alone_undershoots(log):
    events, geom = log
    model = BufferedModel(geom, 10**9)
    rows = [r for r in located(log) if r["op"] == "insert"]
    for r in rows:
        model.update(r["page"], tuple(r["cols"]))
    assert not any(model.pages.values())
    assert model.estimate(rows[0]["page"], tuple(rows[0]["cols"])) >= 1


def test_insert_io_lies_near_the_formula(spark, sf):
    from pagesketch.config import BufferPlan
    from pagesketch.queries_core import Case

    c = Case(stream_of(table(spark, sf, "lineitem"), "l_orderkey"))
    for ratio in (2, 4, 8, 16):
        plan = BufferPlan.oversubscribed(c.geom, ratio)
        io = iosim.paged_inserts(c.stream, c.geom, plan.capacity).first()["io_per_op"]
        assert plan.update_io <= io + 1e-9 and io <= 1 / plan.capacity + c.geom.pages / c.n + 1e-9


def test_store(spark, sf, tmp_path):
    lines = table(spark, sf, "lineitem")
    stream = stream_of(lines, "l_orderkey")
    from pagesketch.queries_core import Case

    c = Case(stream)
    store = PageStore.create(spark, str(tmp_path / "store"), c.geom, buckets=4)
    assert store.append_delta(stream_of(lines.where("l_linenumber < 3"), "l_orderkey"), 0)
    assert not store.append_delta(stream, 0)
    store.compact()
    store.append_delta(stream_of(lines.where("l_linenumber >= 3"), "l_orderkey"), 1)
    again = PageStore.open(spark, str(tmp_path / "store"), c.geom)
    want = {r["item_key"]: r["est"] for r in S.paged_estimate(c.packed(), c.exact, c.geom).collect()}
    assert {r["item_key"]: r["est"] for r in again.estimate(c.exact).collect()} == want
    key = next(iter(want))
    assert again.lookup(key) == want[key]
    assert again.due(1) and not again.due(10**9)
    again.compact()
    assert again.state["n"] == c.n and not again.append_delta(stream, 1)
    assert {r["item_key"]: r["est"] for r in again.estimate(c.exact).collect()} == want
    assert again.vacuum() > 0 and again.vacuum() == 0
    assert {r["item_key"]: r["est"] for r in PageStore.open(spark, again.root, c.geom).estimate(c.exact).collect()} == want
    with pytest.raises(ValueError):
        PageStore.open(spark, str(tmp_path / "store"), PageGeometry.of(SketchConfig.from_stream(123)))


def test_only_full_buckets_are_folded(spark, log, tmp_path, monkeypatch):
    _, geom = log
    store = PageStore.create(spark, str(tmp_path / "store"), geom, buckets=4)
    keys = spark.range(200).select(F.col("id").alias("item_key"))
    place = store.bucket_of(H.page_of(F.col("item_key"), geom))
    hot = keys.select("item_key", F.when(place == 1, 50).otherwise(1).cast("bigint").alias("weight"))
    for batch in range(2):
        store.append_delta(hot, batch)
        assert store.due(200) == [1]
        store.compact(store.due(200))
        assert list(store.state["generations"]) == ["1"] and store.due(200) == []
    assert store.state["batches"] == [0, 1]
    want = S.paged_build(hot.union(hot), geom)
    for _ in range(2):
        assert store.read().exceptAll(want).count() == 0 and want.exceptAll(store.read()).count() == 0
        store.compact()
        assert store.state["batches"] == [] and store.state["folded_to"] == {}
    one = keys.where("item_key = 7")
    page = one.select(H.page_of(F.col("item_key"), geom)).first()[0]
    asked = []
    monkeypatch.setattr(store, "read", lambda buckets: asked.append(buckets) or PageStore.read(store, buckets))
    assert store.estimate(one).first()["est"] >= 2 and asked == [[page * 4 // geom.pages]]
    assert not store.append_delta(hot, 1)


@pytest.fixture(scope="module")
def files(spark, sf, tmp_path_factory):
    folder = tmp_path_factory.mktemp("events")
    events = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    for k in range(3):
        events.where(f"event_id % 3 = {k}").coalesce(1).write.parquet(f"{folder}/part={k}")
    return str(folder)


def source(spark, files):
    return spark.readStream.schema(ingest.EVENTS).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(files)


def test_stream_into_store(spark, sf, files, log, tmp_path):
    _, geom = log
    store = PageStore.create(spark, str(tmp_path / "s"), geom, buckets=2)
    for _ in range(2):  # the second run starts from the checkpoint and adds nothing
        query = ingest.ingest(ingest.item_stream(source(spark, files)), store, str(tmp_path / "c"), capacity=20)
        assert query.awaitTermination(120)
    want = S.paged_build(stream_of(table(spark, sf, "events"), "user_id"), geom)
    assert store.read().exceptAll(want).count() == 0 and want.exceptAll(store.read()).count() == 0


def test_page_states(spark, sf, files, log, tmp_path):
    _, geom = log
    states = ingest.page_states(ingest.item_stream(source(spark, files)).select("item_key", "weight"), geom, capacity=7)
    query = states.writeStream.format("memory").queryName("page_states").outputMode("update").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    assert query.awaitTermination(180)
    last = spark.table("page_states").groupBy("page").agg(F.max("load").alias("load"), F.max_by("pending", "load").alias("pending"), F.max("flushes").alias("flushes"))
    assert last.agg(F.sum("load")).first()[0] == table(spark, sf, "events").count()
    assert last.where(F.col("flushes") * 7 + F.col("pending") != F.col("load")).count() == 0


def test_windows(spark, sf, files, log, tmp_path):
    _, geom = log
    batch = ingest.windowed_build(ingest.item_stream(table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))), geom)
    stream = ingest.windowed_build(ingest.item_stream(source(spark, files)), geom, watermark="10000 days")
    query = stream.writeStream.format("memory").queryName("windows").outputMode("complete").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    assert query.awaitTermination(180)
    assert spark.table("windows").exceptAll(batch).count() == 0 and batch.count() == spark.table("windows").count()


def test_late_rows_and_repeats(spark, tmp_path):
    folder = str(tmp_path / "in")
    for k, rows in enumerate([[(1, "2024-01-01 10:00:00"), (1, "2024-01-01 10:00:00")], [(2, "2024-01-01 20:00:00")], [(5, "2024-01-01 20:30:00")], [(3, "2024-01-01 10:05:00")], [(4, "2024-01-02 20:00:00")]]):
        spark.createDataFrame(rows, "k bigint, t string").select("k", F.to_timestamp("t").alias("ts")).coalesce(1).write.mode("append").parquet(folder)
    import os
    import time

    for k, f in enumerate(sorted((os.path.join(folder, x) for x in os.listdir(folder) if x.endswith(".parquet")), key=os.path.getmtime)):
        os.utime(f, (time.time() - 100 + k, time.time() - 100 + k))
    stream = spark.readStream.schema("k bigint, ts timestamp").option("maxFilesPerTrigger", 1).parquet(folder)
    once = ingest.first_only(stream, "k")
    query = once.writeStream.format("memory").queryName("once").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    assert query.awaitTermination(120)
    assert sorted(r["k"] for r in spark.table("once").collect()) == [1, 2, 4, 5]


def test_stream_of_questions(spark, sf, files, log, tmp_path):
    _, geom = log
    stream = stream_of(table(spark, sf, "events"), "user_id")
    pages = S.paged_pack(S.paged_build(stream, geom), geom)
    asked = ingest.item_stream(source(spark, files)).select("item_key")
    query = ingest.estimate_stream(asked, pages, geom).writeStream.format("memory").queryName("answers").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    assert query.awaitTermination(120)
    want = S.paged_estimate(pages, stream, geom)
    assert spark.table("answers").distinct().exceptAll(want).count() == 0


def test_log_roles(spark, sf):
    log = oplog(table(spark, sf, "events"))
    assert {r["op"] for r in log.select("op").distinct().collect()} == {"insert", "estimate"}
