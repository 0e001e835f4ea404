"""Times the headline queries; prints one JSON line.

BENCH_SF_DIR names the tables (default /root/testdata/sf0.1), BENCH_CPUS the cores (default all).
Beside seconds per query the line has the paper's comparisons as ratios of flat over paged: wall clock, shuffled records an operation,
and logical I/O, and the update cost of in-memory sketches by size.
"""

from __future__ import annotations

import json
import os
import tempfile
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from pagesketch.config import PageGeometry, SketchConfig
from pagesketch.operators import sketch as S
from pagesketch.plans.metrics import shuffle_cost
from pagesketch.queries import QUERIES
from pagesketch.queries_core import Case, uniform_stream
from pagesketch.sources.store import PageStore
from pagesketch.sources.tables import stream_of, table, uniform_keys

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", str(os.cpu_count()))
HEADLINE = ("exact_counts", "flat_build", "paged_build", "flat_estimate", "paged_estimate", "over_summary", "io_ram_sweep", "mixed_estimates", "hh_strict", "bestsellers", "top_words", "word_pairs", "heavy_by_region", "w_query_flat", "w_query_paged")


def seconds(df) -> float:
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return round(time.perf_counter() - began, 3)


def size_sweep(keys, sizes: tuple[int, ...] = tuple(1 << k for k in range(12, 27, 2))) -> dict[str, float]:
    """Nanoseconds an update in one process's memory, by bytes of the sketch, with five hashes throughout."""
    import numpy as np

    out = {}
    for size in sizes:
        width = max(1, size // (5 * 8))
        table_ = np.zeros((5, width), np.int64)
        best = float("inf")
        for _ in range(3):
            began = time.perf_counter()
            for row in range(5):
                at = (keys * np.uint64(2 * row + 0x9E3779B97F4A7C15) >> np.uint64(20)) % np.uint64(width)
                np.add.at(table_[row], at.astype(np.int64), 1)
            best = min(best, time.perf_counter() - began)
        out[str(size)] = round(best / len(keys) * 1e9, 1)
    return out


def four_sizes(spark, n: int, root: str) -> dict[str, dict]:
    """Both sketches at four sizes, whose ratio to a fixed memory is 2, 4, 8 and 16: unique keys inserted and written, then asked for from cold files.

    An insert ends when all counters are in files, as the last drain does. pack_paged is the further cost of one record a page. Ratios are flat over
    paged, without and with packing; overestimates are those of all inserted keys.
    """
    out = {}
    for ratio in (2, 4, 8, 16):
        keys = uniform_keys(spark, n * ratio // 16).select("item_key", F.lit(1).cast("bigint").alias("weight")).cache()
        c = Case(keys)
        path = {k: f"{root}/{ratio}-{k}" for k in ("flat", "paged", "pages")}

        def written(df, to: str) -> float:
            began = time.perf_counter()
            df.write.mode("overwrite").parquet(to)
            return round(time.perf_counter() - began, 3)

        def least(df, to: str) -> float:
            return min(written(df, to) for _ in range(2))

        one = {"n": c.n, "pages": c.geom.pages, "insert_flat": least(c.flat(), path["flat"]), "insert_paged": least(S.paged_build(keys, c.geom, combine="direct"), path["paged"])}
        one["pack_paged"] = least(S.paged_pack(spark.read.parquet(path["paged"]), c.geom, how="arrow"), path["pages"])
        keys.unpersist()
        asked = uniform_keys(spark, c.n).select("item_key")
        ask = {"flat": lambda: S.flat_estimate(spark.read.parquet(path["flat"]), asked, c.cfg, strategy="shuffle_hash"), "paged": lambda: S.paged_estimate(spark.read.parquet(path["pages"]), asked, c.geom, strategy="shuffle_hash")}  # noqa: B023
        for name, run in ask.items():
            one[f"cold_query_{name}"] = min(seconds(run()) for _ in range(2))
            over = run().agg(F.round(F.avg(F.col("est") - 1), 4), F.max(F.col("est") - 1)).first()
            one[f"avg_over_{name}"], one[f"max_over_{name}"] = over[0], over[1]
        one["insert_ratio"] = round(one["insert_flat"] / one["insert_paged"], 2)
        one["insert_ratio_packed"] = round(one["insert_flat"] / (one["insert_paged"] + one["pack_paged"]), 2)
        one["cold_query_ratio"] = round(one["cold_query_flat"] / one["cold_query_paged"], 2)
        out[str(ratio)] = one
    return out


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("OFF")
    spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count().collect()
    queries = {}
    for name in HEADLINE:
        began = time.perf_counter()
        QUERIES[name](spark, SF_DIR).write.format("noop").mode("overwrite").save()
        queries[name] = round(time.perf_counter() - began, 3)

    # the paper's workload: unique keys, inserted and asked
    keys = uniform_stream(spark, SF_DIR).cache()
    c = Case(keys)
    runs = {}
    for name, build in (("flat", c.flat), ("paged", lambda: S.paged_build(keys, c.geom, combine="direct"))):
        build().count()
        runs[f"insert_{name}"] = min(seconds(build()) for _ in range(3))
        runs[f"insert_{name}_shuffle"] = shuffle_cost(build())
    flat, pages = c.flat().cache(), c.packed().cache()
    flat.count(), pages.count()
    asked = keys.select("item_key")
    for name, ask in (("flat", lambda: S.flat_estimate(flat, asked, c.cfg, strategy="shuffle_hash")), ("paged", lambda: S.paged_estimate(pages, asked, c.geom, strategy="shuffle_hash"))):
        runs[f"query_{name}"] = min(seconds(ask()) for _ in range(3))
        runs[f"query_{name}_shuffle"] = shuffle_cost(ask())

    # cold: a store is written, caches are dropped, and one key and many keys are asked
    store = PageStore.create(spark, tempfile.mkdtemp() + "/store", c.geom, buckets=32)
    store.append_delta(keys, 0)
    store.compact()
    spark.catalog.clearCache()
    again = PageStore.open(spark, store.root, c.geom)
    runs["cold_query_store"] = seconds(again.estimate(keys.select("item_key")))
    one = keys.first()["item_key"]
    began = time.perf_counter()
    again.lookup(one)
    runs["cold_point_lookup"] = round(time.perf_counter() - began, 3)

    # larger pages, a lever for large clusters
    for kib in (4, 64):
        geom = PageGeometry.of(SketchConfig.from_stream(c.n), kib << 10)
        runs[f"insert_paged_{kib}k"] = seconds(S.paged_build(keys, geom, combine="direct"))
    weighted = stream_of(table(spark, SF_DIR, "lineitem"), "l_suppkey", "l_quantity")
    hot = Case(weighted)
    runs["insert_skewed_two_step"] = seconds(S.paged_build(weighted, hot.geom, combine="two_step"))
    runs["insert_skewed_direct"] = seconds(S.paged_build(weighted, hot.geom, combine="direct"))

    spark.catalog.clearCache()
    sizes = four_sizes(spark, c.n, tempfile.mkdtemp())

    import numpy as np

    sweep = size_sweep(np.random.default_rng(1).integers(0, 1 << 63, 200_000, dtype=np.uint64))
    ratios = {
        "insert_wall": round(runs["insert_flat"] / runs["insert_paged"], 2),
        "query_wall": round(runs["query_flat"] / runs["query_paged"], 2),
        "insert_shuffled_records": round(runs["insert_flat_shuffle"]["records"] / max(1, runs["insert_paged_shuffle"]["records"]), 2),
        "query_shuffled_records": round(runs["query_flat_shuffle"]["records"] / max(1, runs["query_paged_shuffle"]["records"]), 2),
    }
    line = {"metric": "headline queries, total", "value": round(sum(queries.values()), 3), "unit": "sec", "queries": queries, "sf": os.path.basename(SF_DIR.rstrip("/")), "cpus": CPUS, "n": c.n, "pages": c.geom.pages, "runs": runs, "flat_over_paged": ratios, "by_sketch_over_ram": sizes, "ns_per_update_by_bytes": sweep}
    print(json.dumps(line))
    spark.stop()


if __name__ == "__main__":
    main()
