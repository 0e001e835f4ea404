"""Distributed connected components by union-find in each task and star contraction between tasks."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagesketch.llm.common import cut

#: Edges that one union-find holds before it hands out its forest.
FOREST_EDGES = 1_000_000


class UnionFind:
    """Disjoint sets whose root is the smallest member."""

    def __init__(self) -> None:
        self.parent: dict = {}

    def find(self, x):
        parent = self.parent
        root = x
        while (up := parent.get(root, root)) != root:
            root = up
        while (up := parent.get(x, x)) != root:
            parent[x] = root
            x = up
        return root

    def join(self, a, b) -> None:
        a, b = self.find(a), self.find(b)
        if a != b:
            low, high = (a, b) if a < b else (b, a)
            self.parent[high] = low

    def forest(self) -> list[tuple]:
        return [(x, self.find(x)) for x in list(self.parent)]


def _local_forests(edges: DataFrame) -> DataFrame:
    kind = edges.schema["src"].dataType.simpleString()
    arrow = pa.int64() if kind == "bigint" else pa.string()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets = UnionFind()

        def out() -> pa.RecordBatch:
            rows = sets.forest()
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], arrow), pa.array([r[1] for r in rows], arrow)], ["src", "dst"])

        for batch in batches:
            for a, b in zip(batch.column("src").to_pylist(), batch.column("dst").to_pylist(), strict=True):
                sets.join(a, b)
            if len(sets.parent) >= FOREST_EDGES:
                yield out()
                sets = UnionFind()
        yield out()

    return edges.mapInArrow(run, f"src {kind}, dst {kind}")


def components(edges: DataFrame, max_rounds: int = 50, rows: int | None = None) -> DataFrame:
    """(node, component) of every node that an edge (src, dst) has; component is the smallest node reachable.

    Loops, repeated edges and either direction are fine; edges with a null end are left out.
    rows is about the number of edges, where it is known. Every round takes each node's neighbours to the smallest of them, first for the larger
    neighbours and then for the smaller ones, until only stars are left.
    """
    edges = edges.select("src", "dst").where("src is not null and dst is not null and src <> dst")
    edges = cut(_local_forests(edges), rows)
    rows = edges.count()
    for _ in range(max_rounds):
        both = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        # kept, so that the join has nothing but a shuffle on either side and a hub's edges can be split
        low = cut(both.groupBy("src").agg(F.min("dst").alias("low")).select("src", F.least("src", "low").alias("low")), rows)
        large = both.join(low, "src").where("dst > src").select(F.col("dst").alias("src"), F.col("low").alias("dst")).distinct()
        large = cut(large, rows)
        low = cut(large.groupBy("src").agg(F.min("dst").alias("low")), rows)
        small = large.join(low, "src")
        small = small.where("dst <> low").select(F.col("dst").alias("src"), F.col("low").alias("dst")).unionByName(low.select("src", F.col("low").alias("dst")))
        edges = cut(small.where("src <> dst").distinct(), rows)
        roots = edges.select(F.col("dst").alias("src")).distinct()
        twice = edges.groupBy("src").count().where("count > 1").select("src")
        if not edges.join(roots, "src", "left_semi").select("src").unionByName(twice).take(1):
            break
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = edges.select(F.col("dst").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return edges.select(F.col("src").alias("node"), F.col("dst").alias("component")).unionByName(roots)
