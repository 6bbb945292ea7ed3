"""Connected components of an edge table, with DataFrame operations only."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from objann.llm.shared import WrittenTable, written

ONE_TASK_EDGES = 1_000_000  # an edge table of at most so many rows is one task's work


def _one_task(pairs: DataFrame) -> DataFrame:
    """Components of a small edge table by union and find in one task."""

    def unite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parent: dict = {}

        def root(x):
            while (up := parent.setdefault(x, x)) != x:
                parent[x] = x = parent[up]
            return x

        for batch in batches:
            for u, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                a, b = root(u), root(v)
                if a != b:
                    parent[max(a, b)] = min(a, b)
        nodes = list(parent)
        kind = pairs_kind
        yield pa.RecordBatch.from_arrays([pa.array(nodes, kind), pa.array([root(x) for x in nodes], kind)], ["node", "component"])

    name = pairs.schema["u"].dataType.simpleString()
    pairs_kind = pa.string() if name == "string" else pa.int64()
    return pairs.coalesce(1).mapInArrow(unite, f"node {name}, component {name}")


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 200, one_task_edges: int = ONE_TASK_EDGES) -> DataFrame:
    """(node, component): the least node that each node is connected with.

    Alternates two steps on the edge table until it is stable: every node's larger neighbours are
    linked to its least neighbour, then every node and its smaller neighbours are linked to the
    least of them.  The edges shrink to stars around component minima in a number of rounds that
    grows with the logarithm of the size.  Minima are partial aggregates, so a hub is no single
    task's work; joins with a hub are split by the adaptive planner.  Each round is a written table.
    If it is not stable after ``max_rounds`` rounds, which a doubling of reach makes impossible in practice, that is an error.
    Loops and null ends are ignored; nodes without edges do not appear.  Up to ONE_TASK_EDGES edges
    one task does the same by union and find; the result does not depend on the way.
    """
    pairs = edges.select(F.greatest(src, dst).alias("u"), F.least(src, dst).alias("v")).where("u <> v").distinct()
    state = WrittenTable(pairs, "components")
    if state.df.limit(one_task_edges + 1).count() <= one_task_edges:
        return written(_one_task(state.df), "components-small")
    before = None
    for _ in range(max_rounds):
        e = state.df
        both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = WrittenTable(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "components-least")
        large = both.join(least.df, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        large = WrittenTable(large, "components-large")
        small_least = WrittenTable(large.df.groupBy("u").agg(F.min("v").alias("m")), "components-small")
        joined = large.df.join(small_least.df, "u")
        small = joined.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").union(small_least.df.select("u", F.col("m").alias("v"))).distinct()
        new = WrittenTable(small, "components")
        now = new.df.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        for old in (state, least, large, small_least):
            old.drop()
        state = new
        if tuple(now) == before:
            break
        before = tuple(now)
    else:
        raise RuntimeError(f"components are not stable after {max_rounds} rounds")
    stars = state.df
    roots = stars.select(F.col("v").alias("node")).distinct()
    return stars.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots.select("node", F.col("node").alias("component")))
