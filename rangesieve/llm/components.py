"""Connected components of an edge table; nothing is collected. Each task first reduces its edges to a forest. Where few are
left, one task joins the forests; else they go through alternating star steps."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangesieve.llm.common import materialise, ship_package

#: Edges that one task joins: 8 MB of them. In a task, a forest is made anew each time so many edges have come.
FEW, HELD = 500_000, 200_000


def stars(edges: np.ndarray) -> np.ndarray:
    """A star for each component of the edges, an array of two columns: at most one row (node, least node) a node."""
    parent: dict[int, int] = {}
    for a, b in edges.tolist():
        while (p := parent.setdefault(a, a)) != a:
            parent[a] = a = parent[p]
        while (p := parent.setdefault(b, b)) != b:
            parent[b] = b = parent[p]
        if a < b:
            parent[b] = a
        elif b < a:
            parent[a] = b
    out = []
    for x in sorted(parent):  # a parent is less than its node, so it is at its root already
        parent[x] = top = parent[parent[x]]
        if top != x:
            out.append((x, top))
    return np.array(out, np.int64).reshape(-1, 2)


def _forests(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Stars (u, v) of all the edges of a task."""
    held, made = [np.empty((0, 2), np.int64)], 0
    for batch in batches:
        u, v = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("u", "v"))
        held.append(np.stack([u, v], axis=1))
        if sum(map(len, held)) >= made + HELD:
            held = [stars(np.concatenate(held))]
            made = len(held[0])
    out = stars(np.concatenate(held))
    yield pa.record_batch([pa.array(out[:, 0]), pa.array(out[:, 1])], names=["u", "v"])


EDGES = "u long, v long"


def _least(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("n"), F.least("u", "m").alias("m"))


def _step(edges: DataFrame) -> DataFrame:
    """One large-star and one small-star step on edges (u, v), u > v."""
    both = edges.union(edges.select("v", "u"))
    near = _least(both)
    large = both.join(near, F.col("u") == F.col("n")).where("v > u and v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
    down = _least(large)
    linked = large.join(down, F.col("u") == F.col("n"))
    small = linked.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(down.select(F.col("n").alias("u"), F.col("m").alias("v")))
    return small.where("u > v").distinct()


def _mark(edges: DataFrame):
    return edges.agg(F.count("*").alias("n"), F.expr("bit_xor(xxhash64(u, v))").alias("x")).first()


def connected_components(edges: DataFrame, most: int = 60, few: int = FEW) -> DataFrame:
    """(node, root) of every node that has an edge in edges (u, v): root is the least node of the component."""
    ship_package(edges.sparkSession)
    now = materialise(edges.select("u", "v").where("u <> v").mapInArrow(_forests, EDGES), "edges")
    mark = _mark(now)
    if 0 < mark.n <= few:
        now = materialise(now.coalesce(1).mapInArrow(_forests, EDGES), "edges")
    elif mark.n:
        # Tasks may have the same edge, and the check for an end counts each once.
        now = materialise(now.distinct(), "edges")
        mark = _mark(now)
        for _ in range(most):
            after = materialise(_step(now), "edges")
            seen = _mark(after)
            now, (mark, before) = after, (seen, mark)
            if seen == before:
                break
        else:
            raise RuntimeError("components did not settle")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).union(now.select("v", "v").distinct())
