"""Connected components by contraction."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpart.plans.scratch import cut

#: Edges that one task may settle (16 bytes each, a few arrays of them); more are contracted by joins first.
IN_TASK = 1 << 20


def settle(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The vertices of the edges (a, b), ascending, and the smallest vertex of the component of each."""
    vertices, ends = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = ends[: len(a)], ends[len(a) :]
    root = np.arange(len(vertices))
    while len(x):
        low = np.minimum(root[x], root[y])
        np.minimum.at(root, root[x], low)
        np.minimum.at(root, root[y], low)
        while (root[root] != root).any():
            root = root[root]
        apart = root[x] != root[y]
        x, y = x[apart], y[apart]
    return vertices, vertices[root]


def _in_task(edges: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns]) for batch in batches if batch.num_rows]
        if parts:
            v, to = settle(*np.concatenate(parts, axis=1))
            yield pa.RecordBatch.from_arrays([pa.array(v), pa.array(to)], names=["v", "to"])

    return edges.coalesce(1).mapInArrow(run, "v long, to long")


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", seed: int = 7, max_rounds: int = 100, in_task: int = IN_TASK) -> DataFrame:
    """(v, root) for every vertex of ``edges``, longs; two vertices are connected if and only if their roots are equal.

    In every round a vertex moves to the member of its closed neighbourhood with the smallest keyed hash, and edges
    are contracted along the moves.  The hashed order makes the expected number of rounds logarithmic, also on paths
    with ascending ids.  Rounds are written to the shared folder; nothing but the number of edges left comes to the
    driver, and once ``in_task`` or fewer are left a single task settles them.
    """
    left = cut(edges.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).where("a <> b").distinct())
    roots = None
    for i in range(max_rounds):
        last = left.count() <= in_task
        if last:
            moves = cut(_in_task(left))
        else:
            both = left.union(left.select("b", "a"))
            order = lambda c: F.struct(F.xxhash64(c, F.lit(seed + i)).alias("h"), F.col(c).alias("v"))  # noqa: E731, B023
            moves = cut(both.groupBy("a").agg(F.min(order("b")).alias("n")).select(F.col("a").alias("v"), F.least(order("a"), F.col("n"))["v"].alias("to")))
        if roots is None:
            roots = moves.withColumnRenamed("to", "root")
        else:
            roots = cut(roots.join(moves.withColumnRenamed("v", "root"), "root", "left").select("v", F.coalesce("to", "root").alias("root")))
        if last:
            return roots
        once = left.join(moves.select(F.col("v").alias("a"), F.col("to").alias("x")), "a")
        left = cut(once.join(moves.select(F.col("v").alias("b"), F.col("to").alias("y")), "b").where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct())
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


def further_components(roots: DataFrame, edges: DataFrame, **options) -> DataFrame:
    """(v, root) after ``edges`` (a, b) join the components ``roots``: only the edges between components are contracted."""
    known = lambda end, to: roots.select(F.col("v").alias(end), F.col("root").alias(to))
    between = cut(edges.join(known("a", "x"), "a", "left").join(known("b", "y"), "b", "left").select("a", "b", F.coalesce("x", "a").alias("x"), F.coalesce("y", "b").alias("y")))
    moves = connected_components(between, "x", "y", **options)
    new = between.select(F.col("a").alias("v")).union(between.select("b")).distinct().join(roots, "v", "left_anti").select("v", F.col("v").alias("root"))
    return cut(roots.union(new).join(moves.select(F.col("v").alias("root"), F.col("root").alias("to")), "root", "left").select("v", F.coalesce("to", "root").alias("root")))
