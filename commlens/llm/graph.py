"""Connected components of a large sparse graph by alternating star contractions, as DataFrame joins; a small rest is connected at once."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from commlens.llm.common import Scratch

#: Edges of 64-bit numbers that the driver connects itself (4 MB of them): rounds over so few cost many stages, and the driver keeps a record of each of their tasks.
LOCAL_EDGES = 250_000


def _both_ways(edges: DataFrame) -> DataFrame:
    return edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))


def _large_star(edges: DataFrame) -> DataFrame:
    """Larger neighbours of each node move to the node's least neighbour."""
    around = _both_ways(edges)
    least = around.groupBy("a").agg(F.min("b").alias("m"))
    return around.join(least, "a").where("b > a").select(F.col("b").alias("a"), F.least("a", "m").alias("b")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """A node and its smaller neighbours move to the least of them; edges point from larger to smaller here."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    moved = edges.join(least, "a").where("b > m").select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(least.select("a", F.col("m").alias("b"))).distinct()


def least_of_each(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The nodes of edges (a, b), and the least node that each is connected with."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    left, right, root = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while True:
        low, high = np.minimum(root[left], root[right]), np.maximum(root[left], root[right])
        apart = low < high
        if not apart.any():
            return nodes, nodes[root]
        np.minimum.at(root, high[apart], low[apart])
        while (root[root] != root).any():
            root = root[root]


def components(scratch: Scratch, edges: DataFrame, local: int | None = None) -> DataFrame:
    """(node, root) for every node of an edge; root is the least node of the component.

    ``edges`` has two columns of one ordered type; self-loops and repeats do no harm. Each round is written to the shared folder; at most ``local``
    edges (LOCAL_EDGES) of 64-bit numbers, at the start or after a round, are connected on the driver. An empty table gives an empty table."""
    a, b = (F.col(c) for c in edges.columns)
    now = scratch.table(edges.where(a != b).select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).distinct())

    def mark(df: DataFrame) -> tuple:
        return tuple(df.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    seen = mark(now)
    local = (LOCAL_EDGES if local is None else local) if {t for _, t in now.dtypes} == {"bigint"} else 0
    while seen[0]:
        if seen[0] <= local:
            rows = now.toArrow()
            scratch.drop(now)
            nodes, roots = least_of_each(*(rows.column(c).to_numpy() for c in ("a", "b")))
            return scratch.table(now.sparkSession.createDataFrame(pa.table({"node": nodes, "root": roots})))
        wide = scratch.table(_large_star(now))
        after = scratch.table(_small_star(wide))
        scratch.drop(now)
        scratch.drop(wide)
        now, last, seen = after, seen, mark(after)
        if seen == last:
            break
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
