"""Connected components: a bounded number of links in one task, more by alternating large-star and small-star steps, all in joins and aggregates.

Each step plans several exchanges and broadcasts, whose threads, code and hash tables the driver holds however few the links are. So links that
one task can hold by their count are solved there; they don't pass through the driver.
"""
from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .common import discard, written

MOST_IN_A_TASK = 500_000  # links (16 bytes each, some 10 times that while they are solved) that one task takes


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One step over (u, v), u > v. Minima are aggregated map-side, so a node of any degree is safe; the join may be split by AQE."""
    if large:
        edges = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = edges.groupBy(F.col("u").alias("w")).agg(F.min("v").alias("m")).select("w", F.least("m", "w").alias("m"))
    joined = edges.join(least, F.col("u") == F.col("w"))
    if large:
        out = joined.where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        out = joined.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(least.select(F.col("w").alias("u"), F.col("m").alias("v")))
    return out.where("u <> v").distinct()


def roots_of(u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, roots) of the links u - v: every node that isn't its component's smallest one, and that one."""
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b = at.reshape(2, -1)
    up = np.arange(len(nodes))  # each node points to itself or to a smaller one
    while len(a):
        np.minimum.at(up, np.maximum(a, b), np.minimum(a, b))
        while not np.array_equal(further := up[up], up):
            up = further
        a, b = up[a], up[b]
        a, b = a[a != b], b[a != b]
    below = up != np.arange(len(nodes))
    return nodes[below], nodes[up[below]]


def _solved(batches):
    held = [(b.column(0).to_numpy(), b.column(1).to_numpy()) for b in batches if b.num_rows]
    if held:
        nodes, roots = roots_of(*(np.concatenate(x) for x in zip(*held)))
        yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(roots)], names=["node", "root"])


def connected_components(links: DataFrame, a: str, b: str) -> DataFrame:
    """(node, root) for every node of a link that isn't its component's smallest node; root is that smallest node."""
    pairs = links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u <> v").distinct()
    edges = written(pairs, "links")
    if edges.count() <= MOST_IN_A_TASK:
        roots = written(edges.coalesce(1).mapInArrow(_solved, "node long, root long"), "roots")
        discard(edges)
        return roots
    mark = None
    while True:
        stepped = written(_star(_star(edges, True), False), "stars")
        discard(edges)
        edges = stepped
        now = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")).first()
        if (now.n, now.h) == mark or not now.n:
            roots = edges.select(F.col("u").alias("node"), F.col("v").alias("root"))
            roots._written_at = edges._written_at
            return roots
        mark = (now.n, now.h)
