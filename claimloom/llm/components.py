"""Distributed union-find on an edge table: alternating large and small stars, DataFrame operations only."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import forget, unsent, written


FEW = 1 << 18
ROUNDS = 64


def connected(edges: DataFrame, left: str, right: str, rounds: int | None = None, few: int = FEW) -> DataFrame:
    """(node, root) for every node of an edge; root is the smallest node of the component.

    Each round links every larger neighbour of a node to the node's smallest neighbour (large star), then every node to
    the smallest of its smaller neighbours (small star). A set of stars is a fixed point. Sums and minima combine before
    the shuffle; hot nodes meet only in joins that Spark may split. Up to `few` counted edges, the driver unites them instead,
    unless the caller bounds the rounds (ROUNDS otherwise). Components that have not settled after them are an error.
    """
    e = written(edges.select(F.least(left, right).alias("u"), F.greatest(left, right).alias("v")).where("u < v").distinct(), "edges")
    state = _state(e)
    if rounds is None and state[0] <= few:
        done = written(_gathered(e), "components")
        forget(e)
        return done
    rounds = ROUNDS if rounds is None else rounds
    for _ in range(rounds):
        if not state[0]:
            break
        both = e.union(e.select("v", "u"))
        lowest = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = e.join(unsent(lowest, state[0]), "u").select(F.col("m").alias("u"), "v").where("u < v").distinct()
        parent = large.groupBy("v").agg(F.min("u").alias("m"))
        small = large.join(unsent(parent, state[0]), "v").select(F.explode(F.array(F.struct(F.col("m").alias("u"), F.col("u").alias("v")), F.struct(F.col("m").alias("u"), F.col("v").alias("v")))).alias("x"))
        step = written(small.select("x.*").where("u < v").distinct(), "edges")
        after = _state(step)
        forget(e)
        e = step
        if after == state:
            break
        state = after
    else:
        raise RuntimeError(f"components have not settled after {rounds} rounds")
    return e.select(F.col("v").alias("node"), F.col("u").alias("root")).union(e.select("u", "u").distinct())


def _gathered(e: DataFrame) -> DataFrame:
    """(node, root) by a union-find over all edges (u, v) on the driver."""
    edges = e.toArrow()
    kind = edges.schema.field("u").type
    nodes, ends = np.unique(np.concatenate([edges[c].to_numpy() for c in ("u", "v")]), return_inverse=True)
    u, v = ends[: len(edges)], ends[len(edges) :]
    root = np.arange(len(nodes))  # places in the sorted nodes; always roots of roots
    while True:
        x, y = root[u], root[v]
        apart = x != y
        if not apart.any():
            break
        u, v, x, y = u[apart], v[apart], x[apart], y[apart]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while ((above := root[root]) != root).any():
            root = above
    pairs = pa.table({"node": pa.array(nodes, kind), "root": pa.array(nodes[root], kind)})
    return e.sparkSession.createDataFrame(pairs) if len(nodes) else e.select(F.col("v").alias("node"), F.col("u").alias("root"))


def _state(e: DataFrame) -> tuple:
    row = e.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)")).alias("h")).first()
    return row["n"], row["h"]
