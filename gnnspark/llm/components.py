"""Connected components over an edge table, by alternating large-star and small-star rounds.

Every round is two aggregates and two joins over the edges that are left, followed by a reliable
checkpoint; the driver sees two numbers a round. Labels are the smallest node id of a component.
A table of at most :data:`ONE_TASK` edges is merged by union-find in one task instead: rounds would write thousands of tiny files for it.

A node with very many edges would bring all of them to one task of a join. Such hubs are split off: their
least neighbours are broadcast, and only the edges of other nodes are shuffled. A node is a hub above ``2 E / MOST_HUBS`` edge ends of
E edges, so there are fewer than ``MOST_HUBS`` of them at any size.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blockpairs import Forest
from .state import checkpointed

MOST_HUBS, LEAST_HUB = 4096, 256
#: 16 bytes an edge: two MB at most meet in the task.
ONE_TASK = 1 << 17


def _least_neighbour(pairs: DataFrame) -> DataFrame:
    """(u, m, ends): combined before the shuffle, so a hub costs one row a task."""
    return pairs.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("ends"))


def _told(pairs: DataFrame, least: DataFrame, edges: int) -> DataFrame:
    """``pairs`` with the ``m`` of their ``u``."""
    bound = max(LEAST_HUB, -(-2 * edges // MOST_HUBS))
    hubs = F.broadcast(least.where(F.col("ends") > bound).select("u", "m"))
    usual = least.where(F.col("ends") <= bound).select("u", "m")
    return pairs.join(hubs, "u").union(pairs.join(hubs, "u", "left_anti").join(usual, "u"))


def _large_star(edges: DataFrame, n: int) -> DataFrame:
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = _least_neighbour(both).select("u", F.least("u", "m").alias("m"), "ends")
    return _told(both.where("v > u"), least, n).select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(edges: DataFrame, n: int) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u > v").distinct()
    least = _least_neighbour(down)
    moved = _told(down, least, n).where("v > m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def _in_one_task(edges: DataFrame) -> DataFrame:
    """(node, component) of a bounded edge table (u, v)."""

    def apply(batches):
        held = [np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()]) for b in batches]
        if held:
            ends = np.concatenate(held, axis=1)
            node, at = np.unique(ends, return_inverse=True)
            at = at.reshape(ends.shape)
            forest = Forest(len(node))
            forest.link(at[0], at[1])
            yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(node[forest.label])], names=["node", "component"])

    return edges.coalesce(1).mapInArrow(apply, "node long, component long")


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst") -> DataFrame:
    """(node, component) for every node with an edge to another node.

    Nulls and self loops make no link; repeated and reversed edges count once; an empty table gives an
    empty result. A node without edges is not listed: its component is itself.
    """
    left = checkpointed(edges.select(F.col(src).alias("u"), F.col(dst).alias("v")).where("u <> v"))
    seen = None
    n = left.count()
    if n <= ONE_TASK and {t for _, t in left.dtypes} == {"bigint"}:
        return _in_one_task(left)
    while True:
        left = checkpointed(_small_star(_large_star(left, n), n))
        mark = left.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if mark == seen or not mark[0]:
            break
        seen, n = mark, mark[0]
    label = left.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return label.union(label.select("component", "component").distinct())
