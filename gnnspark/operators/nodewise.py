"""Node-wise sampling: a fan-out per node and layer, for many batches in one plan."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from .prefix import places


def neighbour_rows(frontier: DataFrame, edges: DataFrame) -> DataFrame:
    """(batch_id, dst, src): all neighbours of the frontier's nodes. Edges bucketed by dst are not shuffled."""
    return frontier.select("batch_id", F.col("node_id").alias("dst")).join(edges.select("dst", "src"), "dst")


def sample_neighbors(frontier: DataFrame, edges: DataFrame, k: int, layer: int = 0, epoch: int = 0, seed: int = 7, replace: bool = False, prefer: DataFrame | None = None, prefers: Column | None = None, impl: str = "md5") -> DataFrame:
    """(batch_id, layer, dst, src): at most ``k`` neighbours a node.

    Without replacement the ``k`` least uniforms win; the rank limit runs before and after the shuffle, so hubs lose all but
    ``k`` rows in every input partition. With ``replace`` draw t takes place floor(u deg) of the adjacency ordered by id; hubs are ranked in cells.
    ``impl`` names the hash of the uniforms: ``md5`` agrees with other engines, ``xxhash64`` costs a fifth of it. ``prefer`` is a table of cached nodes that are taken first, in batches where ``prefers`` holds (all by default).
    """
    if replace:
        near = edges.join(frontier.select(F.col("node_id").alias("dst")).distinct(), "dst", "left_semi")
        ranked = places(near.select("dst", "src"), "dst", "src")
        deg = near.groupBy("dst").agg(F.count("*").alias("deg"))
        draws = frontier.select("batch_id", F.col("node_id").alias("dst"), F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("t")).join(deg, "dst")
        u = uniform(seed, epoch, F.col("batch_id"), layer, F.col("dst"), F.col("t"), impl=impl)
        placed = draws.withColumn("at", (F.floor(u * F.col("deg")) + 1).cast("long"))
        return placed.join(ranked, ["dst", "at"]).select("batch_id", F.lit(layer).alias("layer"), "dst", "src", "t")
    rows = neighbour_rows(frontier, edges)
    order = [uniform(seed, epoch, F.col("batch_id"), layer, F.col("dst"), F.col("src"), impl=impl), F.col("src")]
    if prefer is not None:
        rows = rows.join(prefer.select(F.col("node_id").alias("src"), F.lit(1).alias("cached")), "src", "left").withColumn("cached", F.coalesce("cached", F.lit(0)))
        first = F.col("cached") if prefers is None else F.when(prefers, F.col("cached")).otherwise(0)
        order = [first.desc(), *order]
    kept = rows.withColumn("r", F.row_number().over(Window.partitionBy("batch_id", "dst").orderBy(*order))).where(F.col("r") <= k)
    return kept.select("batch_id", F.lit(layer).alias("layer"), "dst", "src", *(["cached"] if prefer is not None else []))


def next_frontier(frontier: DataFrame, block: DataFrame) -> DataFrame:
    return frontier.select("batch_id", "node_id").union(block.select("batch_id", F.col("src").alias("node_id"))).distinct()


def sage_weights(block: DataFrame) -> DataFrame:
    """Adds ``w`` = 1/kept: the kept entries of the mean, scaled by degree over kept."""
    return block.withColumn("w", F.lit(1.0) / F.count("*").over(Window.partitionBy("batch_id", "layer", "dst")))


def gcn_block(block: DataFrame, frontier: DataFrame, prop: DataFrame, layer: int) -> DataFrame:
    """(batch_id, layer, dst, src, w): propagation entries of kept neighbours times degree over kept, and each node's own entry.

    Nodes of the frontier without neighbours have their own entry only.
    """
    deg = prop.where("row <> col").groupBy(F.col("row").alias("dst")).agg(F.count("*").alias("deg"))
    kept = F.count("*").over(Window.partitionBy("batch_id", "layer", "dst"))
    entries = prop.select(F.col("row").alias("dst"), F.col("col").alias("src"), "w")
    others = block.withColumn("kept", kept).join(entries, ["dst", "src"]).join(deg, "dst").select("batch_id", "layer", "dst", "src", (F.col("w") * F.col("deg") / F.col("kept")).alias("w"))
    own = frontier.select("batch_id", F.col("node_id").alias("dst")).join(entries.where("dst = src"), "dst")
    return others.unionByName(own.select("batch_id", F.lit(layer).alias("layer"), "dst", "src", "w"))


def expand_full(seeds: DataFrame, edges: DataFrame, hops: int) -> DataFrame:
    """(batch_id, hop, node_id): first-to-last full neighbourhoods, which the samplers avoid."""
    reached = seeds.select("batch_id", "node_id").distinct()
    out = reached.select("batch_id", F.lit(0).alias("hop"), "node_id")
    for hop in range(1, hops + 1):
        reached = reached.union(neighbour_rows(reached, edges).select("batch_id", F.col("src").alias("node_id"))).distinct()
        out = out.union(reached.select("batch_id", F.lit(hop).alias("hop"), "node_id"))
    return out


def node_wise_batches(seeds: DataFrame, edges: DataFrame, fanouts: list[int], epoch: int = 0, seed: int = 7, prefer: DataFrame | None = None, prefers: Column | None = None, keep: Callable[[DataFrame], DataFrame] | None = None, impl: str = "md5") -> tuple[list[DataFrame], list[DataFrame]]:
    """Blocks from the seeds' layer down, and the frontier above each block; the last frontier holds the inputs. One plan for all batches, unless ``keep`` (persist, spool) cuts it after each layer."""
    frontiers, blocks = [seeds.select("batch_id", "node_id").distinct()], []
    for i, k in enumerate(fanouts):
        layer = len(fanouts) - 1 - i
        block = sample_neighbors(frontiers[-1], edges, k, layer, epoch, seed, prefer=prefer, prefers=prefers, impl=impl)
        blocks.append(keep(block) if keep else block)
        block = blocks[-1]
        frontiers.append(next_frontier(frontiers[-1], block))
    return blocks, frontiers
