"""Streams of mini-batches: sampled and packaged by a few Spark plans for all models, seeds, epochs and splits at once.

A stream is what a training run reads: the batches of one model, with or without the cache, for one seed. Streams, epochs and places are parts of the batch id, so
the two node-wise models share one plan, and so do the four variants of each layer-wise base. The id of the batch at ``place`` of epoch e in stream s is
``(s * (epochs + 2) + e) * width + place``; epoch ``epochs`` holds the validation batches, the one after it the test batches.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..operators import cache as C
from ..operators import kernels, layerwise, nodewise
from ..operators.propagation import propagation, split_of
from ..sources.graphs import Graph

NODE_WISE = ("gcn", "graphsage")
MODELS = (*NODE_WISE, *layerwise.VARIANTS)


@dataclass(frozen=True)
class Stream:
    model: str
    cached: bool = False
    seed: int = 7


@dataclass(frozen=True)
class Ids:
    """The parts of a batch id."""

    epochs: int
    width: int

    def of(self, stream: Column, epoch: Column, place: Column) -> Column:
        return ((stream * (self.epochs + 2) + epoch) * self.width + place).cast("long")

    def stream(self, batch: Column) -> Column:
        return F.floor(batch / (self.width * (self.epochs + 2))).cast("int")

    def epoch(self, batch: Column) -> Column:
        return (F.floor(batch / self.width) % (self.epochs + 2)).cast("int")


@dataclass
class Sizes:
    batch: int = 64
    fanout: int = 5
    layer: int = 512
    epochs: int = 3
    cache_share: float = 0.01


def known_nodes(g: Graph, labels: DataFrame, seed: int = 7) -> DataFrame:
    """(node_id, y, split) of the labelled nodes."""
    return labels.where("y is not null").join(g.nodes.select("node_id", split_of(F.col("node_id"), g.name, seed).alias("split")), "node_id").select("node_id", "y", "split")


def seeds_of(known: DataFrame, streams: list[Stream], sizes: Sizes) -> tuple[DataFrame, Ids, dict[str, int]]:
    """(batch_id, node_id) of all streams: hash buckets of the splits, new in each epoch; and the number of batches by split."""
    counts = {r["split"]: max(1, -(-r["count"] // sizes.batch)) for r in known.groupBy("split").count().collect()}
    ids, e = Ids(sizes.epochs, max(counts.values(), default=1)), sizes.epochs
    every = F.array(*[F.struct(F.lit(i).alias("stream"), F.lit(s.seed).alias("seed")) for i, s in enumerate(streams)])
    turns = F.when(F.col("split") == "train", F.sequence(F.lit(0), F.lit(e - 1))).otherwise(F.array(F.when(F.col("split") == "val", e).otherwise(e + 1)))
    n = F.when(F.col("split") == "train", counts.get("train", 1)).when(F.col("split") == "val", counts.get("val", 1)).otherwise(counts.get("test", 1))
    spread = known.select("node_id", n.alias("n"), F.explode(turns).alias("epoch"), every.alias("every")).select("node_id", "n", "epoch", F.explode("every").alias("s"))
    place = F.floor(uniform(F.col("s.seed"), "batch", F.col("epoch"), F.col("node_id")) * F.col("n"))
    return spread.select(ids.of(F.col("s.stream"), F.col("epoch"), place).alias("batch_id"), "node_id"), ids, counts


def of_streams(ids: Ids, streams: list[Stream], test: Callable[[Stream], bool]) -> Column:
    """Whether a batch belongs to a stream that passes ``test``."""
    held = [i for i, s in enumerate(streams) if test(s)]
    return ids.stream(F.col("batch_id")).isin(held) if held else F.lit(False)


def sampled(g: Graph, prop: DataFrame, seeds: DataFrame, ids: Ids, streams: list[Stream], sizes: Sizes, cache: DataFrame | None, keep, seed: int = 7):
    """(edges with layer and weight, inputs) of all batches, by one plan for each of the three sampler families that occur."""
    told = lambda test: of_streams(ids, streams, test)
    edges, inputs = [], []
    if any(s.model in NODE_WISE for s in streams):
        mine = seeds.where(told(lambda s: s.model in NODE_WISE))
        raw, fronts = nodewise.node_wise_batches(mine, g.edges, [sizes.fanout] * 2, 0, seed, prefer=cache, prefers=told(lambda s: s.cached), keep=keep, impl="xxhash64")
        inputs.append(fronts[-1])
        for layer, block, front in zip((1, 0), raw, fronts):
            for model in NODE_WISE:
                if any(s.model == model for s in streams):
                    here = told(lambda s, m=model: s.model == m)
                    own = block.where(here).select("batch_id", "layer", "dst", "src")
                    edges.append(nodewise.sage_weights(own) if model == "graphsage" else nodewise.gcn_block(own, front.where(here), prop, layer))
    for base in ("fastgcn", "ladies"):
        if any(s.model.startswith(base) for s in streams):
            of = {x: layerwise.VARIANTS[x] for x in layerwise.VARIANTS}
            flat, debias = told(lambda s: s.model in of and of[s.model][1]), told(lambda s: s.model in of and of[s.model][2])
            sampler = layerwise.LayerSampler(base, flat, debias, sizes=(sizes.layer,) * 2, seed=seed, impl="xxhash64", keep=keep)
            chosen, blocks = sampler.layers(prop, seeds.where(told(lambda s, b=base: s.model.startswith(b))))
            inputs.append(chosen[-1].select("batch_id", "node_id").distinct())
            edges += blocks
    cut = [b.select("batch_id", "layer", "dst", "src", "w") for b in edges]
    return _union(cut), _union(inputs)


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def package(seeds: DataFrame, edges: DataFrame, inputs: DataFrame, features: DataFrame, labels: DataFrame) -> DataFrame:
    """One row a batch, bounded by the sampler's sizes: batch_id and the flat arrays of :meth:`kernels.Batch.of`, which Arrow hands over as numpy arrays.

    Each feature row is fetched once. Null edge arrays: no edge was sampled. A batch none of whose inputs has features, or none of whose seeds has a label, is left out.
    """
    y = seeds.join(labels, "node_id").groupBy("batch_id").agg(F.sort_array(F.collect_list(F.struct("node_id", "y"))).alias("seeds"))
    e = edges.groupBy("batch_id").agg(F.sort_array(F.collect_list(F.struct("layer", "dst", "src", "w"))).alias("blocks"))
    needed = features.join(inputs.select("node_id").distinct(), "node_id", "left_semi")
    x = inputs.join(needed, "node_id").groupBy("batch_id").agg(F.sort_array(F.collect_list(F.struct("node_id", "f"))).alias("x"))
    return y.join(x, "batch_id").join(e, "batch_id", "left").select("batch_id", *packed())


def packed() -> list[Column]:
    """Flat arrays from the columns seeds (node_id, y), blocks (layer, dst, src, w) and x (node_id, f), all arrays of structs."""
    return [F.col("seeds.node_id").alias("seeds"), F.col("seeds.y").alias("y"), *[F.col(f"blocks.{c}").alias(c) for c in ("layer", "dst", "src", "w")], F.col("x.node_id").alias("inputs"), F.flatten("x.f").alias("x")]


def unpacked(row) -> kernels.Batch:
    if getattr(row, "made", None) is not None:
        return row.made
    array = lambda v, kind: np.array([] if v is None else v, kind)
    edges = array(row.layer, np.int64), array(row.dst, np.int64), array(row.src, np.int64), array(row.w, float)
    return kernels.Batch.of(array(row.seeds, np.int64), array(row.y, np.int64), *edges, array(row.inputs, np.int64), array(row.x, float))


@dataclass
class Prepared:
    """A graph's tables that all runs share, each written once."""

    g: Graph
    prop: DataFrame
    known: DataFrame
    cache_p: DataFrame
    cache_size: int


def kept(g: Graph, keep) -> Graph:
    return replace(g, nodes=keep(g.nodes), edges=keep(g.edges.select("dst", "src")))


def prepare(g: Graph, labels: DataFrame, sizes: Sizes, keep, seed: int = 7) -> Prepared:
    """The tables of a graph whose own tables are kept."""
    known = keep(known_nodes(g, labels, seed))
    train = known.where("split = 'train'").select("node_id")
    return Prepared(g, keep(propagation(g)), known, keep(C.cache_probs(g, train)), C.cache_size(g.nodes.count(), sizes.cache_share))
