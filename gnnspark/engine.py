"""One object for users: graphs, samplers, caches, training and SQL views over a folder of tables."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .operators import cache as C
from .operators import nodewise
from .operators.batching import make_batches
from .operators.layerwise import VARIANTS, LayerSampler
from .operators.propagation import propagation, split_of
from .plans.train import RunResult, train
from .sources.graphs import NAMES, Graph, load_graph
from .sources.spool import spool

NODE_WISE = ("gcn", "graphsage")


@dataclass(frozen=True)
class Sample:
    """Blocks (batch_id, layer, dst, src, w) from the seeds' layer down, and inputs (batch_id, node_id)."""

    blocks: DataFrame
    inputs: DataFrame


@dataclass(frozen=True)
class OpenGraph:
    """A graph whose nodes, edges and propagation operator are written once."""

    g: Graph
    prop: DataFrame

    def split(self, part: str = "train", seed: int = 7) -> DataFrame:
        return self.g.nodes.where(split_of(F.col("node_id"), self.g.name, seed) == part).select("node_id")

    def batches(self, size: int = 64, epoch: int = 0, workers: int = 1, seed: int = 7) -> DataFrame:
        """(epoch, batch_id, worker, node_id) over the training split."""
        return make_batches(self.split(seed=seed), size, epoch, workers, seed)

    def cache(self, share: float = 0.01, mode: str = "auto", epoch: int = 0, seed: int = 7) -> DataFrame:
        """(epoch, node_id, p, ord): the cached nodes of an epoch."""
        return C.build_cache(C.cache_probs(self.g, self.split(seed=seed), mode), C.cache_size(self.g.nodes.count(), share), epoch, seed)

    def sample(self, model: str, batches: DataFrame, fanout: int = 5, layers: int = 2, size: int = 512, epoch: int = 0, seed: int = 7, cache: DataFrame | None = None) -> Sample:
        """Blocks of all ``batches`` in one plan. ``model``: gcn, graphsage, or one of the eight layer-wise variants; a cache is preferred by the first two."""
        seeds = batches.select("batch_id", "node_id")
        if model in VARIANTS:
            chosen, blocks = LayerSampler.named(model, sizes=(size,) * layers, epoch=epoch, seed=seed, impl="xxhash64").layers(self.prop, seeds)
            return Sample(_all(blocks), chosen[-1].select("batch_id", "node_id"))
        if model not in NODE_WISE:
            raise ValueError(f"unknown model {model}; known are {(*NODE_WISE, *VARIANTS)}")
        raw, fronts = nodewise.node_wise_batches(seeds, self.g.edges, [fanout] * layers, epoch, seed, prefer=cache, impl="xxhash64")
        cut = [b.select("batch_id", "layer", "dst", "src") for b in raw]
        weighted = [nodewise.sage_weights(b) if model == "graphsage" else nodewise.gcn_block(b, f, self.prop, layers - 1 - i) for i, (b, f) in enumerate(zip(cut, fronts))]
        return Sample(_all(weighted), fronts[-1])

    def gather(self, inputs: DataFrame, features: DataFrame, cache: DataFrame) -> DataFrame:
        """(batch_id, node_id, hit, f): features of the inputs, each missing node fetched once a window."""
        return C.gather_inputs(inputs, cache, features)

    def train(self, features: DataFrame, labels: DataFrame, dims: tuple[int, int, int], model: str = "gcn", **how) -> RunResult:
        """Train one model over the cluster; see :func:`plans.train.train` for ``how``."""
        return train(self.g, features, labels, dims, model, **how)

    def views(self, batches: DataFrame | None = None, prefix: str = "gs") -> "OpenGraph":
        """Register ``gs_nodes``, ``gs_edges``, ``gs_prop`` and, if given, ``gs_batches`` for SQL."""
        tables = {"nodes": self.g.nodes, "edges": self.g.edges, "prop": self.prop} | ({"batches": batches} if batches is not None else {})
        for name, df in tables.items():
            df.createOrReplaceTempView(f"{prefix}_{name}")
        return self


@dataclass(frozen=True)
class Engine:
    """``Engine(spark, folder).graph("cust_part").sample("ladies_fd", batches)``; ``folder`` holds the given tables as Parquet."""

    spark: SparkSession
    folder: str

    @property
    def names(self) -> tuple[str, ...]:
        return NAMES

    def graph(self, name: str, operator: str = "sym") -> OpenGraph:
        if name not in NAMES:
            raise ValueError(f"unknown graph {name}; known are {NAMES}")
        return self.of(load_graph(self.spark, self.folder, name), operator)

    def of(self, g: Graph, operator: str = "sym") -> OpenGraph:
        """Open a graph of the user's own."""
        held = Graph(**{**g.__dict__, "nodes": spool(g.nodes), "edges": spool(g.edges)})
        return OpenGraph(held, spool(propagation(held, operator)))


def _all(parts: list[DataFrame]) -> DataFrame:
    out = parts[0].select("batch_id", "layer", "dst", "src", "w")
    for p in parts[1:]:
        out = out.unionByName(p.select("batch_id", "layer", "dst", "src", "w"))
    return out
