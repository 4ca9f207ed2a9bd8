"""What each batch of an epoch holds, counted from a graph's arrays (:mod:`local`): the draws of the plans by md5, made by the task that has the batch.

Neither the neighbours that a batch touches nor its pool is ever a row of a table, so nothing of them is shuffled or spilled; a batch tells eight numbers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..functions.md5 import Tails
from ..operators import cache as C
from ..operators import kernels, layerwise
from ..sources.graphs import Graph
from ..sources.spool import Spool, piece, put
from . import local
from .batches import NODE_WISE, Sizes

TOLD = ("batch_id", "touched", "e1", "e0", "r1", "r0", "inputs", "missing")


class Epoch(local.Sampler):
    """The batches of one epoch over the training nodes, whose ``y`` is the place of their batch; batches of model i have the ids from i times ``n`` on."""

    def __init__(self, a: local.Arrays, models: tuple[str, ...], n: int, sizes: Sizes, cached: np.ndarray, seed: int = 7):
        super().__init__(a, [], sizes, seed)
        self.models, self.many, self.tails = models, n, Tails(self.ids)
        self.hot, self.mark = np.zeros(a.nodes, bool), np.zeros(a.nodes, bool)
        self.hot[cached] = True
        train = self.of_split[0]
        self.train = train[np.argsort(self.y[train], kind="stable")]
        self.turn = self.y[self.train]

    def told(self, places: list[int]) -> Iterator[tuple]:
        """Rows of :data:`TOLD` of these batches, for all models. The node-wise models share the samples of the first of them."""
        node = [i for i, m in enumerate(self.models) if m in NODE_WISE]
        for place in places:
            seeds = self.train[slice(*np.searchsorted(self.turn, (place, place + 1)))]
            if not len(seeds):
                continue
            if node:
                some = self.near(node[0] * self.many + place, seeds)
                yield from ((i * self.many + place, *some) for i in node)
            top = {}
            for i, m in enumerate(self.models):
                if i not in node:
                    yield (i * self.many + place, *self.layers(m, i * self.many + place, seeds, top))

    def near(self, batch: int, seeds: np.ndarray) -> tuple:
        front, touched, sizes, edges = seeds, 0, [], []
        for layer in (1, 0):
            sizes.append(len(front))
            touched += int(self.degree[front].sum()) - len(front)  # but for the self loop
            taken = self.neighbours(batch, layer, front)
            edges.append(len(taken))
            front = np.unique(np.concatenate([front, taken]))
        return touched, *edges, *sizes, len(front), len(front) - int(self.hot[front].sum())

    def neighbours(self, batch: int, layer: int, front: np.ndarray) -> np.ndarray:
        """The neighbours that each node of the front takes: those of least hash, then least id."""
        fan, out = self.sizes.fanout, []
        cuts = np.cumsum(self.degree[front], dtype=np.int64) // local.PIECE
        for rows in np.split(front, np.flatnonzero(np.diff(cuts)) + 1):
            sizes, col = self.entries(rows)
            which = np.repeat(np.arange(len(rows)), sizes)
            other = col != rows[which]
            which, col = which[other], col[other]
            d = np.bincount(which, minlength=len(rows))
            out.append(col[d[which] <= fan])
            which, col = which[d[which] > fan], col[d[which] > fan]
            bits = self.tails.bits([f"{self.seed}:0:{batch}:{layer}:{x}:".encode() for x in self.ids[rows].tolist()], which, col)
            near = bits <= np.minimum(4.0 * fan / np.maximum(d, 1), 1.0)[which] * 4294967295.0
            near |= (np.bincount(which[near], minlength=len(rows)) < fan)[which]  # rows with too few are taken whole
            which, col, bits = which[near], col[near], bits[near]
            order = np.lexsort((col, bits, which))
            sizes = np.bincount(which, minlength=len(rows))
            out.append(col[order[np.arange(len(order)) - np.repeat(np.cumsum(sizes) - sizes, sizes) < fan]])
        return np.concatenate(out)

    def pool(self, rows: np.ndarray) -> tuple:
        """(columns of the rows' entries, LADIES' candidates, their masses)."""
        sizes, col = self.entries(rows)
        q = np.bincount(col, np.repeat(1.0 / self.degree[rows], sizes), len(self.ids))
        pool = np.flatnonzero(q)
        return col, pool, q[pool] / self.degree[pool]

    def layers(self, model: str, batch: int, seeds: np.ndarray, top: dict) -> tuple:
        """``top`` keeps what the models share: the candidates below the seeds."""
        base, flat, _ = layerwise.VARIANTS[model]
        rows, touched, sizes, edges = seeds, 0, [], []
        for layer in (1, 0):
            sizes.append(len(rows))
            touched += int(self.degree[rows].sum())
            if base == "ladies":
                if layer:
                    top[base] = top.get(base) or self.pool(rows)
                col, pool, q = top[base] if layer else self.pool(rows)
                q = np.sqrt(q) if flat else q
                chosen = self.drawn(batch, layer, pool, q / q.sum())
            else:
                col = self.entries(rows)[1]
                pool, p, least, *_ = self.bounded(int(flat), self.sizes.layer)
                chosen = self.drawn(batch, layer, pool, p, least)
            self.mark[chosen] = True
            edges.append(int(self.mark[col].sum()))
            self.mark[chosen] = False
            rows = chosen
        return touched, *edges, *sizes, len(rows), len(rows) - int(self.hot[rows].sum())

    def drawn(self, batch: int, layer: int, pool: np.ndarray, p: np.ndarray, least: np.ndarray | None = None) -> np.ndarray:
        """The nodes of a race; those with a uniform below ``least`` are left out, unless too few remain."""
        size = self.sizes.layer
        u = (self.tails.bits([f"{self.seed}:0:{batch}:{layer}:".encode()], None, pool) + 0.5) / 4294967296.0
        if least is not None:
            near = np.flatnonzero(u >= least)
            if len(near) >= size:
                pool, p, u = pool[near], p[near], u[near]
        key = -np.log(u) / p
        if len(key) > size:
            near = np.flatnonzero(key <= np.partition(key, size - 1)[size - 1])
            pool, key = pool[near], key[near]
        return pool[np.lexsort((pool, key))[:size]]


def _degrees(a: local.Arrays):
    """One task: (node_id, deg) from the arrays, without self loops."""

    def go(parts):
        for _ in parts:
            pass
        ids, degree = piece(a.folder, "ids", "<i8", a.nodes), piece(a.folder, "degree", "<i4", a.nodes)
        for i in range(0, a.nodes, local.PIECE):
            yield pa.RecordBatch.from_pydict({"node_id": np.array(ids[i : i + local.PIECE]), "deg": np.array(degree[i : i + local.PIECE], np.int64) - 1})

    return go


def _places(a: local.Arrays):
    """One task: the places of nodes to a file."""

    def go(parts):
        held = [p.column("node_id").to_numpy() for p in parts if p.num_rows]
        at = kernels.index_of(np.concatenate(held), np.array(piece(a.folder, "ids", "<i8", a.nodes))) if held else np.zeros(0)
        yield pa.RecordBatch.from_pydict({"name": [put(a.folder, at.astype("<i4"))], "k": [len(at)]})

    return go


def counts(g: Graph, train: DataFrame, n: int, models: tuple[str, ...], sizes: Sizes, cache_share: float, keep: Spool, seed: int = 7) -> DataFrame | None:
    """:data:`TOLD` of the ``n`` batches of the ``train`` nodes for all models, written once; none for graphs that do not lie in arrays. Nodes are kept already; edges are read once.

    Files go with ``keep``, which the caller closes.
    """
    spark, nodes = g.nodes.sparkSession, g.nodes.count()
    if not nodes or nodes > local.NODES or g.nodes.where("node_id is null").count():
        return None
    place = F.floor(uniform(seed, "batch", 0, F.col("node_id")) * n).cast("int")
    known = train.select("node_id", place.alias("y"), F.lit("train").alias("split"))
    none = g.nodes.limit(0).select("node_id", F.array(F.lit(0.0).cast("float")).alias("f"))
    a = local.arrays(g, known, None, none, f"{keep.folder}/arrays", local.ENTRIES)
    if not a or a.nodes != nodes:
        return None
    deg = keep(spark.range(0, 1, 1, 1).mapInArrow(_degrees(a), "node_id long, deg long"))
    cache = C.build_cache(C.mass_probs(deg.select("node_id", F.col("deg").cast("double").alias("p"))), C.cache_size(nodes, cache_share), 0, seed)
    held = cache.select("node_id").repartition(1).mapInArrow(_places(a), "name string, k long").first()

    def go(parts):
        made = None
        for pdf in parts:
            made = made or Epoch(a, models, n, sizes, np.asarray(piece(a.folder, held["name"], "<i4", held["k"])) if held else np.zeros(0, np.int64), seed)
            mine = pdf["id"].tolist()
            for i in range(0, len(mine), 256):
                yield pd.DataFrame(list(made.told(mine[i : i + 256])), columns=TOLD, dtype="int64")

    tasks = max(1, min(n, 2 * spark.sparkContext.defaultParallelism))
    return spark.range(0, n, 1, tasks).mapInPandas(go, ", ".join(f"{c} long" for c in TOLD))


__all__ = ["Epoch", "TOLD", "counts"]
