"""Errors of one layer's estimates for all rows of a graph, from its arrays (:mod:`local`): the draws of the plans, one hash for each pair of batch and node.

Batches of a lot have the same rows in every run, so a task keeps the estimates of a lot and tells their sums only. All variants race by the same uniforms.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.md5 import pair_bits
from ..operators import layerwise
from ..sources.graphs import Graph
from ..sources.spool import Spool
from . import local
from .batches import Sizes

#: Hashes (4 bytes each) that a task holds at once, if one lot has no more.
HELD = 16_000_000


def _uniforms(bits: np.ndarray) -> np.ndarray:
    return (bits + 0.5) / 4294967296.0


class Lots(local.Sampler):
    """Lots of rows, and the columns that each variant draws for them. ``x`` is the scalar feature, zero where there is none."""

    def __init__(self, a: local.Arrays, lots: int, size: int, runs: int, seed: int = 7):
        super().__init__(a, [], Sizes(layer=size), seed)
        self.lots, self.size, self.runs = lots, size, runs
        self.tails = [str(v).encode() for v in self.ids.tolist()]
        self.x = np.where(self.place >= 0, self.features[self.place].astype(float).sum(1), 0.0) if len(self.features) else np.zeros(a.nodes)
        bits = np.zeros(a.nodes, np.uint32)
        for _, j, b in pair_bits([f"{seed}:batch:0:".encode()], self.tails):
            bits[j] = b[0]
        self.lot = np.floor(_uniforms(bits) * lots).astype(np.int64)

    def hashes(self, some: list[int]) -> np.ndarray:
        """(lots, runs, nodes): the bits of all races of these lots."""
        out = np.empty((len(some) * self.runs, len(self.ids)), np.uint32)
        for i, j, b in pair_bits([f"{self.seed}:0:{r * self.lots + lot}:0:".encode() for lot in some for r in range(self.runs)], self.tails):
            out[np.ix_(i, j)] = b
        return out.reshape(len(some), self.runs, -1)

    def drawn(self, base: str, flat: bool, bits: np.ndarray, pool: np.ndarray, q: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
        """(nodes in draw order, p, support) of one race; ``pool`` and ``q`` are LADIES' candidates and their masses."""
        if base == "fastgcn":
            pool, p, least, *_ = self.bounded(int(flat), self.size)
            n = len(pool)
            u = _uniforms(bits if n == len(bits) else bits[pool])
            near = np.flatnonzero(u >= least) if least is not None else np.arange(n)
            if len(near) >= self.size:
                pool, p, u = pool[near], p[near], u[near]
        else:
            q = np.sqrt(q) if flat else q
            p, n, u = q / q.sum(), len(pool), _uniforms(bits[pool])
        key = -np.log(u) / p
        if len(key) > 4 * self.size:
            near = np.flatnonzero(key <= np.partition(key, self.size - 1)[self.size - 1])
            pool, p, key = pool[near], p[near], key[near]
        order = np.lexsort((pool, key))[: self.size]
        return pool[order], p[order], n

    def errors(self, lot: int, hashes: np.ndarray) -> list[tuple]:
        """(variant, sum of the mean squared errors, sum of the squared mean errors, sum of the squared products) over the rows of a lot."""
        rows = np.flatnonzero(self.lot == lot)
        if not len(rows):
            return []
        sizes, col = self.entries(rows)
        starts = np.cumsum(sizes) - sizes  # every row has its self loop
        q = np.bincount(col, np.repeat(1.0 / self.degree[rows], sizes), len(self.ids))
        pool = np.flatnonzero(q)
        q = q[pool] / self.degree[pool]
        applied = lambda v: np.add.reduceat(v[col], starts) * self.root[rows]
        truth, value, out = applied(self.root * self.x), np.zeros(len(self.ids)), []
        sums = {v: np.zeros((2, len(rows))) for v in layerwise.VARIANTS}
        for bits in hashes:
            for base in ("fastgcn", "ladies"):
                for flat in (False, True):
                    chosen, p, n = self.drawn(base, flat, bits, pool, q)
                    for v, own in layerwise.VARIANTS.items():
                        if own[:2] == (base, flat):
                            coef = local.debiased(p, n) if own[2] else 1.0 / (len(p) * p)
                            value[chosen] = self.root[chosen] * coef * self.x[chosen]
                            e = applied(value) - truth
                            value[chosen] = 0.0
                            sums[v] += (e, e * e)
        for v, (e, ee) in sums.items():
            out.append((v, float(ee.sum() / self.runs), float(((e / self.runs) ** 2).sum()), float((truth * truth).sum())))
        return out


def lot_errors(g: Graph, scalar: DataFrame, lots: int, size: int, runs: int, keep: Spool) -> DataFrame | None:
    """(variant, rmse, bias) of all variants, with ``size`` draws a batch, for the rows of a kept graph in ``lots`` hash buckets; none for graphs that do not lie in arrays.

    ``scalar``: (node_id, pos, x) with one row a node at most. The value goes as two floats, so nothing of a double is lost.
    """
    spark, high = g.nodes.sparkSession, F.col("x").cast("float")
    if not local.fits(g, 2):
        return None
    none = g.nodes.limit(0).select("node_id", F.lit(0).alias("y"), F.lit("train").alias("split"))
    feats = scalar.where("x is not null").select("node_id", F.array(high, (F.col("x") - high.cast("double")).cast("float")).alias("f"))
    a = local.arrays(g, none, None, feats, f"{keep.folder}/arrays")
    if not a or not a.nodes:
        return None

    def go(parts):
        held, step = None, max(1, HELD // (runs * a.nodes))
        for pdf in parts:
            mine = pdf["id"].tolist()
            held = held or Lots(a, lots, size, runs)
            for i in range(0, len(mine), step):
                some = mine[i : i + step]
                for lot, h in zip(some, held.hashes(some)):
                    yield pd.DataFrame(held.errors(lot, h), columns=["variant", "mse", "b2", "t2"])

    tasks = max(1, min(lots, 4 * spark.sparkContext.defaultParallelism, 1 + lots * runs * a.nodes // 10_000_000))
    told = spark.range(0, lots, 1, tasks).mapInPandas(go, "variant string, mse double, b2 double, t2 double")
    total = told.groupBy("variant").agg(*[F.sum(c).alias(c) for c in ("mse", "b2", "t2")])
    return keep(total.select("variant", F.sqrt(F.col("mse") / F.col("t2")).alias("rmse"), F.sqrt(F.col("b2") / F.col("t2")).alias("bias")))
