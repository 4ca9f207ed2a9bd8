"""Weighted draws: by race without replacement, by prefix sums with replacement; and the weights that make them estimators."""

from __future__ import annotations

import math
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import race_key, uniform
from ..functions.md5 import pair_bits
from .prefix import running


def race(pool: DataFrame, size: int, layer: int, epoch: int = 0, seed: int = 7, impl: str = "md5", *more: str) -> DataFrame:
    """(batch_id, layer, node_id, p, ord): ``size`` nodes of each batch's pool (batch_id, node_id, p), in draw order; with the pool's columns ``more``.

    The order of the race is that of sequential draws without replacement. The rank limit runs before the shuffle, too.
    """
    key = race_key(uniform(seed, epoch, F.col("batch_id"), layer, F.col("node_id"), impl=impl), F.col("p"))
    order = Window.partitionBy("batch_id").orderBy(key, "node_id")
    ranked = pool.where("p > 0").select("batch_id", F.lit(layer).alias("layer"), "node_id", "p", F.row_number().over(order).alias("ord"), *more)
    return ranked.where(F.col("ord") <= size)


def race_bound(probs: DataFrame, size: int) -> tuple[int, float | None]:
    """The number of nodes with p > 0, and a bound that ``size`` race keys of a batch all but surely lie below; none if hardly any node lies above it.

    A node's key is below t with probability 1 - exp(-p t), so one aggregate gives the mean number of keys below each t of a ladder; the mean asked for is eight deviations above ``size``.
    """
    ladder = [size * 1.1**k for k in range(1, 73)]
    held = probs.where("p > 0").agg(F.count("*"), *[F.sum(1 - F.exp(-F.col("p") * t)) for t in ladder]).first()
    most = size + 8 * math.sqrt(size) + 16
    return held[0], next((t for t, mean in zip(ladder, held[1:]) if (mean or 0) >= most), None)


def _above(batches: list[int], before: str, after: str) -> Callable:
    """Nodes (node_id, p, least) to the pairs (batch_id, node_id, p) whose 32 bits are ``least`` or more: a superset of those below the bound, rounding included."""
    ids, heads = np.array(batches, np.int64), [f"{before}{b}{after}".encode() for b in batches]

    def told(found):
        return pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in zip(*found)], ["batch_id", "node_id", "p"])

    def go(parts):
        for part in parts:
            node, p, least = (part.column(c).to_numpy() for c in ("node_id", "p", "least"))
            found, n = [], 0
            for hs, ts, bits in pair_bits(heads, [str(x).encode() for x in node.tolist()]):
                h, t = np.nonzero(bits >= least[ts])
                found.append((ids[hs[h]], node[ts[t]], p[ts[t]]))
                n += len(h)
                if n >= 50_000:
                    yield told(found)
                    found, n = [], 0
            if found:
                yield told(found)

    return go


def race_all(probs: DataFrame, batches: DataFrame, size: int, layer: int, keep: Callable[[DataFrame], DataFrame], bound: tuple[int, float | None], epoch: int = 0, seed: int = 7, impl: str = "md5") -> DataFrame:
    """The :func:`race` of one measure (node_id, p) in each of ``batches``, ranking only keys below ``bound`` (:func:`race_bound`).

    Nodes are dealt to tasks by the number of pairs. A batch that has too few keys below the bound is raced again without one, so the draw is that of :func:`race`.
    """
    n, most = bound
    left, done = batches.select("batch_id").distinct(), []
    while True:
        parts = max(1, min(2000, -(-n * left.count() // 1_000_000)))
        nodes = probs.where("p > 0").select("node_id", "p").repartition(parts, "node_id")
        pairs = nodes.crossJoin(F.broadcast(left)).select("batch_id", "node_id", "p")
        if most is None:
            done.append(keep(race(pairs, size, layer, epoch, seed, impl)))
            break
        key = race_key(uniform(seed, epoch, F.col("batch_id"), layer, F.col("node_id"), impl=impl), F.col("p"))
        if impl == "md5":  # most pairs go by their hash alone, made in numpy
            least = F.greatest(F.floor(F.exp(-F.col("p") * most) * 4294967296.0) - 2, F.lit(0)).cast("long")
            pairs = nodes.withColumn("least", least).mapInArrow(_above([r[0] for r in left.collect()], f"{seed}:{epoch}:", f":{layer}:"), "batch_id long, node_id long, p double")
        ranked = keep(race(pairs.where(key <= most), size, layer, epoch, seed, impl))
        full = ranked.groupBy("batch_id").agg(F.count("*").alias("n")).where(F.col("n") >= min(size, n)).select("batch_id")
        short = left.join(full, "batch_id", "left_anti")
        if short.isEmpty():
            done.append(ranked)
            break
        done.append(ranked.join(full, "batch_id", "left_semi"))
        left, most = keep(short), None
    out = done[0]
    for more in done[1:]:
        out = out.union(more)
    return out


def prefix_sums(probs: DataFrame, cells: int = 64) -> DataFrame:
    """(node_id, p, low, high): cumulative p in node order, in two levels (:mod:`prefix`) whose cells hold alike many nodes whatever their ids."""
    return running(probs.select("node_id", "p"), ["node_id"], F.col("p"), cells).select("node_id", "p", F.col("before").alias("low"), (F.col("before") + F.col("p")).alias("high"))


def iid(probs: DataFrame, batches: DataFrame, size: int, layer: int, epoch: int = 0, seed: int = 7, slots: int = 1024) -> DataFrame:
    """(batch_id, layer, t, node_id, p): ``size`` independent draws a batch from one measure.

    Draws and cumulative ranges meet in slots of the unit interval: an equi-join with a range filter, not a nested loop.
    """
    sums = prefix_sums(probs)
    slot = lambda x: F.floor(x * slots).cast("int")
    spread = sums.where("p > 0").withColumn("slot", F.explode(F.sequence(slot(F.col("low")), F.least(slot(F.col("high")), F.lit(slots)))))
    draws = batches.select("batch_id").distinct().select("batch_id", F.explode(F.sequence(F.lit(0), F.lit(size - 1))).alias("t"))
    drawn = draws.withColumn("u", uniform(seed, epoch, F.col("batch_id"), layer, F.col("t"))).withColumn("slot", slot(F.col("u")))
    return drawn.join(spread, "slot").where("low <= u and u < high").select("batch_id", F.lit(layer).alias("layer"), "t", "node_id", "p")


def arrivals(probs: DataFrame, batches: DataFrame, size: int, layer: int, epoch: int = 0, seed: int = 7, factor: int = 4, keep: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(batch_id, layer, node_id, p, ord): ``size`` nodes a batch without replacement, from one measure for all batches.

    The order of first arrivals among independent draws is that of sequential weighted draws without replacement, so ``factor`` x ``size`` draws a batch do the work
    of a race over batches x nodes. Batches that met too few nodes draw on, with twice as many draws each time; the first draws stay the same.
    """
    want = min(size, probs.where("p > 0").limit(size).count())
    left, out = batches.select("batch_id").distinct(), None
    while want:
        drawn = iid(probs, left, factor * size, layer, epoch, seed).groupBy("batch_id", "layer", "node_id", "p").agg(F.min("t").alias("t"))
        ranked = drawn.withColumn("ord", F.row_number().over(Window.partitionBy("batch_id").orderBy("t"))).where(F.col("ord") <= size).drop("t")
        ranked = keep(ranked) if keep else ranked
        full = ranked.groupBy("batch_id").agg(F.count("*").alias("n")).where(F.col("n") >= want)
        done = ranked.join(full.select("batch_id"), "batch_id", "left_semi")
        out = done if out is None else out.union(done)
        left = left.join(full, "batch_id", "left_anti")
        if left.isEmpty():
            return out
        factor *= 2
    return batches.sparkSession.createDataFrame([], "batch_id long, layer int, node_id long, p double, ord int")


def drawn_counts(draws: DataFrame) -> DataFrame:
    """(batch_id, layer, node_id, p, times) of independent draws."""
    return draws.groupBy("batch_id", "layer", "node_id").agg(F.first("p").alias("p"), F.count("*").alias("times"))


def importance_weights(drawn: DataFrame) -> DataFrame:
    """Adds ``coef`` = times/(s p), with ``times`` 1 for draws without replacement; s is the number of draws in the batch and layer."""
    times = F.col("times") if "times" in drawn.columns else F.lit(1)
    s = F.sum(times).over(Window.partitionBy("batch_id", "layer"))
    return drawn.withColumn("coef", times / (s * F.col("p")))


def debias_weights(drawn: DataFrame, support: DataFrame | Column) -> DataFrame:
    """Adds ``coef`` for ordered draws without replacement, unbiased for the sum over the support.

    The recursion over draws is telescoped: one running sum of p gives each draw its renormalised probability q, and the weight is
    a fixed combination of 1/q and a constant. ``support``: the number of nodes with p > 0, as a column or a table (batch_id, n).
    """
    rows = drawn.join(support, "batch_id") if isinstance(support, DataFrame) else drawn.withColumn("n", support)
    group = Window.partitionBy("batch_id", "layer")
    before = F.coalesce(F.sum("p").over(group.orderBy("ord").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    rows = rows.withColumn("s", F.count("*").over(group)).withColumn("q", F.col("p") / F.greatest(1 - before, F.lit(1e-12)))
    n, s, j = F.col("n").cast("double"), F.col("s").cast("double"), F.col("ord").cast("double")
    partial = n * (n - s) / (s * (n - j) * (n - j + 1)) / F.col("q") + n * (s - j) / (s * (n - j))
    return rows.withColumn("coef", F.when(s < n, partial).otherwise(F.lit(1.0))).drop("n", "s", "q")
