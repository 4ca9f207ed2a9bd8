"""The global node cache: probabilities, draw, cache-first sampling, gathering of missing features, reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import race_key, uniform
from ..sources.graphs import Graph


def in_degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy(F.col("dst").alias("node_id")).agg(F.count("*").alias("deg"))


def mass_probs(mass: DataFrame) -> DataFrame:
    """(node_id, p): masses over their total."""
    total = mass.agg(F.sum("p")).scalar()
    return mass.select("node_id", (F.col("p") / total).alias("p"))


def cache_probs_degree(g: Graph) -> DataFrame:
    """(node_id, p): in-degree over the sum of in-degrees; nodes that receive nothing have 0."""
    d = g.nodes.select("node_id").join(in_degrees(g.edges), "node_id", "left").select("node_id", F.coalesce("deg", F.lit(0)).cast("double").alias("p"))
    return mass_probs(d)


def walk_mass(g: Graph, train: DataFrame, fanout: int, steps: int, orientation: str = "printed") -> DataFrame:
    """(node_id, p), not normalised: short walks from the training set, ``steps`` joins in one plan.

    A node's ratio is min(fanout, in-degree)/in-degree. ``printed`` scales what a node receives by its own ratio;
    ``expander`` lets a node pass its mass to the neighbours that it would sample, at its own ratio.
    """
    ratio = in_degrees(g.edges).select("node_id", (F.least(F.lit(fanout), F.col("deg")) / F.col("deg")).alias("r"))
    n = train.agg(F.count("*").alias("n")).withColumn("k", F.lit(1))
    p = train.select("node_id").withColumn("k", F.lit(1)).join(F.broadcast(n), "k").select("node_id", (F.lit(1.0) / F.col("n")).alias("p"))
    for _ in range(steps):
        if orientation == "printed":
            got = g.edges.join(p, F.col("src") == p["node_id"]).groupBy(F.col("dst").alias("node_id")).agg(F.sum("p").alias("p"))
            moved = got.join(ratio, "node_id").select("node_id", (F.col("p") * F.col("r")).alias("p"))
        else:
            gives = p.join(ratio, "node_id").select(F.col("node_id").alias("dst"), (F.col("p") * F.col("r")).alias("p"))
            moved = g.edges.join(gives, "dst").groupBy(F.col("src").alias("node_id")).agg(F.sum("p").alias("p"))
        p = p.union(moved).groupBy("node_id").agg(F.sum("p").alias("p"))
    return g.nodes.select("node_id").join(p, "node_id", "left").select("node_id", F.coalesce("p", F.lit(0.0)).alias("p"))


def cache_probs_walk(g: Graph, train: DataFrame, fanout: int = 5, steps: int = 2, orientation: str = "printed") -> DataFrame:
    return mass_probs(walk_mass(g, train, fanout, steps, orientation))


def cache_probs(g: Graph, train: DataFrame, mode: str = "auto", **walk) -> DataFrame:
    """By degree if most nodes are training nodes, else by walks; or as told: uniform, degree, walk."""
    if mode == "auto":
        mode = "degree" if 2 * train.count() > g.nodes.count() else "walk"
    if mode == "uniform":
        return mass_probs(g.nodes.select("node_id", F.lit(1.0).alias("p")))
    return cache_probs_degree(g) if mode == "degree" else cache_probs_walk(g, train, **walk)


def cache_size(n: int, share: float) -> int:
    return max(1, int(share * n + 1e-9))


def build_cache(probs: DataFrame, size: int, epoch: int = 0, seed: int = 7, impl: str = "md5") -> DataFrame:
    """(epoch, node_id, p, ord): a weighted draw without replacement, new for each epoch.

    Race keys are counted by cells of their logarithm; whole cells are in or out, and ``ord`` is a cell's offset plus the place inside it, so no task sorts all nodes or all cached ones.
    """
    key = race_key(uniform(seed, "cache", epoch, F.col("node_id"), impl=impl), F.col("p"))
    keyed = probs.where("p > 0").select("node_id", "p", key.alias("key")).withColumn("cell", F.floor(F.log("key") * 256).cast("int"))
    above = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    cells = keyed.groupBy("cell").agg(F.count("*").alias("n")).select("cell", F.coalesce(F.sum("n").over(above), F.lit(0)).alias("before")).where(F.col("before") < size)
    inside = F.row_number().over(Window.partitionBy("cell").orderBy("key", "node_id"))
    ranked = keyed.join(F.broadcast(cells), "cell").withColumn("ord", (F.col("before") + inside).cast("int"))
    return ranked.where(F.col("ord") <= size).select(F.lit(epoch).alias("epoch"), "node_id", "p", "ord")


def split_inputs(inputs: DataFrame, cache: DataFrame) -> DataFrame:
    """(batch_id, node_id, hit)."""
    held = cache.select("node_id", F.lit(1).alias("c"))
    return inputs.join(held, "node_id", "left").select("batch_id", "node_id", F.coalesce("c", F.lit(0)).alias("hit"))


def gather_inputs(inputs: DataFrame, cache: DataFrame, features: DataFrame, bulk: bool = True) -> DataFrame:
    """(batch_id, node_id, hit, f): features of all inputs; what the cache holds is read from the cached rows.

    ``bulk`` fetches each missing node of the window once, however many of its batches need it.
    """
    split = split_inputs(inputs, cache)
    hot = features.join(cache.select("node_id"), "node_id", "left_semi")
    hits = split.where("hit = 1").join(hot, "node_id")
    missing = split.where("hit = 0")
    if bulk:
        fetched = features.join(missing.select("node_id").distinct(), "node_id", "left_semi")
        return hits.unionByName(missing.join(fetched, "node_id"))
    return hits.unionByName(missing.join(features, "node_id"))


def transfer_bytes(inputs: DataFrame, cache: DataFrame, d: int) -> DataFrame:
    """(batch_id, inputs, missing, bytes): four bytes for each value of a missing feature row."""
    split = split_inputs(inputs, cache)
    miss = F.sum(1 - F.col("hit"))
    return split.groupBy("batch_id").agg(F.count("*").alias("inputs"), miss.alias("missing"), (miss * d * 4).alias("bytes"))


def coverage(g: Graph, cache: DataFrame) -> DataFrame:
    """(nodes, covered, share): nodes with a cached neighbour, of those with any."""
    held = cache.select(F.col("node_id").alias("src"), F.lit(1).alias("c"))
    per = g.edges.join(held, "src", "left").groupBy("dst").agg(F.max(F.coalesce("c", F.lit(0))).alias("c"))
    return per.agg(F.count("*").alias("nodes"), F.sum("c").alias("covered"), F.round(F.avg("c"), 6).alias("share"))


def hit_rate(inputs: DataFrame, cache: DataFrame) -> DataFrame:
    """(inputs, hits, rate)."""
    return split_inputs(inputs, cache).agg(F.count("*").alias("inputs"), F.sum("hit").alias("hits"), F.round(F.avg("hit"), 6).alias("rate"))


def batch_overlap(inputs: DataFrame) -> DataFrame:
    """(sum_inputs, distinct_inputs, overlap): how often a node of the window is needed on average."""
    per = inputs.groupBy("node_id").agg(F.count("*").alias("n"))
    return per.agg(F.sum("n").alias("sum_inputs"), F.count("*").alias("distinct_inputs"), F.round(F.sum("n") / F.count("*"), 6).alias("overlap"))
