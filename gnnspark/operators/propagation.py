"""Degrees, self loops, the normalised propagation operator, splits and planted labels."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..sources.graphs import Graph


def degrees(g: Graph) -> DataFrame:
    """(node_id, deg_in, deg_out, deg) for every node, isolated ones included; counts combine before the shuffle."""
    ends = g.edges.select(F.col("dst").alias("node_id"), F.lit(1).alias("i"), F.lit(0).alias("o")).union(g.edges.select("src", F.lit(0), F.lit(1)))
    counts = ends.groupBy("node_id").agg(F.sum("i").alias("i"), F.sum("o").alias("o"))
    joined = g.nodes.select("node_id").join(counts, "node_id", "left")
    i, o = F.coalesce("i", F.lit(0)), F.coalesce("o", F.lit(0))
    return joined.select("node_id", i.alias("deg_in"), o.alias("deg_out"), (i + o if g.directed else i).alias("deg"))


def degree_skew(g: Graph, share: float = 0.01) -> DataFrame:
    """(nodes, top_nodes, top_share): part of all edge ends that the ``share`` of nodes of largest degree holds. Sums by degree value, so the window runs over distinct degrees only."""
    from pyspark.sql import Window

    hist = degrees(g).groupBy("deg").agg(F.count("*").alias("n"))
    above = Window.orderBy(F.col("deg").desc()).rowsBetween(Window.unboundedPreceding, -1)
    every = Window.orderBy(F.col("deg").desc()).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ranked = hist.select("deg", "n", F.coalesce(F.sum("n").over(above), F.lit(0)).alias("before"), F.sum("n").over(every).alias("nodes"), F.sum(F.col("n") * F.col("deg")).over(every).alias("ends"))
    top = F.greatest(F.lit(1), F.floor(F.col("nodes") * F.lit(share)))
    taken = F.greatest(F.lit(0), F.least(F.col("n"), top - F.col("before")))
    return ranked.groupBy("nodes", "ends").agg(F.sum(taken).alias("top_nodes"), F.sum(taken * F.col("deg")).alias("held")).select("nodes", "top_nodes", F.round(F.col("held") / F.col("ends"), 6).alias("top_share"))


def with_self_loops(g: Graph) -> DataFrame:
    """(row, col): receivers and senders with one self loop a node."""
    return g.edges.select(F.col("dst").alias("row"), F.col("src").alias("col")).unionByName(g.nodes.select(F.col("node_id").alias("row"), F.col("node_id").alias("col")))


def propagation(g: Graph, operator: str = "sym") -> DataFrame:
    """(row, col, w). ``sym``: 1/sqrt(d_row d_col) with d the row sum including the self loop; ``row``: 1/d_row; ``self_loop``: 1.

    Two joins with the degree table. On bucketed edge tables the join on ``row`` needs no shuffle; Spark broadcasts degrees where they are small.
    """
    a = with_self_loops(g)
    if operator == "self_loop":
        return a.withColumn("w", F.lit(1.0))
    d = a.groupBy("row").agg(F.count("*").alias("d"))
    by_row = a.join(d.withColumnRenamed("d", "d_row"), "row")
    if operator == "row":
        return by_row.select("row", "col", (F.lit(1.0) / F.col("d_row")).alias("w"))
    both = by_row.join(d.select(F.col("row").alias("col"), F.col("d").alias("d_col")), "col")
    return both.select("row", "col", (F.lit(1.0) / F.sqrt(F.col("d_row").cast("double") * F.col("d_col"))).alias("w"))


SPLITS = {"cust_supp": (65, 16), "emb_knn": (54, 18), "part_pair": (66, 10), "cust_part": (8, 2)}


def split_of(node: Column, name: str, seed: int = 7) -> Column:
    """train, val or test by a hash bucket of the node; shares per graph, 54/18/28 by default."""
    train, val = SPLITS.get(name, (54, 18))
    bucket = F.floor(100 * uniform(seed, "split", node))
    return F.when(bucket < train, "train").when(bucket < train + val, "val").otherwise("test")


def assign_split(g: Graph, seed: int = 7) -> DataFrame:
    return g.nodes.select("node_id", split_of(F.col("node_id"), g.name, seed).alias("split"))


def summary(g: Graph, d: int, classes: int, seed: int = 7) -> DataFrame:
    """One row: name, sizes, both degree conventions, width, classes and split counts."""
    shares = assign_split(g, seed).groupBy().pivot("split", ["train", "val", "test"]).count()
    n, e = g.nodes.agg(F.count("*").alias("v")), g.counted().agg(F.count("*").alias("e"))
    one = n.withColumn("k", F.lit(1)).join(e.withColumn("k", F.lit(1)), "k").join(shares.withColumn("k", F.lit(1)), "k")
    nz = lambda c: F.coalesce(c, F.lit(0)).cast("long")
    return one.select(F.lit(g.name).alias("graph"), F.col("v"), F.col("e"), F.round(2 * F.col("e") / F.col("v"), 6).alias("avg_degree_und"), F.round(F.col("e") / F.col("v"), 6).alias("edges_per_node"), F.lit(d).alias("width"), F.lit(classes).alias("classes"), nz("train").alias("n_train"), nz("val").alias("n_val"), nz("test").alias("n_test"))


def planted_label(g: Graph, scalar: DataFrame) -> DataFrame:
    """(node_id, y): whether the mean of one feature over the neighbours lies above the median of those means; null for isolated nodes."""
    mean = g.edges.join(scalar, F.col("src") == scalar["node_id"]).groupBy("dst").agg(F.round(F.avg("x"), 9).alias("m"))
    median = mean.agg(F.percentile("m", F.lit(0.5)).alias("mid"))
    named = mean.withColumn("k", F.lit(1)).join(F.broadcast(median.withColumn("k", F.lit(1))), "k")
    return g.nodes.select("node_id").join(named, F.col("node_id") == F.col("dst"), "left").select("node_id", (F.col("m") > F.col("mid")).cast("int").alias("y"))


def smoothed_label(g: Graph, prop: DataFrame | None, scalar: DataFrame, hops: int = 2) -> DataFrame:
    """(node_id, y): whether a feature, propagated over ``hops`` layers without sampling, lies above its median: what a network of as many layers can learn.

    A missing feature counts as zero; every node has a label, as propagation holds self loops. Without ``prop`` the symmetric operator is applied by degrees, and no entry of it is made.
    """
    x = scalar.select("node_id", "x")
    if prop is None:
        a = with_self_loops(g)
        d = a.groupBy(F.col("row").alias("node_id")).agg(F.sqrt(F.count("*").cast("double")).alias("r"))
    for _ in range(hops if prop is None else 0):
        scaled = x.join(d, "node_id").select(F.col("node_id").alias("col"), (F.col("x") / F.col("r")).alias("x"))
        x = a.join(scaled, "col").groupBy(F.col("row").alias("node_id")).agg(F.sum("x").alias("x")).join(d, "node_id").select("node_id", (F.col("x") / F.col("r")).alias("x"))
    for _ in range(0 if prop is None else hops):
        x = prop.join(x, F.col("col") == F.col("node_id")).groupBy(F.col("row").alias("node_id")).agg(F.sum(F.col("w") * F.col("x")).alias("x"))
    x = g.nodes.select("node_id").join(x, "node_id", "left").select("node_id", F.round(F.coalesce("x", F.lit(0.0)), 9).alias("x"), F.lit(1).alias("k"))
    median = x.agg(F.percentile("x", F.lit(0.5)).alias("mid")).withColumn("k", F.lit(1))
    return x.join(F.broadcast(median), "k").select("node_id", (F.col("x") > F.col("mid")).cast("int").alias("y"))
