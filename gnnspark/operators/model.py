"""Two-layer networks in rows form: joins and aggregates over (node_id, pos, x) and (i, j, w).

The rows form is exact and checkable in SQL; :mod:`kernels` computes the same per batch in numpy.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform


def init_params(spark: SparkSession, dims: tuple[int, ...], seed: int = 7) -> DataFrame:
    """(layer, i, j, w): equal on every worker, as each weight is a function of its place."""
    out = None
    for layer, (a, b) in enumerate(zip(dims, dims[1:]), 1):
        cells = spark.range(a * b).select(F.floor(F.col("id") / b).cast("int").alias("i"), (F.col("id") % b).cast("int").alias("j"))
        w = (2 * uniform(seed, "w", layer, F.col("i"), F.col("j")) - 1) * F.lit((6 / (a + b)) ** 0.5)
        one = cells.select(F.lit(layer).alias("layer"), "i", "j", w.alias("w"))
        out = one if out is None else out.union(one)
    return out


def weights(params: DataFrame, layer: int) -> DataFrame:
    return params.where(F.col("layer") == layer).select("i", "j", "w")


def gather(entries: DataFrame, h: DataFrame) -> DataFrame:
    """The operator's rows times the senders' vectors: (dst, src, w), (node_id, pos, x) -> (node_id, pos, x)."""
    return entries.join(h, F.col("src") == h["node_id"]).groupBy(F.col("dst").alias("node_id"), "pos").agg(F.sum(F.col("w") * F.col("x")).alias("x"))


def apply_nn(h: DataFrame, w: DataFrame) -> DataFrame:
    """Vectors times a weight matrix; the matrix is of model size and broadcast."""
    return h.join(F.broadcast(w), F.col("pos") == F.col("i")).groupBy("node_id", F.col("j").alias("pos")).agg(F.sum(F.col("x") * F.col("w")).alias("x"))


def relu(h: DataFrame) -> DataFrame:
    return h.withColumn("x", F.greatest("x", F.lit(0.0)))


def beside(mean: DataFrame, own: DataFrame, width: int) -> DataFrame:
    """Concatenation: the own vector's positions follow those of the neighbours' mean."""
    return mean.union(own.select("node_id", (F.col("pos") + width).alias("pos"), "x"))


def gcn_forward(inner: DataFrame, outer: DataFrame, x: DataFrame, params: DataFrame) -> dict[str, DataFrame]:
    """All intermediate tables of a two-layer network; ``inner``/``outer`` are the entries (dst, src, w) of the two layers."""
    ax = gather(inner, x)
    z1 = apply_nn(ax, weights(params, 1))
    h1 = relu(z1)
    ah = gather(outer, h1)
    return {"ax": ax, "z1": z1, "h1": h1, "ah": ah, "z2": apply_nn(ah, weights(params, 2))}


def sage_layer(neighbours: DataFrame, own: DataFrame, rows: DataFrame, w: DataFrame, width: int) -> DataFrame:
    """Mean of neighbours beside the own vector, times the weights; ``rows``: (node_id)."""
    mine = own.join(rows, "node_id", "left_semi")
    return apply_nn(beside(gather(neighbours, own), mine, width), w)


def softmax(z: DataFrame) -> DataFrame:
    w = Window.partitionBy("node_id")
    shifted = z.withColumn("e", F.exp(F.col("x") - F.max("x").over(w)))
    return shifted.select("node_id", "pos", (F.col("e") / F.sum("e").over(w)).alias("p"))


def softmax_loss(z: DataFrame, labels: DataFrame, reduction: str = "sum") -> DataFrame:
    """(loss, n) over labelled nodes; probabilities are clipped."""
    hit = softmax(z).join(labels, "node_id").where("pos = y")
    one = -F.log(F.greatest("p", F.lit(1e-12)))
    return hit.agg((F.sum(one) if reduction == "sum" else F.avg(one)).alias("loss"), F.count("*").alias("n"))


def bce_loss(predictions: DataFrame, reduction: str = "sum") -> DataFrame:
    """(loss, n) of rows (y, p)."""
    p = F.least(F.greatest(F.col("p"), F.lit(1e-12)), F.lit(1 - 1e-12))
    one = -(F.col("y") * F.log(p) + (1 - F.col("y")) * F.log(1 - p))
    return predictions.agg((F.sum(one) if reduction == "sum" else F.avg(one)).alias("loss"), F.count("*").alias("n"))


def gcn_gradients(inner: DataFrame, outer: DataFrame, x: DataFrame, params: DataFrame, labels: DataFrame) -> DataFrame:
    """(layer, i, j, g): the gradient of the mean cross-entropy. Transposed products are the same joins with the ends swapped."""
    f = gcn_forward(inner, outer, x, params)
    n = labels.agg(F.count("*").alias("n")).withColumn("k", F.lit(1))
    g2 = softmax(f["z2"]).join(labels, "node_id").withColumn("k", F.lit(1)).join(F.broadcast(n), "k").select("node_id", "pos", ((F.col("p") - (F.col("pos") == F.col("y")).cast("double")) / F.col("n")).alias("x"))
    outer_product = lambda h, g: h.select("node_id", F.col("pos").alias("i"), F.col("x").alias("hx")).join(g.select("node_id", F.col("pos").alias("j"), F.col("x").alias("gx")), "node_id").groupBy("i", "j").agg(F.sum(F.col("hx") * F.col("gx")).alias("g"))
    back = apply_nn(g2, weights(params, 2).select(F.col("j").alias("i"), F.col("i").alias("j"), "w"))
    dh = gather(outer.select(F.col("src").alias("dst"), F.col("dst").alias("src"), "w"), back)
    on = f["z1"].where("x > 0").select("node_id", "pos")
    g1 = dh.join(on, ["node_id", "pos"], "left_semi")
    return outer_product(f["ax"], g1).select(F.lit(1).alias("layer"), "i", "j", "g").union(outer_product(f["ah"], g2).select(F.lit(2).alias("layer"), "i", "j", "g"))


def sgd_step(params: DataFrame, grads: DataFrame, rate: float) -> DataFrame:
    return params.join(grads, ["layer", "i", "j"], "left").select("layer", "i", "j", (F.col("w") - F.lit(rate) * F.coalesce("g", F.lit(0.0))).alias("w"))


def adam_step(params: DataFrame, grads: DataFrame, t: int = 1, rate: float = 0.001, b1: float = 0.9, b2: float = 0.999, eps: float = 1e-8) -> DataFrame:
    """One step with moments ``m`` and ``v`` (0 where absent): (layer, i, j, w, m, v)."""
    df = params if "m" in params.columns else params.withColumns({"m": F.lit(0.0), "v": F.lit(0.0)})
    g = F.coalesce("g", F.lit(0.0))
    moved = df.join(grads, ["layer", "i", "j"], "left").withColumns({"m": b1 * F.col("m") + (1 - b1) * g, "v": b2 * F.col("v") + (1 - b2) * g * g})
    step = F.lit(rate) * (F.col("m") / (1 - b1**t)) / (F.sqrt(F.col("v") / (1 - b2**t)) + eps)
    return moved.select("layer", "i", "j", (F.col("w") - step).alias("w"), "m", "v")
