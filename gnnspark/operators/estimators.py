"""How well a sampled block estimates the exact product: error, bias and variance over seeds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def products(entries: DataFrame, scalar: DataFrame, by: list[str]) -> DataFrame:
    """(by..., dst, z): sums of w times the feature ``x`` of the sender. ``scalar``: (node_id, pos, x), one row per feature dimension."""
    return entries.join(scalar, F.col("src") == scalar["node_id"]).groupBy(*by, "dst", "pos").agg(F.sum(F.col("w") * F.col("x")).alias("z"))


def estimator_error(blocks: DataFrame, exact: DataFrame, scalar: DataFrame) -> DataFrame:
    """(variant, rmse, bias): blocks are (variant, seed, dst, src, w); rows without an entry estimate 0.

    ``rmse``: root of the mean squared Frobenius error over seeds, relative to the exact product; ``bias``: that of the mean estimate.
    """
    truth = products(exact, scalar, []).withColumnRenamed("z", "truth")
    n = blocks.groupBy("variant").agg(F.count_distinct("seed").alias("seeds"))
    est = products(blocks, scalar, ["variant", "seed"])
    cell = est.groupBy("variant", "dst", "pos").agg(F.sum("z").alias("s"), F.sum(F.col("z") * F.col("z")).alias("ss")).join(truth, ["dst", "pos"]).join(n, "variant")
    mean, square = F.col("s") / F.col("seeds"), F.col("ss") / F.col("seeds")
    # beyond truth squared, which a cell without an estimate adds alone: runs and cells need no product
    more = cell.groupBy("variant").agg(F.sum(square - 2 * F.col("truth") * mean).alias("mse"), F.sum(mean * mean - 2 * F.col("truth") * mean).alias("b2"))
    whole = truth.agg(F.sum(F.col("truth") * F.col("truth")).alias("t2")).withColumn("one", F.lit(1))
    summed = more.withColumn("one", F.lit(1)).join(F.broadcast(whole), "one")
    total = summed.select("variant", "t2", *[F.greatest(F.col(c) + F.col("t2"), F.lit(0.0)).alias(c) for c in ("mse", "b2")])
    return total.select("variant", F.sqrt(F.col("mse") / F.col("t2")).alias("rmse"), F.sqrt(F.col("b2") / F.col("t2")).alias("bias"), F.sqrt(F.greatest(F.col("mse") - F.col("b2"), F.lit(0.0)) / F.col("t2")).alias("spread"))
