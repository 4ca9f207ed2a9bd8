"""Seeds and mini-batches."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform


def make_batches(train: DataFrame, batch_size: int, epoch: int = 0, workers: int = 1, seed: int = 7, exact: bool = False) -> DataFrame:
    """(epoch, batch_id, worker, node_id).

    By default a batch is a hash bucket: one count, no sort, sizes vary around ``batch_size``. ``exact`` ranks nodes by hash in one global order,
    which gives equal batches and suits small training sets.
    """
    u = uniform(seed, "batch", epoch, F.col("node_id"))
    if exact:
        batch = F.floor((F.row_number().over(Window.orderBy(u, "node_id")) - 1) / batch_size)
    else:
        batch = F.floor(u * F.lit(max(1, -(-train.count() // batch_size))))
    placed = train.select("node_id", batch.cast("long").alias("batch_id"))
    return placed.select(F.lit(epoch).alias("epoch"), "batch_id", (F.col("batch_id") % workers).cast("int").alias("worker"), "node_id")


def hashed_seeds(nodes: DataFrame, batches: int, size: int, seed: int = 7) -> DataFrame:
    """(batch_id, node_id): for each batch the ``size`` nodes of least hash; a bounded workload for experiments."""
    ids = nodes.select("node_id", F.explode(F.sequence(F.lit(0), F.lit(batches - 1))).alias("batch_id"))
    order = Window.partitionBy("batch_id").orderBy(uniform(seed, "seed", F.col("batch_id"), F.col("node_id")), "node_id")
    return ids.withColumn("r", F.row_number().over(order)).where(F.col("r") <= size).select(F.col("batch_id").cast("long").alias("batch_id"), "node_id")
