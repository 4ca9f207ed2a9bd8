"""Gradient exchange between logical workers on a logical clock: arrivals, running means, updates, staleness, resync.

Iteration t of a worker ends at time t. Its gradient reaches worker j after a delay that is a function of (seed, t, sender, receiver), 0
for itself. Everything here is windows and aggregates over event tables, so a run is reproducible row by row.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import uniform


def delay_table(spark: SparkSession, workers: int, iterations: int, seed: int = 7, most: int = 3, straggler: int = 2) -> DataFrame:
    """(iter, sender, receiver, delay): 0 to ``most`` - 1 iterations, and ``straggler`` more from the last worker."""
    n = workers
    ids = spark.range(iterations * n * n)
    rows = ids.select((F.floor(F.col("id") / (n * n)) + 1).cast("int").alias("iter"), (F.floor(F.col("id") / n) % n).cast("int").alias("sender"), (F.col("id") % n).cast("int").alias("receiver"))
    drawn = F.floor(most * uniform(seed, "delay", F.col("iter"), F.col("sender"), F.col("receiver"))).cast("int")
    return rows.withColumn("delay", F.when(F.col("sender") == F.col("receiver"), 0).otherwise(drawn + F.when(F.col("sender") == n - 1, straggler).otherwise(0)))


def delay_of(t: int, sender: int, receiver: int, workers: int, seed: int = 7, most: int = 3, straggler: int = 2) -> int:
    """One entry of :func:`delay_table`, for code outside of a plan."""
    if sender == receiver:
        return 0
    u = (int(hashlib.md5(f"{seed}:delay:{t}:{sender}:{receiver}".encode()).hexdigest()[:8], 16) + 0.5) / 4294967296
    return int(most * u) + (straggler if sender == workers - 1 else 0)


def arrivals(delays: DataFrame) -> DataFrame:
    return delays.withColumn("arrive", F.col("iter") + F.col("delay"))


def accumulate(arrived: DataFrame) -> DataFrame:
    """Adds ``running`` and ``n`` to rows (iter, sender, receiver, arrive, g): the mean of what has arrived so far."""
    w = Window.partitionBy("iter", "receiver").orderBy("arrive", "sender").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return arrived.withColumns({"running": F.avg("g").over(w), "n": F.count("*").over(w)})


def gradient_mean(grads: DataFrame, by: tuple[str, ...] = ("iter",)) -> DataFrame:
    """The plain mean over workers: what the running mean is once all have arrived."""
    return grads.groupBy(*by).agg(F.avg("g").alias("g"))


def update_schedule(arrived: DataFrame, period: int | None = None) -> DataFrame:
    """(iter, receiver, ready, applied, staleness): when a worker has all gradients of an iteration, and in which own iteration it applies their mean.

    At a resync, every ``period`` iterations, all workers wait for what is pending and apply it; period 1 is the synchronous method.
    """
    ready = arrived.groupBy("iter", "receiver").agg(F.max("arrive").cast("int").alias("ready"))
    applied = F.col("ready") if period is None else F.least(F.col("ready"), (F.ceil(F.col("iter") / period) * period).cast("int"))
    return ready.withColumn("applied", applied).withColumn("staleness", F.col("applied") - F.col("iter"))


def divergence(schedule: DataFrame, means: DataFrame, iterations: int, rate: float = 0.1) -> DataFrame:
    """(iter, spread): the largest difference between two workers' models after each iteration, for a scalar model moved by the means."""
    moved = schedule.join(means.withColumnRenamed("g", "mean"), "iter").groupBy("receiver", F.col("applied").alias("at")).agg(F.sum("mean").alias("step"))
    grid = schedule.select("receiver").distinct().withColumn("at", F.explode(F.sequence(F.lit(1), F.lit(iterations))))
    w = Window.partitionBy("receiver").orderBy("at").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    model = grid.join(moved, ["receiver", "at"], "left").withColumn("model", -F.lit(rate) * F.sum(F.coalesce("step", F.lit(0.0))).over(w))
    return model.groupBy(F.col("at").alias("iter")).agg((F.max("model") - F.min("model")).alias("spread"))


def resync(params: DataFrame, how: str = "mean") -> DataFrame:
    """(worker, i, w) with all workers equal: their mean, or worker 0's values."""
    if how == "mean":
        one = params.groupBy("i").agg(F.avg("w").alias("w"))
    else:
        one = params.where("worker = 0").select("i", "w")
    return params.select("worker", "i").join(one, "i").select("worker", "i", "w")


def staleness_report(schedule: DataFrame) -> DataFrame:
    """(staleness, n)."""
    return schedule.groupBy("staleness").agg(F.count("*").alias("n"))


def durations(spark: SparkSession, workers: int, iterations: int, seed: int = 7, straggler: float = 2.0) -> DataFrame:
    """(worker, iter, ms): 1 to 5, and more for the last worker."""
    rows = spark.range(workers * iterations).select((F.col("id") % workers).cast("int").alias("worker"), (F.floor(F.col("id") / workers) + 1).cast("int").alias("iter"))
    return rows.withColumn("ms", 1.0 + F.floor(5 * uniform(seed, "ms", F.col("worker"), F.col("iter"))) + F.when(F.col("worker") == workers - 1, straggler).otherwise(0.0))


def synchronous_time(ms: DataFrame) -> DataFrame:
    """(total): every iteration waits for the slowest."""
    return ms.groupBy("iter").agg(F.max("ms").alias("t")).agg(F.sum("t").alias("total"))


def asynchronous_time(ms: DataFrame, period: int) -> DataFrame:
    """(total): workers run on their own and join at every ``period``-th iteration."""
    part = ms.groupBy("worker", F.floor((F.col("iter") - 1) / period).alias("part")).agg(F.sum("ms").alias("t"))
    return part.groupBy("part").agg(F.max("t").alias("t")).agg(F.sum("t").alias("total"))


def exchange_bytes(workers: int, params: int) -> dict[str, int]:
    """Messages and bytes an iteration: all-to-all as published, and one aggregate as here."""
    return {"messages": workers * (workers - 1), "bytes": workers * (workers - 1) * params * 8, "aggregate_bytes": workers * params * 8}
