"""The resync period and its cost."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def sync_cost_of(p: float, n: int, m: int, workers: int, alpha: float = 1.0, beta: float = 1.0) -> float:
    return alpha * p * m + beta * n / (p * workers)


def sync_period(n: int, m: int, workers: int, k: float = 1.0, mode: str = "printed") -> int:
    """Iterations between resyncs: the ceiling of k sqrt(n/(workers m)); ``integer_opt`` takes the cheaper of its two neighbours instead."""
    raw = k * math.sqrt(n / (workers * m)) if m else 1.0
    up = max(1, math.ceil(raw - 1e-12))
    if mode == "printed":
        return up
    low = max(1, math.floor(raw))
    beta = k * k
    return min((low, up), key=lambda p: (sync_cost_of(p, n, m, workers, 1.0, beta), p))


def sync_periods(sizes: DataFrame, workers: range, k: float = 1.0) -> DataFrame:
    """(graph, workers, raw, period, integer_opt) for rows (graph, n, m)."""
    g = F.col("workers")
    raw = F.lit(k) * F.sqrt(F.col("n") / (g * F.col("m")))
    cost = lambda p: p * F.col("m") + F.lit(k * k) * F.col("n") / (p * g)
    every = sizes.withColumn("workers", F.explode(F.array(*[F.lit(w) for w in workers]))).withColumn("raw", raw)
    up, low = F.greatest(F.lit(1), F.ceil("raw")), F.greatest(F.lit(1), F.floor("raw"))
    return every.select("graph", "workers", F.round("raw", 6).alias("raw"), up.cast("long").alias("period"), F.when(cost(low) <= cost(up), low).otherwise(up).cast("long").alias("integer_opt"))


def sync_cost(sizes: DataFrame, periods: range, workers: int, alpha: float = 1.0, beta: float = 1.0) -> DataFrame:
    """(graph, p, cost) for rows (graph, n, m)."""
    every = sizes.withColumn("p", F.explode(F.array(*[F.lit(p) for p in periods])))
    return every.select("graph", "p", (F.lit(alpha) * F.col("p") * F.col("m") + F.lit(beta) * F.col("n") / (F.col("p") * workers)).alias("cost"))
