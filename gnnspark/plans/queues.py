"""Queue sizes: the formula over measured times, the memory cap, re-tuning, sweeps; and the bounded queues of a real run."""

from __future__ import annotations

import queue
import threading

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .schedule import STAGES, makespans, schedule


def queue_size(timings: DataFrame, cap: int | Column) -> DataFrame:
    """(run, raw, size, memory_bound): min(cap, max(2, ceil(max preparation / mean compute))), 1 at least."""
    told = timings.groupBy("run").agg(F.max(F.col("sampling") + F.col("transfer")).alias("prep"), F.avg("compute").alias("mean"))
    raw = F.ceil(F.col("prep") / F.col("mean")).cast("long")
    limit = (cap if isinstance(cap, Column) else F.lit(cap)).cast("long")
    return told.select("run", raw.alias("raw"), F.greatest(F.lit(1), F.least(limit, F.greatest(F.lit(2), raw))).cast("long").alias("size"), (limit < F.greatest(F.lit(2), raw)).cast("int").alias("memory_bound"))


def batch_memory(stats: DataFrame, d: int, activations: str = "act") -> DataFrame:
    """Adds ``mem``: bytes of input features, of block edges (two ids and a float) and of activations."""
    return stats.withColumn("mem", F.col("inputs") * d * 4 + F.col("edges") * 20 + F.col(activations) * 4)


def queue_cap(stats: DataFrame, total: float, peak: float, margin: float = 0.10) -> DataFrame:
    """(run, cap): batches that fit in what the peak, with its margin, leaves of the memory; all in one unit."""
    return stats.groupBy("run").agg(F.floor((F.lit(float(total)) - F.lit(peak * (1 + margin))) / F.max("mem")).cast("long").alias("cap"))


def queue_sweep(costs: DataFrame, sizes: range) -> DataFrame:
    """(run, queue, makespan, waiting): all sizes over the same costs; waiting is the compute stage's idle time."""
    out = None
    work = costs.groupBy("run", "worker").agg(F.sum("compute").alias("work")).groupBy("run").agg(F.max("work").alias("work"))
    for q in sizes:
        one = makespans(schedule(costs, "pipelined", q)).join(work, "run").select("run", F.lit(q).alias("queue"), "makespan", (F.col("makespan") - F.col("work")).alias("waiting"))
        out = one if out is None else out.union(one)
    return out


def adapt_queue(previous: DataFrame, cap: int) -> DataFrame:
    """(run, epoch, size): an epoch's size from the epoch before it; the first epoch uses 2."""
    sized = queue_size(previous.withColumn("run", F.struct("run", "epoch")), cap)
    later = sized.select(F.col("run.run").alias("run"), (F.col("run.epoch") + 1).alias("epoch"), "size")
    first = previous.select("run").distinct().select("run", F.lit(0).alias("epoch"), F.lit(2).cast("long").alias("size"))
    return first.union(later)


class BoundedQueues:
    """Queues of a run: prepared windows and transferred windows per worker, and gradients if there is more than one worker."""

    KINDS = ("host", "device", "gradient")

    def __init__(self, size: int, workers: int):
        kinds = self.KINDS if workers > 1 else self.KINDS[:2]
        self.size = size
        self.of = {(kind, w): queue.Queue(maxsize=size) for kind in kinds for w in range(workers)}
        self.most: dict[tuple[str, int], int] = dict.fromkeys(self.of, 0)
        self.lock = threading.Lock()
        self.log: list[tuple[str, int, int, int]] = []

    def resize(self, size: int) -> None:
        """A new bound for the queues of batches; producers that wait see it at once."""
        for (kind, _), q in self.of.items():
            if kind != "gradient":
                with q.mutex:
                    q.maxsize = size
                    q.not_full.notify_all()
        self.size = size

    def put(self, kind: str, worker: int, item, timeout: float | None = None) -> None:
        q = self.of[kind, worker]
        q.put(item, timeout=timeout)
        with self.lock:
            self.most[kind, worker] = max(self.most[kind, worker], q.qsize())
            self.log.append((kind, worker, q.qsize(), self.size))

    def get(self, kind: str, worker: int, timeout: float | None = None):
        return self.of[kind, worker].get(timeout=timeout)


__all__ = ["BoundedQueues", "STAGES", "adapt_queue", "batch_memory", "queue_cap", "queue_size", "queue_sweep"]
