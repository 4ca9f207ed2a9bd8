"""Stages of the pipeline, their costs on a deterministic clock, and schedules: serial, prefetching, pipelined, bounded.

Costs are rows (run, worker, k, one column a stage); k numbers a worker's batches. All schedules but the bounded one are running
windows within a worker; the bounded one is a true recursion and runs per worker.
"""

from __future__ import annotations

from enum import Enum

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


class Stage(str, Enum):
    LOAD = "load"
    MODEL_TRANSFER = "model_transfer"
    GENERATE = "sampling"
    TRANSFER = "transfer"
    COMPUTE = "compute"
    SHARE = "share"
    UPDATE = "update"


STAGES = (Stage.GENERATE.value, Stage.TRANSFER.value, Stage.COMPUTE.value)


def cost_clock(stats: DataFrame, per_edge: float = 1e-4, bandwidth: float = 1e6, per_flop: float = 3e-6, fixed: tuple[float, float, float] = (1.0, 0.5, 0.5)) -> DataFrame:
    """Adds milliseconds per stage to batch statistics (touched edges, bytes, flops); only ratios and orders mean anything."""
    return stats.withColumns({"sampling": F.lit(fixed[0]) + F.col("touched") * per_edge, "transfer": F.lit(fixed[1]) + F.col("bytes") / bandwidth, "compute": F.lit(fixed[2]) + F.col("flops") * per_flop})


def _order() -> Window:
    return Window.partitionBy("run", "worker").orderBy("k")


def _through(df: DataFrame, stage: str, ready: Column, i: int) -> DataFrame:
    """One server after another: finish(k) = cum(k) + max over j <= k of (ready(j) - cum(j-1))."""
    upto = _order().rowsBetween(Window.unboundedPreceding, Window.currentRow)
    df = df.withColumn(f"__c{i}", F.sum(stage).over(upto)).withColumn(f"__r{i}", ready)
    finish = F.col(f"__c{i}") + F.max(F.col(f"__r{i}") - (F.col(f"__c{i}") - F.col(stage))).over(upto)
    return df.withColumn(f"finish_{stage}", finish)


def schedule(costs: DataFrame, mode: str = "pipelined", queue: int | None = None, stages: tuple[str, ...] = STAGES) -> DataFrame:
    """(run, worker, k, finish_<stage>...) under a schedule.

    ``serial``: one batch after another; ``prefetch``: the first stage runs ahead, the rest in series; ``pipelined``: every
    stage runs ahead, without bound or with ``queue`` slots between stages (a batch may start once the next stage has taken the
    batch ``queue`` before it).
    """
    keep = ["run", "worker", "k", *stages]
    df = costs.select(*keep)
    if mode == "serial":
        total = sum((F.col(s) for s in stages), F.lit(0.0))
        before = F.sum(total).over(_order().rowsBetween(Window.unboundedPreceding, Window.currentRow)) - total
        at = before
        for s in stages:
            at = at + F.col(s)
            df = df.withColumn(f"finish_{s}", at)
    elif mode == "prefetch":
        rest = sum((F.col(s) for s in stages[1:]), F.lit(0.0))
        df = _through(df, stages[0], F.lit(0.0), 0).withColumn("__rest", rest)
        df = _through(df, "__rest", F.col(f"finish_{stages[0]}"), 1)
        at = F.col("finish___rest") - F.col("__rest")
        for s in stages[1:]:
            at = at + F.col(s)
            df = df.withColumn(f"finish_{s}", at)
    elif queue is None:
        ready = F.lit(0.0)
        for i, s in enumerate(stages):
            df = _through(df, s, ready, i)
            ready = F.col(f"finish_{s}")
    else:
        schema = StructType(list(df.schema.fields))
        for s in stages:
            schema = schema.add(f"finish_{s}", "double")
        df = df.groupBy("run", "worker").applyInPandas(lambda pdf: bounded(pdf, queue, stages), schema)
    return df.select("run", "worker", "k", *[f"finish_{s}" for s in stages])


def bounded(pdf: pd.DataFrame, queue: int, stages: tuple[str, ...]) -> pd.DataFrame:
    """One worker's batches through stages with ``queue`` slots between neighbours."""
    pdf = pdf.sort_values("k").reset_index(drop=True)
    starts = [[0.0] * len(pdf) for _ in stages]
    done = [[0.0] * len(pdf) for _ in stages]
    costs = [pdf[s].tolist() for s in stages]
    for k in range(len(pdf)):
        for i in range(len(stages)):
            at = max(done[i][k - 1] if k else 0.0, done[i - 1][k] if i else 0.0)
            if i + 1 < len(stages) and k >= queue:
                at = max(at, starts[i + 1][k - queue])
            starts[i][k], done[i][k] = at, at + costs[i][k]
    for i, s in enumerate(stages):
        pdf[f"finish_{s}"] = done[i]
    return pdf


def makespans(scheduled: DataFrame, last: str = "compute") -> DataFrame:
    """(run, makespan): the latest worker's end."""
    return scheduled.groupBy("run").agg(F.max(f"finish_{last}").alias("makespan"))


def synchronous(costs: DataFrame, exchange_ms: Column, stages: tuple[str, ...] = STAGES) -> DataFrame:
    """(run, makespan) when every iteration waits for the slowest worker and then exchanges gradients."""
    total = sum((F.col(s) for s in stages), F.lit(0.0))
    step = costs.groupBy("run", "k").agg(F.max(total).alias("t"))
    return step.groupBy("run").agg((F.sum("t") + F.count("*") * exchange_ms).alias("makespan"))
