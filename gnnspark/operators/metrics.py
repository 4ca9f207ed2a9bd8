"""Accuracy and cost measures, each a plan over result tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .prefix import running


def trimmed(timings: DataFrame, trim: int = 20, by: str = "run") -> DataFrame:
    """Rows (run, k, ms) without the first and last ``trim`` of each run."""
    up, down = Window.partitionBy(by).orderBy("k"), Window.partitionBy(by).orderBy(F.col("k").desc())
    return timings.withColumns({"a": F.row_number().over(up), "b": F.row_number().over(down)}).where((F.col("a") > trim) & (F.col("b") > trim)).drop("a", "b")


def batch_time(timings: DataFrame, trim: int = 20) -> DataFrame:
    """(run, mean, sd, n)."""
    return trimmed(timings, trim).groupBy("run").agg(F.avg("ms").alias("mean"), F.stddev_samp("ms").alias("sd"), F.count("*").alias("n"))


def training_time(spans: DataFrame) -> DataFrame:
    """(run, ms) from rows (run, start_ms, end_ms)."""
    return spans.groupBy("run").agg((F.max("end_ms") - F.min("start_ms")).alias("ms"))


def accuracy(pred: DataFrame) -> DataFrame:
    """(accuracy) of rows (y, yhat)."""
    return pred.agg(F.avg((F.col("y") == F.col("yhat")).cast("double")).alias("accuracy"))


def f1(pred: DataFrame) -> DataFrame:
    """(micro, macro) over classes in truth or prediction; a class without support or predictions counts 0."""
    ends = pred.select(F.col("y").alias("c"), F.lit(1).alias("t"), F.lit(0).alias("p"), (F.col("y") == F.col("yhat")).cast("int").alias("tp")).union(pred.select(F.col("yhat"), F.lit(0), F.lit(1), F.lit(0)))
    per = ends.groupBy("c").agg(F.sum("t").alias("t"), F.sum("p").alias("p"), F.sum("tp").alias("tp"))
    score = lambda tp, t, p: F.when(t + p > 0, 2.0 * tp / (t + p)).otherwise(0.0)
    return per.agg(score(F.sum("tp"), F.sum("t"), F.sum("p")).alias("micro"), F.avg(score(F.col("tp"), F.col("t"), F.col("p"))).alias("macro"))


def roc_auc(scores: DataFrame) -> DataFrame:
    """(auc) of rows (y in 0/1, score), ties at mean rank. Counts are summed by distinct score first, and ranks are running sums in two levels."""
    by = scores.groupBy("score").agg(F.sum("y").alias("pos"), F.count("*").alias("n"))
    ranked = running(by, ["score"], F.col("n")).withColumn("rank", F.col("before") + (F.col("n") + 1) / 2.0)
    told = ranked.agg(F.sum(F.col("rank") * F.col("pos")).alias("r"), F.sum("pos").alias("p"), F.sum(F.col("n") - F.col("pos")).alias("q"))
    return told.select(((F.col("r") - F.col("p") * (F.col("p") + 1) / 2.0) / (F.col("p") * F.col("q"))).alias("auc"))


def binned_auc(scores: DataFrame, bins: int = 1024) -> DataFrame:
    """ROC-AUC from a histogram of scores in [0, 1]: bounded state at any size."""
    return roc_auc(scores.select("y", F.floor(F.col("score") * bins).alias("score")))


def utilisation(busy: DataFrame, tick: int = 10, width: int = 150) -> DataFrame:
    """(run, mean, peak, idle) from compute spans (run, start_ms, end_ms): busy share of the makespan, and the peak of a trailing mean over ticks."""
    ends = busy.groupBy("run").agg(F.max("end_ms").alias("end"), F.sum(F.col("end_ms") - F.col("start_ms")).alias("busy"))
    smooth = smoothed(busy, tick, width).groupBy("run").agg(F.max("smooth").alias("peak"))
    return ends.join(smooth, "run").select("run", (F.col("busy") / F.col("end")).alias("mean"), "peak", (1 - F.col("busy") / F.col("end")).alias("idle"))


def smoothed(busy: DataFrame, tick: int = 10, width: int = 150) -> DataFrame:
    """(run, tick, share, smooth). Spans are cut at ticks, so the overlap join is a generator and an aggregate."""
    cut = busy.select("run", "start_ms", "end_ms", F.explode(F.sequence(F.floor(F.col("start_ms") / tick), F.floor(F.col("end_ms") / tick))).alias("tick"))
    part = F.greatest(F.lit(0.0), F.least(F.col("end_ms"), (F.col("tick") + 1) * float(tick)) - F.greatest(F.col("start_ms"), F.col("tick") * float(tick)))
    filled = cut.groupBy("run", "tick").agg((F.sum(part) / tick).alias("share"))
    grid = busy.groupBy("run").agg(F.max("end_ms").alias("end")).select("run", F.explode(F.sequence(F.lit(0).cast("long"), F.floor(F.col("end") / tick))).alias("tick"))
    w = Window.partitionBy("run").orderBy("tick").rowsBetween(-(width // tick - 1), 0)
    return grid.join(filled, ["run", "tick"], "left").withColumn("share", F.coalesce("share", F.lit(0.0))).withColumn("smooth", F.avg("share").over(w))


def speedup(results: DataFrame) -> DataFrame:
    """(model, dataset, workers, speedup) of rows (model, dataset, workers, piped, training_ms)."""
    k = ["model", "dataset", "workers"]
    base, piped = results.where("piped = 0").select(*k, F.col("training_ms").alias("b")), results.where("piped = 1").select(*k, F.col("training_ms").alias("p"))
    return base.join(piped, k).select(*k, (F.col("b") / F.col("p")).alias("speedup"))


def metric_change(results: DataFrame) -> DataFrame:
    """(model, dataset, workers, points): metric of the piped run less that of the base run."""
    k = ["model", "dataset", "workers"]
    base, piped = results.where("piped = 0").select(*k, F.col("metric").alias("b")), results.where("piped = 1").select(*k, F.col("metric").alias("p"))
    return base.join(piped, k).select(*k, (F.col("p") - F.col("b")).alias("points"))


def run_stats(runs: DataFrame, by: tuple[str, ...], value: str = "value") -> DataFrame:
    return runs.groupBy(*by).agg(F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"), F.count("*").alias("n"))


def scaling(results: DataFrame) -> DataFrame:
    """(model, dataset, t1..t4, eff4): training time by workers, and efficiency at four."""
    wide = results.groupBy("model", "dataset").pivot("workers", [1, 2, 3, 4]).agg(F.first("training_ms"))
    named = wide.select("model", "dataset", *[F.col(str(w)).alias(f"t{w}") for w in (1, 2, 3, 4)])
    return named.withColumn("eff4", F.col("t1") / (4 * F.col("t4")))


def stage_share(costs: DataFrame) -> DataFrame:
    """(run, loading): share of sampling and transfer in all stage time."""
    load = F.sum(F.col("sampling") + F.col("transfer"))
    return costs.groupBy("run").agg((load / (load + F.sum("compute"))).alias("loading"))


def early_stop(history: DataFrame, delta: float = 0.01, patience: int = 200) -> DataFrame:
    """(run, stop_step, best_step): the reference moves when a value is ``delta`` above it; after ``patience`` steps without a move the run stops.

    The moving reference is a fold over a run's short history (one value a check), collected in order within its run.
    """
    steps = history.groupBy("run").agg(F.sort_array(F.collect_list(F.struct("step", "value"))).alias("h"))
    begin = F.struct(F.lit(None).cast("double").alias("ref"), F.lit(0).alias("misses"), F.lit(None).cast("int").alias("stop"), F.lit(0).alias("last"))

    def step(acc, x):
        moved = acc["ref"].isNull() | (F.round(x["value"] - acc["ref"], 9) >= delta)
        misses = F.when(moved, 0).otherwise(acc["misses"] + 1)
        stop = F.coalesce(acc["stop"], F.when(misses >= patience, x["step"].cast("int")))
        return F.struct(F.when(moved, x["value"]).otherwise(acc["ref"]).alias("ref"), misses.alias("misses"), stop.alias("stop"), x["step"].cast("int").alias("last"))

    told = steps.select("run", "h", F.aggregate("h", begin, step).alias("a")).select("run", "h", F.coalesce("a.stop", "a.last").alias("stop_step"))
    seen = told.select("run", "stop_step", F.explode("h").alias("x")).where("x.step <= stop_step")
    best = seen.groupBy("run", "stop_step").agg(F.max_by("x.step", F.struct("x.value", -F.col("x.step"))).alias("best_step"))
    return best.select("run", "stop_step", F.col("best_step").cast("int").alias("best_step"))
