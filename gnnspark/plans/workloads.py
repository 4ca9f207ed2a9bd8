"""Experiment workloads on the cost clock: a sampler's batch statistics over a whole epoch of a graph, then base and piped runs for numbers of workers."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import uniform
from ..operators import cache as C
from ..operators import layerwise, nodewise
from ..operators.propagation import propagation, split_of
from ..sources.graphs import Graph, load_graph
from ..sources.spool import Spool, let_go, spool
from . import epochs
from .batches import Sizes
from .schedule import STAGES, cost_clock, makespans, schedule, synchronous

DATASETS = ("cust_supp", "emb_knn", "part_pair", "cust_part")
SHAPES = {"cust_supp": (8, 2), "emb_knn": (64, 10), "part_pair": (128, 2), "cust_part": (16, 2)}
HIDDEN, BATCH, FANOUT, SIZE = 64, 64, 5, 512
SHARE_MS, CACHE_SHARE = 0.1, 0.01


def _counts(parts: list[tuple[str, DataFrame]]) -> DataFrame:
    """One row a batch with a column per named table: its rows, or the sum of its column ``n``."""
    out = None
    for name, df in parts:
        n = F.col("n").cast("long") if "n" in df.columns else F.lit(1).cast("long")
        one = df.select("batch_id", F.lit(name).alias("what"), n.alias("n"))
        out = one if out is None else out.union(one)
    wide = out.groupBy("batch_id").pivot("what", [p[0] for p in parts]).agg(F.sum("n"))
    return wide.fillna(0)


def planned(g: Graph, train: DataFrame, n: int, models: tuple[str, ...]) -> DataFrame:
    """What each of the ``n`` batches of an epoch holds (:data:`epochs.TOLD`), by Spark plans: for graphs that do not lie in arrays."""
    g = replace(g, edges=spool(g.edges.select("dst", "src")))
    deg, cache = spool(C.in_degrees(g.edges)), spool(C.build_cache(C.cache_probs_degree(g), C.cache_size(g.nodes.count(), CACHE_SHARE)))
    place = F.floor(uniform(7, "batch", 0, F.col("node_id")) * n).cast("long")
    seeds = spool(train.select(F.explode(F.array(*map(F.lit, range(len(models))))).alias("i"), "node_id", place.alias("p")).select((F.col("i") * n + F.col("p")).alias("batch_id"), "node_id"))
    of = lambda test: F.floor(F.col("batch_id") / n).isin([i for i, m in enumerate(models) if test(m)])
    prop, out = None, None
    for family in ("node", "fastgcn", "ladies"):
        mine = [m for m in models if (m in layerwise.VARIANTS and m.startswith(family)) or (family == "node" and m not in layerwise.VARIANTS)]
        if not mine:
            continue
        here = seeds.where(of(lambda m: m in mine) if family != "node" else of(lambda m: m == mine[0]))  # noqa: B023
        if family == "node":
            blocks, fronts = nodewise.node_wise_batches(here, g.edges, [FANOUT, FANOUT], keep=spool)
            rows, inputs, extra = fronts[1], fronts[2], 0
        else:
            prop = prop if prop is not None else spool(propagation(g))
            flat, debias = (of(lambda m, x=x: m in mine and layerwise.VARIANTS[m][x]) for x in (1, 2))  # noqa: B023
            chosen, _ = layerwise.LayerSampler(family, flat, debias, sizes=(SIZE, SIZE), keep=spool).layers(prop, here)
            above = here, chosen[0]  # counts need no weights
            blocks = [layerwise.meetings(prop, a, c, layerwise.is_small(a, c)).select("batch_id") for a, c in zip(above, chosen)]
            rows, inputs, extra = chosen[0].select("batch_id", "node_id"), chosen[1].select("batch_id", "node_id"), 1
        touched = here.union(rows.select("batch_id", "node_id")).join(deg, "node_id", "left").select("batch_id", (F.coalesce("deg", F.lit(0)) + extra).alias("n"))
        told = _counts([("touched", touched), ("e1", blocks[0]), ("e0", blocks[1]), ("r1", here), ("r0", rows), ("inputs", inputs), ("missing", inputs.join(cache, "node_id", "left_anti"))])
        if family == "node":
            told = told.withColumn("batch_id", F.explode(F.array(*[(F.col("batch_id") % n + models.index(m) * n).cast("long") for m in mine])))
        out = told if out is None else out.unionByName(told)
    return out


def epoch_stats(spark: SparkSession, d: str, dataset: str, models: tuple[str, ...]) -> DataFrame:
    """(model, batch_id, touched, edges, inputs, missing, act, flops): what each batch of an epoch costs, written once.

    The batches are those of the whole training split. Layer-wise models of one family share a plan: model i has the batch ids from i times the number of batches on.
    The node-wise models share their very samples, which have the ids of the first model.
    """
    g = load_graph(spark, d, dataset)
    g, keep = replace(g, nodes=spool(g.nodes)), Spool(spark)
    train = g.nodes.where(split_of(F.col("node_id"), dataset) == "train").select("node_id")
    n = max(1, -(-train.count() // BATCH))
    out = epochs.counts(g, train, n, models, Sizes(BATCH, FANOUT, SIZE), CACHE_SHARE, keep)
    out = planned(g, train, n, models) if out is None else spool(out)
    keep.close()
    (d0, classes), model = SHAPES[dataset], F.element_at(F.array(*map(F.lit, models)), (F.floor(F.col("batch_id") / n) + 1).cast("int"))
    m = F.when(model == "graphsage", 2).otherwise(1)
    flops = F.col("e0") * d0 + F.col("r0") * m * (d0 * HIDDEN) + F.col("e1") * HIDDEN + F.col("r1") * m * (HIDDEN * classes)
    return spool(out.select(model.alias("model"), (F.col("batch_id") % n).alias("batch_id"), "touched", (F.col("e0") + F.col("e1")).alias("edges"), "inputs", "missing", (F.col("r0") * HIDDEN + F.col("r1") * classes).alias("act"), flops.alias("flops")))


def all_stats(spark: SparkSession, d: str, datasets: tuple[str, ...], models: tuple[str, ...]) -> list[DataFrame]:
    """The statistics by data set, one after another, so that the files of one graph are gone before the next is built."""
    out = []
    for x in datasets:
        out.append(epoch_stats(spark, d, x, models))
        let_go(spark)
    return out


def one_model(spark: SparkSession, d: str, dataset: str, model: str) -> DataFrame:
    """The statistics of one model's epoch."""
    return epoch_stats(spark, d, dataset, (model,)).drop("model")


def costs_of(stats: DataFrame, width: int, workers: int, piped: bool, run=None) -> DataFrame:
    """(run, worker, k, sampling, transfer, compute, share, bytes)."""
    bytes_ = (F.col("missing") if piped else F.col("inputs")) * width * 4
    clock = cost_clock(stats.withColumn("bytes", bytes_))
    return clock.select((F.lit(0) if run is None else run).alias("run"), (F.col("batch_id") % workers).cast("int").alias("worker"), F.floor(F.col("batch_id") / workers).alias("k"), *STAGES, F.lit(SHARE_MS * (workers - 1)).alias("share"), "bytes")


def workload(spark: SparkSession, d: str, models: tuple[str, ...], workers: int | tuple[int, ...], datasets: tuple[str, ...] = DATASETS) -> DataFrame:
    """(model, dataset, workers, piped, batches, batch_ms, training_ms, bytes) of an epoch: base runs are serial and synchronous, piped runs overlap all stages.

    Statistics do not depend on the number of workers; models are runs of one plan.
    """
    out = None
    for dataset, stats in zip(datasets, all_stats(spark, d, datasets, models)):
        for g in (workers,) if isinstance(workers, int) else workers:
            for piped in (False, True):
                costs = costs_of(stats, SHAPES[dataset][0], g, piped, F.col("model"))
                if piped:
                    spans = makespans(schedule(costs, "pipelined", None, (*STAGES, "share")), "share")
                else:
                    spans = synchronous(costs, F.lit(SHARE_MS * (g - 1)))
                size = costs.groupBy("run").agg(F.count("*").alias("n"), F.sum("bytes").alias("bytes"))
                one = spans.join(size, "run").select(F.col("run").alias("model"), F.lit(dataset).alias("dataset"), F.lit(g).alias("workers"), F.lit(int(piped)).alias("piped"), F.col("n").alias("batches"), (F.col("makespan") / F.col("n")).alias("batch_ms"), F.col("makespan").alias("training_ms"), "bytes")
                out = one if out is None else out.union(one)
    return out
