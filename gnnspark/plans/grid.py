"""Many training runs in one Spark job: experiments over models, exchange forms, numbers of workers and seeds.

Batches drive a :class:`fleet.Fleet` in order (epoch, then training before validation, then place); nothing of a run is held but its models and the gradients under way. Runs that read the same stream
share its sampling. Validation is measured after each epoch; a run stops early, keeps its best model, and scores the test batches with it.

A graph of bounded size lies as arrays in the shared folder, and tasks sample the batches that their runs still need (:mod:`local`). For larger ones all batches are sampled and packaged
by Spark plans, and a run is a partition that its packaged batches reach one Arrow batch at a time.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import kernels
from ..operators.fleet import Fleet, HashedDelays
from ..sources.graphs import Graph
from ..sources.spool import Spool
from . import local
from .batches import NODE_WISE, Sizes, Stream, kept, known_nodes, package, prepare, sampled, seeds_of, unpacked

TOLD = "run int, kind string, epoch int, a long, b long, c long, value double"


@dataclass(frozen=True)
class Run:
    """A run of the grid. ``piped``: stale exchange and the cache (for node-wise models); otherwise synchronous without cache."""

    model: str
    piped: bool = False
    workers: int = 1
    period: int = 1
    seed: int = 7

    @property
    def stream(self) -> Stream:
        return Stream(self.model, self.piped and self.model in NODE_WISE, self.seed)


@dataclass
class Course:
    """How runs are trained: ``metric`` accuracy or auc; early stop after ``patience`` batches without a gain of ``delta``."""

    dims: tuple[int, int, int]
    rate: float = 0.001
    metric: str = "accuracy"
    delta: float = 0.01
    patience: int = 200


@dataclass
class Validation:
    """Counts of scored rows: right ones, and histograms of scores by class (1024 bins) for the area under the curve."""

    hit: int = 0
    n: int = 0
    bins: np.ndarray = field(default_factory=lambda: np.zeros((2, 1024)))

    def add(self, p: np.ndarray, y: np.ndarray) -> None:
        self.hit, self.n = self.hit + int((p.argmax(1) == y).sum()), self.n + len(y)
        if p.shape[1] == 2:
            np.add.at(self.bins, (y, np.minimum((p[:, 1] * 1024).astype(int), 1023)), 1)

    def value(self, metric: str) -> float:
        if metric == "accuracy":
            return self.hit / self.n if self.n else 0.0
        no, yes = self.bins
        below = np.cumsum(no) - no
        pairs = no.sum() * yes.sum()
        return float((yes * (below + no / 2)).sum() / pairs) if pairs else 0.5


class Trainer:
    """One run as a consumer of batches in order."""

    def __init__(self, number: int, run: Run, course: Course):
        self.number, self.run, self.course, self.sage = number, run, course, run.model == "graphsage"
        params = kernels.init(course.dims, self.sage, run.seed)
        delay = HashedDelays(run.workers, run.seed) if run.piped else None
        self.fleet = Fleet(params, kernels.Adam(course.rate), run.workers, run.period if run.piped else 1, delay)
        self.waiting: list = []
        self.epoch, self.done, self.losses, self.check = -1, 0, [], None
        self.best, self.best_value, self.best_epoch = params, -1.0, -1
        self.reference, self.last_gain, self.stopped = None, 0, False
        self.rows: list[tuple] = []

    def tell(self, kind: str, a: int = 0, b: int = 0, c: int = 0, value: float = 0.0) -> None:
        self.rows.append((self.number, kind, self.epoch, a, b, c, float(value)))

    def take(self, row, epoch: int, phase: int) -> None:
        if epoch != self.epoch or (phase and self.waiting):
            self.close(epoch)
        if phase == 2:
            b = unpacked(row)
            p = kernels.forward(b, self.best, self.sage)["p"]
            ids = np.asarray(row.seeds)
            for i in range(len(b.y)):
                self.tell("test", ids[i], b.y[i], p[i].argmax(), p[i, 1] if p.shape[1] == 2 else p[i].max())
        elif not self.stopped:
            if phase == 1:
                b = unpacked(row)
                self.check = self.check or Validation()
                self.check.add(kernels.forward(b, self.fleet.mean_model(), self.sage)["p"], b.y)
            else:
                self.waiting.append(unpacked(row))
                if len(self.waiting) == self.run.workers:
                    self.iterate()

    def iterate(self) -> None:
        grads, began = {}, time.perf_counter()
        for w, b in enumerate(self.waiting):
            loss, grads[w] = kernels.loss_and_gradients(b, self.fleet.models[w], self.sage)
            self.losses.append(loss)
            now = time.perf_counter()
            self.tell("ms", self.done, w, 0, 1000 * (now - began))
            self.done, began = self.done + 1, now
        self.waiting = []
        self.fleet.iterate(grads)

    def close(self, epoch: int) -> None:
        """End of an epoch's training batches, or of its validation."""
        if self.waiting:
            self.iterate()
        if epoch != self.epoch:
            if self.check:
                self.validated(self.check.value(self.course.metric))
            if self.losses:
                self.tell("loss", self.done, value=np.mean(self.losses))
            self.check, self.losses, self.epoch = None, [], epoch

    def validated(self, value: float) -> None:
        self.tell("val", self.done, value=value)
        if value > self.best_value:
            self.best, self.best_value, self.best_epoch = self.fleet.mean_model(), value, self.epoch
        if self.reference is None or value - self.reference >= self.course.delta - 1e-9:
            self.reference, self.last_gain = value, self.done
        elif self.done - self.last_gain >= self.course.patience:
            self.stopped = True
            self.tell("stop", self.done)

    def finish(self) -> None:
        self.close(self.epoch + 1)
        self.tell("best", self.best_epoch, value=self.best_value)
        for x in self.fleet.log:
            self.tell("applied", x.made, x.receiver, x.applied, x.ready)
        for t, value in self.fleet.spread:
            self.tell("spread", t, value=value)

    def drained(self) -> pd.DataFrame:
        rows, self.rows = self.rows, []
        return pd.DataFrame(rows, columns=["run", "kind", "epoch", "a", "b", "c", "value"])


def train_grid(g: Graph, features: DataFrame, labels: DataFrame, runs: list[Run], course: Course, sizes: Sizes, keep: Spool, seed: int = 7, is_kept: bool = False) -> DataFrame:
    """(run, kind, epoch, a, b, c, value) of all runs, run numbers being places in ``runs``.

    ``loss`` and ``val`` by epoch (a: batches so far), ``stop`` and ``best`` (a: epoch) if any, ``ms`` by batch (a: batch, b: worker), ``applied`` (a: iteration of the gradients,
    b: receiver, c: iteration in which their mean was applied, value: in which the last one arrived), ``spread`` (a: iteration, value: largest difference between two workers' weights), and ``test`` by node
    (a: node, b: label, c: prediction, value: score). ``is_kept``: the graph's tables are spooled already.
    """
    from ..operators import cache as C

    streams = list(dict.fromkeys(r.stream for r in runs))
    g, cached = g if is_kept else kept(g, keep), any(s.cached for s in streams)
    if local.fits(g, course.dims[0]):
        known, cache = keep(known_nodes(g, labels, seed)), None
        if cached:
            p = C.cache_probs(g, known.where("split = 'train'").select("node_id"))
            cache = keep(C.build_cache(keep(p), C.cache_size(g.nodes.count(), sizes.cache_share), 0, seed))
        arrays = local.arrays(g, known, cache, features, f"{keep.folder}/arrays-{len(runs)}")
        if arrays:
            return keep(played_here(g.nodes.sparkSession, arrays, runs, streams, course, sizes, seed))
    x = prepare(g, labels, sizes, keep, seed)
    cache = keep(C.build_cache(x.cache_p, x.cache_size, 0, seed)) if cached else None
    seeds, ids, _ = seeds_of(x.known, streams, sizes)
    seeds = keep(seeds)
    edges, inputs = sampled(x.g, x.prop, seeds, ids, streams, sizes, cache, keep, seed)
    packaged = keep(package(seeds, edges, inputs, features, x.known.select("node_id", "y")))
    return keep(played(packaged, ids, runs, streams, course))


def shares(runs: list[Run], streams: list[Stream], tasks: int) -> list[list[int]]:
    """Numbers of the runs of each task: those of a stream together, or in even parts if there are fewer streams than ``tasks``."""
    out = []
    for s in streams:
        mine = [n for n, r in enumerate(runs) if r.stream == s]
        parts = min(len(mine), max(1, -(-tasks // len(streams))))
        out += [mine[i::parts] for i in range(parts)]
    return sorted(out, key=len, reverse=True)


def played_here(spark: SparkSession, arrays: local.Arrays, runs: list[Run], streams: list[Stream], course: Course, sizes: Sizes, seed: int = 7) -> DataFrame:
    """All runs over batches that their tasks sample; an epoch is sampled once for the runs of a task, and only if one of them has not stopped."""
    dealt = shares(runs, streams, spark.sparkContext.defaultParallelism)

    def go(parts):
        for pdf in parts:
            for task in pdf["id"]:
                mine = [Trainer(n, runs[n], course) for n in dealt[task]]
                stream, sampler = streams.index(mine[0].run.stream), local.Sampler(arrays, streams, sizes, seed)
                for epoch in range(sizes.epochs):
                    if all(t.stopped for t in mine):
                        break
                    for phase, held in ((0, epoch), (1, sizes.epochs)):
                        for row in sampler.batches(stream, held):
                            for t in mine:
                                t.take(row, epoch, phase)
                    for t in mine:
                        t.close(epoch + 1)
                        yield t.drained()
                for row in sampler.batches(stream, sizes.epochs + 1):
                    for t in mine:
                        t.take(row, sizes.epochs, 2)
                        if len(t.rows) > 10_000:
                            yield t.drained()
                for t in mine:
                    t.finish()
                    yield t.drained()

    return spark.range(0, len(dealt), 1, len(dealt)).mapInPandas(go, TOLD)


def played(packaged: DataFrame, ids, runs: list[Run], streams: list[Stream], course: Course) -> DataFrame:
    """All runs over packaged batches, each as one partition."""
    e = ids.epochs
    readers = F.create_map(*[F.lit(v) if not isinstance(v, list) else F.array(*map(F.lit, v)) for i, s in enumerate(streams) for v in (i, [n for n, r in enumerate(runs) if r.stream == s])])
    b, at = F.col("batch_id"), ids.epoch(F.col("batch_id"))
    turns = F.when(at < e, F.array(F.struct(at.alias("epoch"), F.lit(0).alias("phase"))))
    turns = turns.when(at == e, F.transform(F.sequence(F.lit(0), F.lit(e - 1)), lambda i: F.struct(i.alias("epoch"), F.lit(1).alias("phase"))))
    turns = turns.otherwise(F.array(F.struct(F.lit(e).alias("epoch"), F.lit(2).alias("phase"))))
    dealt = packaged.withColumn("run", F.explode(readers[ids.stream(b)])).withColumn("turn", F.explode(turns)).select("*", "turn.epoch", "turn.phase").drop("turn")
    ordered = dealt.repartitionById(len(runs), F.col("run")).sortWithinPartitions("run", "epoch", "phase", "batch_id")

    def go(parts):
        now: Trainer | None = None
        for pdf in parts:
            for row in pdf.itertuples():
                if now is None or now.number != row.run:
                    if now:
                        now.finish()
                        yield now.drained()
                    now = Trainer(row.run, runs[row.run], course)
                now.take(row, row.epoch, row.phase)
            if now and now.rows:
                yield now.drained()
        if now:
            now.finish()
            yield now.drained()

    return ordered.mapInPandas(go, TOLD)
