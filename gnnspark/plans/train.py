"""One training run over the cluster: a pipeline of three stages with queues between them, and workers that exchange late gradients.

A sampling thread turns windows of epochs into blocks (one Spark job a layer for all batches of the window) and hands them to the host queue of each worker. A transfer thread per worker
fetches the features of its batches and hands packaged batches to the worker's device queue. The compute stage takes one window from each device queue. With several workers each iteration is a
job with one task a worker: batches stay on executors, and only gradients, which have the size of the model, reach the driver, where they pass the gradient queues to
:class:`fleet.Fleet`. With one worker a window is one task that reads its batches in order, one Arrow batch at a time.

The size of the queues follows the measured times of the windows so far, up to what memory allows beyond the measured peak of the compute tasks. Validation follows each window; a run stops early and keeps its best model. Windows are tables in the shared folder:
plans stay small, a lost executor costs the tasks that it ran, and a window is deleted once it was used.
"""

from __future__ import annotations

import math
import pickle
import queue
import resource
import threading
import time
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import cache as C
from ..operators import kernels, sync
from ..operators.fleet import Fleet, HashedDelays
from ..sources.graphs import Graph
from ..sources.spool import Spool
from .batches import NODE_WISE, Sizes, Stream, kept, package, prepare, sampled, seeds_of, unpacked
from .queues import BoundedQueues


@dataclass
class RunResult:
    """What a run did: history rows (epoch, what, value), stage spans (worker, turn, stage, start, end) in seconds, ms by batch, the model, and the queues' sizes by turn."""

    model: str
    piped: bool
    workers: int
    period: int
    history: list[tuple[int, str, float]] = field(default_factory=list)
    timings: list[tuple[int, int, str, float, float]] = field(default_factory=list)
    batch_ms: list[float] = field(default_factory=list)
    params: list[np.ndarray] = field(default_factory=list)
    most_queued: dict = field(default_factory=dict)
    queue_sizes: list[int] = field(default_factory=list)
    peak_bytes: float = 0.0
    fleet: Fleet | None = None


GRADIENTS = "worker int, state binary, loss double, ms double, peak long"


def gradients(rows: DataFrame, models: list[list[np.ndarray]], sage: bool, worker) -> list:
    """Loss and gradient of each batch on its worker's model, computed where the batch is."""
    packed = pickle.dumps(models)

    def go(parts):
        held = pickle.loads(packed)
        for pdf in parts:
            for row in pdf.itertuples():
                began = time.perf_counter()
                loss, grads = kernels.loss_and_gradients(unpacked(row), held[row.worker], sage)
                ms = 1000 * (time.perf_counter() - began)
                yield pd.DataFrame([(row.worker, pickle.dumps(grads), loss, ms, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss)], columns=["worker", "state", "loss", "ms", "peak"])

    return rows.withColumn("worker", worker).repartitionById(len(models), F.col("worker")).mapInPandas(go, GRADIENTS).collect()


def alone(rows: DataFrame, fleet: Fleet, sage: bool) -> list:
    """One worker's batches in order in one task; the last row holds the resulting fleet."""
    packed = pickle.dumps(fleet)

    def go(parts):
        mine, peak = pickle.loads(packed), 0
        for pdf in parts:
            out = []
            for row in pdf.itertuples():
                began = time.perf_counter()
                loss, grads = kernels.loss_and_gradients(unpacked(row), mine.models[0], sage)
                mine.iterate({0: grads})
                peak = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
                out.append((0, b"", loss, 1000 * (time.perf_counter() - began), peak))
            yield pd.DataFrame(out, columns=["worker", "state", "loss", "ms", "peak"])
        yield pd.DataFrame([(-1, pickle.dumps(mine), 0.0, 0.0, peak)], columns=["worker", "state", "loss", "ms", "peak"])

    return rows.coalesce(1).sortWithinPartitions("batch_id").mapInPandas(go, GRADIENTS).collect()


def evaluate(packaged: DataFrame, params, sage: bool) -> float:
    """Accuracy over packaged batches, scored on executors."""

    def go(parts):
        for pdf in parts:
            hit = n = 0
            for row in pdf.itertuples():
                b = unpacked(row)
                hit += int((kernels.forward(b, params, sage)["p"].argmax(1) == b.y).sum())
                n += len(b.y)
            yield pd.DataFrame({"hit": [hit], "n": [n]})

    told = packaged.mapInPandas(go, "hit long, n long").agg(F.sum("hit"), F.sum("n")).first()
    return told[0] / told[1] if told[1] else 0.0


def window_bytes(packaged: DataFrame) -> float:
    """Bytes of the largest batch of a window."""
    size = F.coalesce(F.size("layer"), F.lit(0)) * 28 + F.size("x") * 4 + (F.size("inputs") + F.size("seeds")) * 8
    return float(packaged.agg(F.max(size)).first()[0] or 1)


def train(g: Graph, features: DataFrame, labels: DataFrame, dims: tuple[int, int, int], model: str = "gcn", piped: bool = True, workers: int = 1, period: int | None = None, epochs: int = 3, span: int = 1, batch: int = 64, fanout: int = 5, size: int = 512, rate: float = 0.001, seed: int = 7, queue_size: int = 2, memory: float = 8e9, delta: float = 0.01, patience: int = 200) -> RunResult:
    """Train one model. ``piped``: overlapped stages, the cache for node-wise models and stale exchange with a resync every ``period`` iterations (by
    default the graph's); otherwise one stage after another, no cache, and gradients averaged in every iteration. ``span`` epochs make a window."""
    spark, sage = g.edges.sparkSession, model == "graphsage"
    keep, sizes = Spool(spark), Sizes(batch, fanout, size, epochs)
    stream = Stream(model, piped and model in NODE_WISE, seed)
    x = prepare(kept(g, keep), labels, sizes, keep, seed)
    if period is None:
        edges = x.g.edges.count()
        period = sync.sync_period(x.g.nodes.count(), edges if g.directed else edges // 2, workers)
    period = period if piped else 1
    seeds, ids, counts = seeds_of(x.known, [stream], sizes)
    y = x.known.select("node_id", "y")
    turns = [(low, min(low + span, epochs)) for low in range(0, epochs, span)]
    out, began = RunResult(model, piped, workers, period), time.time()
    out.fleet = Fleet(kernels.init(dims, sage, seed), kernels.Adam(rate), workers, period, HashedDelays(workers, seed) if piped else None)
    queues, stop, failed, threads = BoundedQueues(queue_size, workers), threading.Event(), [], []
    place = F.col("batch_id") % ids.width
    worker = (place % workers).cast("int")

    def spanned(w: int, turn: int, stage: str, what):
        t = time.time()
        done = what()
        out.timings.append((w, turn, stage, t - began, time.time() - began))
        return done

    def blocks(low: int, high: int, turn: int, use_cache: bool):
        cache = keep(C.build_cache(x.cache_p, x.cache_size, turn, seed)) if use_cache else None
        mine = keep(seeds.where(ids.epoch(F.col("batch_id")).between(low, high - 1)))
        edges, inputs = sampled(x.g, x.prop, mine, ids, [stream], sizes, cache, keep, seed)
        return mine, keep(edges), keep(inputs)

    def packaged(three, only=None) -> DataFrame:
        mine = [df if only is None else df.where(only) for df in three]
        return keep(package(*mine, features, y).repartitionByRange("batch_id").sortWithinPartitions("batch_id"))

    def put(kind: str, w: int, item) -> bool:
        while not stop.is_set():
            try:
                queues.put(kind, w, item, 0.2)
                return True
            except queue.Full:
                continue
        return False

    def get(kind: str, w: int):
        while not stop.is_set():
            try:
                return queues.get(kind, w, 0.2)
            except queue.Empty:
                continue
        return None

    def guarded(work, *args):
        try:
            work(*args)
        except Exception as problem:  # handed to the compute stage, which would wait for ever otherwise
            failed.append(problem)
            stop.set()

    def sampling():
        for turn, (low, high) in enumerate(turns):
            three = spanned(0, turn, "sampling", lambda: blocks(low, high, turn, stream.cached))  # noqa: B023
            for w in range(workers):
                if not put("host", w, three):
                    return

    def transfer(w: int):
        for turn in range(len(turns)):
            three = get("host", w)
            if three is None or not put("device", w, spanned(w, turn, "transfer", lambda: packaged(three, worker == w))):  # noqa: B023
                return

    if piped:
        from pyspark import InheritableThread

        for target in ((sampling,), *((transfer, w) for w in range(workers))):
            threads.append(InheritableThread(target=guarded, args=target, daemon=True))
            threads[-1].start()

    def window(turn: int) -> list[DataFrame]:
        if piped:
            return [get("device", w) for w in range(workers)]
        low, high = turns[turn]
        three = spanned(0, turn, "sampling", lambda: blocks(low, high, turn, False))
        return [spanned(0, turn, "transfer", lambda: packaged(three))]

    def compute(parts: list[DataFrame], low: int, high: int) -> None:
        rows = parts[0]
        for p in parts[1:]:
            rows = rows.unionByName(p)
        for e in range(low, high):
            losses, first = [], int(e * ids.width)
            if workers == 1:
                told = alone(rows.where(F.col("batch_id").between(first, first + ids.width - 1)), out.fleet, sage)
                states = [t for t in told if t["worker"] < 0]
                out.fleet = pickle.loads(states[-1]["state"]) if states else out.fleet
                note(told, losses)
            for t in range(first, first + counts.get("train", 1), workers) if workers > 1 else ():
                told = gradients(rows.where(F.col("batch_id").between(t, t + workers - 1)), out.fleet.models, sage, worker)
                for one in told:  # a gradient queue per worker, emptied by the exchange
                    queues.put("gradient", one["worker"], pickle.loads(one["state"]))
                if told:
                    out.fleet.iterate({one["worker"]: queues.get("gradient", one["worker"]) for one in told})
                note(told, losses)
            out.history.append((e, "loss", float(np.mean(losses)) if losses else float("nan")))

    def note(told, losses: list[float]) -> None:
        real = [t for t in told if t["worker"] >= 0]
        losses += [t["loss"] for t in real]
        out.batch_ms += [t["ms"] for t in real]
        out.peak_bytes = max([out.peak_bytes, *(1024.0 * t["peak"] for t in told)])

    held = {}

    def score(split: str, params) -> float:
        if split not in held:
            at = epochs + (split == "test")
            held[split] = packaged(blocks(at, at + 1, len(turns), False))
        return evaluate(held[split], params, sage)

    best, reference, last_gain = (-1.0, out.fleet.mean_model()), None, 0
    try:
        for turn, (low, high) in enumerate(turns):
            parts = window(turn)
            if failed:
                raise failed[0]
            spanned(0, turn, "compute", lambda: compute(parts, low, high))  # noqa: B023
            value = score("val", out.fleet.mean_model())
            out.history.append((high - 1, "val", value))
            queues.resize(tuned(out.timings, queue_size, memory, out.peak_bytes, window_bytes(parts[0]) * counts.get("train", 1) * span / len(parts)))
            out.queue_sizes.append(queues.size)
            if value > best[0]:
                best = value, out.fleet.mean_model()
            if reference is None or value - reference >= delta - 1e-9:
                reference, last_gain = value, len(out.batch_ms)
            elif len(out.batch_ms) - last_gain >= patience:
                out.history.append((high - 1, "stop", float(len(out.batch_ms))))
                break
        out.params = best[1]
        out.history.append((epochs, "test", score("test", best[1])))
    finally:
        stop.set()
        for thread in threads:
            thread.join()
        keep.close()
    out.most_queued = dict(queues.most)
    return out


def tuned(timings: list[tuple[int, int, str, float, float]], least: int, memory: float, peak: float, one: float, margin: float = 0.10) -> int:
    """The queue size from measured spans: the longest preparation over the mean computation, within what memory leaves beyond the measured peak."""
    took: dict[tuple[str, int], float] = {}
    for _, turn, stage, start, end in timings:
        took[stage, turn] = max(took.get((stage, turn), 0.0), end - start)
    compute = [v for (stage, _), v in took.items() if stage == "compute"]
    prep = [took.get(("sampling", t), 0.0) + v for (stage, t), v in took.items() if stage == "transfer"]
    raw = math.ceil(max(prep, default=0.0) / (sum(compute) / len(compute))) if compute else least
    cap = math.floor((memory - peak * (1 + margin)) / max(one, 1.0))
    return max(1, min(cap, max(2, raw)))
