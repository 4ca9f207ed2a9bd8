"""Batches made where they are trained: a graph of bounded size lies as arrays in the shared folder, and a task samples each batch when its runs need it.

The batches are those of :func:`batches.sampled` and :func:`batches.package`: the same seeds, the same hashes, the same weights. Nothing of a batch is written, and epochs after an
early stop are never sampled. Arrays are written by many tasks in pieces and put together by one; readers map them from a local folder, or read them from elsewhere.
Graphs beyond the bounds take the distributed plans.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import xxhash
from ..functions.md5 import pair_bits
from ..operators import kernels, layerwise
from ..operators.propagation import with_self_loops
from ..sources.graphs import Graph
from ..sources.spool import piece as _array
from ..sources.spool import put as _written
from ..sources.spool import store as _store
from .batches import NODE_WISE, Ids, Sizes, Stream

#: Most entries of the operator (4 bytes each), nodes, and bytes of features of a graph that lies in arrays.
ENTRIES, NODES, FEATURE_BYTES = 200_000_000, 4_000_000, 400_000_000
PIECE = 1_000_000
SPLITS = ("train", "val", "test")
ARRAYS = {"ids": "<i8", "degree": "<i4", "start": "<i8", "cols": "<i4", "mass": "<f8", "y": "<i4", "split": "<i1", "cached": "<i1", "place": "<i4", "features": "<f4"}


def _told(**columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_pydict(columns)


def _sorted_ids(folder: str):
    """One task: the distinct ids of all nodes in order."""

    def go(parts):
        held = [p.column("node_id").to_numpy() for p in parts if p.num_rows]
        ids = np.unique(np.concatenate(held)) if held else np.zeros(0, np.int64)
        yield _told(name=[_written(folder, ids.astype("<i8"))], k=[len(ids)], n=[0])

    return go


def _entry_piece(folder: str, ids_file: str, nodes: int):
    """Entries (row, col) of a task to files of bounded size: rows, their sizes, and the columns by row, all as places of nodes. ``n`` is -1 if an end is no node."""

    def piece(held):
        ids = _array(folder, ids_file, "<i8", nodes)
        row, col = (kernels.index_of(np.concatenate(x), ids) for x in zip(*held))
        if min(row.min(), col.min()) < 0:
            return _told(name=[""], k=[0], n=[-1])
        order = np.argsort(row, kind="stable")
        rows, sizes = np.unique(row, return_counts=True)
        return _told(name=[_written(folder, rows.astype("<i4"), sizes.astype("<i4"), col[order].astype("<i4"))], k=[len(rows)], n=[len(col)])

    def go(parts):
        held, n = [], 0
        for p in parts:
            if p.num_rows:
                held.append((p.column("row").to_numpy(), p.column("col").to_numpy()))
                n += p.num_rows
            if n >= PIECE:
                yield piece(held)
                held, n = [], 0
        if held:
            yield piece(held)

    return go


def _feature_piece(folder: str):
    """Features (node_id, f) of a task to one file: ids and rows. ``n``: the width, -1 if rows differ in it."""

    def go(parts):
        for p in parts:
            if p.num_rows:
                f = p.column("f")
                values, k = f.flatten().to_numpy(zero_copy_only=False).astype("<f4"), p.num_rows
                wide = np.unique(f.value_lengths().to_numpy(zero_copy_only=False))
                yield _told(name=[_written(folder, p.column("node_id").to_numpy().astype("<i8"), values)], k=[k], n=[int(wide[0]) if len(wide) == 1 else -1])

    return go


def _assembled(folder: str, ids_file: str, nodes: int, entries: list, features: list):
    """One task: all arrays from the pieces and from (node_id, y, split) of labelled and cached nodes. Tells the number of nodes, entries and feature rows; not whole if some id occurs twice or feature rows differ in width."""

    def go(parts):
        table = [[p.column(c).to_numpy(zero_copy_only=False) for c in ("node_id", "y", "split")] for p in parts if p.num_rows]
        node, y, split = (np.concatenate(x) for x in zip(*table)) if table else (np.zeros(0, np.int64),) * 3
        piece = lambda name, k, n: (_array(folder, name, "<i4", k), _array(folder, name, "<i4", k, 4 * k), _array(folder, name, "<i4", n, 8 * k))
        ids = np.array(_array(folder, ids_file, "<i8", nodes))
        degree, mass = np.zeros(len(ids), np.int64), np.zeros((2, len(ids)))
        for e in entries:
            rows, sizes, _ = piece(*e)
            degree[rows] += sizes
        start, at = np.cumsum(degree) - degree, int(degree.sum())
        free, whole, store_path = start.copy(), True, _store(folder)
        cols = np.memmap(f"{store_path[1]}/cols", "<i4", "w+", shape=(at,)) if at and isinstance(store_path[0], fs.LocalFileSystem) else np.zeros(at, "<i4")
        for e in entries:
            rows, sizes, col = piece(*e)
            cols[np.arange(len(col)) + np.repeat(free[rows] - np.cumsum(sizes, dtype=np.int64) + sizes, sizes)] = col
            free[rows] += sizes
            mass[0] += np.bincount(col, np.repeat(1.0 / degree[rows], sizes), len(ids))
        if not isinstance(cols, np.memmap):
            with store_path[0].open_output_stream(f"{store_path[1]}/cols") as out:
                out.write(cols.tobytes())
        mass[0] /= np.maximum(degree, 1)
        mass[1] = np.sqrt(mass[0])
        mass /= np.maximum(mass.sum(1, keepdims=True), 1e-300)
        place, n = np.full(len(ids), -1, "<i4"), 0
        with store_path[0].open_output_stream(f"{store_path[1]}/features") as out:
            for name, k, wide in features:
                i, own = kernels.index_of(np.asarray(_array(folder, name, "<i8", k)), ids), np.arange(k)
                whole &= wide == features[0][2] and len(np.unique(i[i >= 0])) == (i >= 0).sum() and bool((place[i[i >= 0]] < 0).all())
                place[i[i >= 0]] = n + own[i >= 0]
                out.write(_array(folder, name, "<f4", k * max(wide, 0), 8 * k).tobytes())
                n += k
        i, known = kernels.index_of(node, ids), split < 3
        whole &= bool((i >= 0).all()) and len(np.unique(i[known])) == known.sum()
        told = {"ids": ids, "degree": degree, "start": start, "mass": mass, "place": place}
        told |= {"y": np.full(len(ids), -1, "<i4"), "split": np.full(len(ids), -1, "<i1"), "cached": np.zeros(len(ids), "<i1")}
        if whole:
            told["y"][i[known]], told["split"][i[known]], told["cached"][i[~known]] = y[known], split[known], 1
        for name, v in told.items():
            with store_path[0].open_output_stream(f"{store_path[1]}/{name}") as out:
                out.write(np.ascontiguousarray(v.astype(ARRAYS[name])).tobytes())
        for name, *_ in [(ids_file,), *entries, *features]:
            store_path[0].delete_file(f"{store_path[1]}/{name}")
        yield _told(whole=[whole], nodes=[len(ids)], entries=[at], rows=[n])

    return go


@dataclass(frozen=True)
class Arrays:
    """Where a graph's arrays lie, and how long they are."""

    folder: str
    nodes: int
    entries: int
    rows: int
    width: int


def fits(g: Graph, width: int) -> bool:
    """Whether a graph, its tables being kept, is small enough."""
    n = g.nodes.count()
    return n <= NODES and 4 * n * width <= FEATURE_BYTES and n + g.edges.count() <= ENTRIES


def arrays(g: Graph, known: DataFrame, cache: DataFrame | None, features: DataFrame, folder: str, most: int | None = None) -> Arrays | None:
    """The arrays of a graph below ``folder``; none where an edge ends at no node, labels or features of an id occur twice or feature rows differ in width, or where there are more than ``most`` entries, which takes the plans' joins."""
    told = "name string, k long, n long"
    ids = g.nodes.select(F.col("node_id").cast("long")).repartition(1).mapInArrow(_sorted_ids(folder), told).first()
    if ids is None:
        return None
    entries = [tuple(r) for r in with_self_loops(g).mapInArrow(_entry_piece(folder, ids["name"], ids["k"]), told).collect()]
    if any(n < 0 for *_, n in entries) or (most is not None and sum(n for *_, n in entries) > most):
        return None
    held = features.where("f is not null").select(F.col("node_id").cast("long"), "f")
    pieces = [tuple(r) for r in held.mapInArrow(_feature_piece(folder), told).collect()]
    code = F.when(F.col("split") == "train", 0).when(F.col("split") == "val", 1).otherwise(2)
    nodes = known.select(F.col("node_id").cast("long"), F.col("y").cast("long"), code.alias("split"))
    if cache is not None:
        nodes = nodes.union(cache.select(F.col("node_id").cast("long"), F.lit(0).cast("long"), F.lit(3)))
    one = nodes.union(nodes.sparkSession.range(0).select(F.col("id"), F.col("id"), F.lit(0))).repartition(1)
    made = one.mapInArrow(_assembled(folder, ids["name"], ids["k"], entries, pieces), "whole boolean, nodes long, entries long, rows long").first()
    if made is None or not made["whole"]:
        return None
    return Arrays(folder, made["nodes"], made["entries"], made["rows"], pieces[0][2] if pieces else 0)


class Row:
    """A packaged batch; its compact form is made once for all runs that read it."""

    def __init__(self, *columns):
        self.seeds, self.y, self.layer, self.dst, self.src, self.w, self.inputs, self.x = columns
        self.made = kernels.Batch.of(*columns)


class Sampler:
    """The batches of all streams from the arrays of a graph."""

    def __init__(self, a: Arrays, streams: list[Stream], sizes: Sizes, seed: int = 7):
        long = {"cols": a.entries, "mass": 2 * a.nodes, "features": a.rows * a.width}
        for name, kind in ARRAYS.items():
            setattr(self, name, np.asarray(_array(a.folder, name, kind, long.get(name, a.nodes))))
        self.mass, self.features = self.mass.reshape(2, -1), self.features.reshape(-1, max(1, a.width))
        self.ids, self.degree, self.start = np.array(self.ids), np.array(self.degree), np.array(self.start)
        self.streams, self.sizes, self.seed, self.width = streams, sizes, seed, a.width
        self.root, self.at, self.links = 1.0 / np.sqrt(np.maximum(self.degree, 1)), np.full(a.nodes, -1, np.int32), np.full(a.nodes, -1, np.int64)
        self.part, self.of_split = xxhash.long_part(self.ids), [np.flatnonzero(self.split == i) for i in range(3)]
        self.n = [max(1, -(-len(v) // sizes.batch)) for v in self.of_split]
        self.id_form = Ids(sizes.epochs, max([n for n, v in zip(self.n, self.of_split) if len(v)], default=1))
        self.supports, self.limits = [np.flatnonzero(m > 0) for m in self.mass], {}

    def batches(self, stream: int, epoch: int) -> Iterator[Row]:
        """The batches of an epoch in order of their ids; epoch ``epochs`` holds the validation, the next one the test."""
        split = max(0, epoch - self.sizes.epochs + 1)
        mine, s = self.of_split[split], self.streams[stream]
        bits = np.zeros(len(mine), np.uint32)
        for _, j, b in pair_bits([f"{s.seed}:batch:{epoch}:".encode()], [str(v).encode() for v in self.ids[mine].tolist()]):
            bits[j] = b[0]
        place = np.floor((bits + 0.5) / 4294967296.0 * self.n[split]).astype(np.int64)
        order = np.argsort(place, kind="stable")
        cuts = np.flatnonzero(np.diff(place[order])) + 1
        for lot in np.split(order, cuts) if len(order) else []:
            batch = (stream * (self.sizes.epochs + 2) + epoch) * self.id_form.width + int(place[lot[0]])
            row = self.batch(s, batch, mine[lot])
            if row:
                yield row

    def batch(self, s: Stream, batch: int, seeds: np.ndarray) -> Row | None:
        """Seeds are ascending places of nodes."""
        layer, dst, src, w, inputs = (self.node_wise if s.model in NODE_WISE else self.layer_wise)(s, batch, seeds)
        inputs = inputs[self.place[inputs] >= 0]
        if not len(inputs):
            return None
        order = np.lexsort((src, dst, layer))
        x = self.features[self.place[inputs]].astype(float)
        return Row(self.ids[seeds], self.y[seeds].astype(np.int64), layer[order], self.ids[dst[order]], self.ids[src[order]], w[order], self.ids[inputs], x)

    def entries(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(numbers of the rows' entries, columns one row after another)."""
        sizes, starts = self.degree[rows].astype(np.int64), self.start[rows]
        if sizes.sum() > 32 * len(rows):  # long rows are copied one by one
            return sizes, np.concatenate([self.cols[i:j] for i, j in zip(starts.tolist(), (starts + sizes).tolist())])
        return sizes, self.cols[np.arange(sizes.sum()) + np.repeat(starts - np.cumsum(sizes) + sizes, sizes)]

    def keys(self, batch: int, layer: int) -> np.ndarray:
        return xxhash.with_int(layer, xxhash.with_long(batch, xxhash.with_int(0, xxhash.with_int(self.seed, xxhash.START))))

    def others(self, rows: np.ndarray) -> np.ndarray:
        """How many entries of the rows lead to other nodes."""
        new = rows[self.links[rows] < 0]
        if len(new):
            sizes, col = self.entries(new)
            self.links[new] = sizes - np.bincount(np.repeat(np.arange(len(new)), sizes)[col == np.repeat(new, sizes)], minlength=len(new))
        return self.links[rows]

    def early(self, s: Stream, rows: np.ndarray, heads: np.ndarray, most: np.ndarray):
        """(places in ``rows``, columns, uniforms, whether first) of the rows' entries to other nodes that go first or whose uniform is at most the row's ``most``."""
        bits, out, cuts = xxhash.most_hash(most), [], np.cumsum(self.degree[rows], dtype=np.int64) // (2 * xxhash.PIECE)
        for mine in np.split(np.arange(len(rows)), np.flatnonzero(np.diff(cuts)) + 1):  # pieces that stay in a core's cache
            sizes, col = self.entries(rows[mine])
            h = xxhash.with_part(self.part[col], np.repeat(heads[mine], sizes))
            near = h <= np.repeat(bits[mine], sizes)
            if s.cached:
                near |= self.cached[col] > 0
            near = np.flatnonzero(near)
            which, col, u = mine[np.searchsorted(np.cumsum(sizes), near, "right")], col[near], xxhash.uniforms(h[near])
            first = self.cached[col] > 0 if s.cached else np.zeros(len(col), bool)
            held = ((u <= most[which]) | first) & (col != rows[which])
            out.append((which[held], col[held], u[held], first[held]))
        return tuple(map(np.concatenate, zip(*out)))

    def node_wise(self, s: Stream, batch: int, seeds: np.ndarray):
        out, front = [], seeds
        for layer in (1, 0):
            d, heads = self.others(front), xxhash.with_part(self.part[front], self.keys(batch, layer))
            which, col, u, first = self.early(s, front, heads, np.minimum(4.0 * self.sizes.fanout / np.maximum(d, 1), 1.0))
            short = np.flatnonzero(np.bincount(which, minlength=len(front)) < np.minimum(d, self.sizes.fanout))
            if len(short):  # rows with too few are taken whole
                more = self.early(s, front[short], heads[short], np.ones(len(short)))
                left = ~np.isin(which, short)
                which, col, u, first = (np.concatenate([a[left], b]) for a, b in zip((which, col, u, first), (short[more[0]], *more[1:])))
            order = np.lexsort((col, u, ~first, which))
            sizes = np.bincount(which, minlength=len(front))
            rank = np.arange(len(order)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
            taken = order[rank < self.sizes.fanout]
            r, c = which[taken], col[taken]
            kept = np.bincount(r, minlength=len(front))
            if s.model == "graphsage":
                out.append((layer, front[r], c, 1.0 / kept[r]))
            else:
                out.append((layer, front[r], c, self.root[front[r]] * self.root[c] * d[r] / kept[r]))
                own = front[self.degree[front] > d]
                out.append((layer, own, own, self.root[own] ** 2))
            front = np.unique(np.concatenate([front, c]))
        return *self.joined(out), front

    def layer_wise(self, s: Stream, batch: int, seeds: np.ndarray):
        base, flat, debias = layerwise.VARIANTS[s.model]
        out, rows, size = [], seeds, self.sizes.layer
        for layer in (1, 0):
            sizes, col = self.entries(rows)
            if base == "fastgcn":
                pool, n, p, u = self.raced(int(flat), size, self.keys(batch, layer))
            else:
                q = np.bincount(col, np.repeat(1.0 / self.degree[rows], sizes), len(self.ids))
                pool = np.flatnonzero(q)
                q = q[pool] / self.degree[pool]
                q = np.sqrt(q) if flat else q
                p, n, u = q / q.sum(), len(pool), xxhash.uniforms(xxhash.with_part(self.part[pool], self.keys(batch, layer)))
            key = -np.log(u) / p
            if len(key) > 4 * size:
                near = np.flatnonzero(key <= np.partition(key, size - 1)[size - 1])
                pool, p, key = pool[near], p[near], key[near]
            order = np.lexsort((pool, key))[:size]
            chosen, p = pool[order], p[order]
            coef = debiased(p, n) if debias else 1.0 / (len(p) * p)
            self.at[chosen] = np.arange(len(chosen))
            at = self.at[col]
            self.at[chosen] = -1
            held = np.flatnonzero(at >= 0)
            r, c = np.searchsorted(np.cumsum(sizes), held, "right"), at[held]
            w = self.root[rows[r]] * self.root[chosen[c]] * coef[c]
            if base == "ladies" and not debias:
                w = w / np.bincount(r, w, len(rows))[r]
            out.append((layer, rows[r], chosen[c], w))
            rows = chosen
        return *self.joined(out), np.sort(rows)

    def bounded(self, flat: int, size: int):
        """(support, p, least uniform, its hash, hash parts) of FastGCN's race, made once: ``size`` keys all but surely have a uniform of ``least`` or more; none if hardly any node has less."""
        if flat not in self.limits:
            pool = self.supports[flat]
            p = self.mass[flat][pool]
            most = next((t for t in (size * 1.1**k for k in range(1, 73)) if (1 - np.exp(-p * t)).sum() >= size + 8 * math.sqrt(size) + 16), None)
            least = None if most is None else np.exp(-p * most)
            self.limits[flat] = pool, p, least, None if most is None else xxhash.least_hash(least), self.part[pool]
        return self.limits[flat]

    def raced(self, flat: int, size: int, head: np.ndarray):
        """(nodes, support, p, u) of FastGCN's race: those whose keys lie below a bound that ``size`` keys all but surely do, or all nodes."""
        pool, p, least, bits, part = self.bounded(flat, size)
        if least is not None:
            near, h = xxhash.reaching(part, head, bits)
            u = xxhash.uniforms(h)
            held = u >= least[near]
            if held.sum() >= size:
                near = near[held]
                return pool[near], len(pool), p[near], u[held]
        return pool, len(pool), p, xxhash.uniforms(xxhash.with_part(part, head))

    @staticmethod
    def joined(parts: list) -> tuple[np.ndarray, ...]:
        layer = np.concatenate([np.full(len(p[1]), p[0]) for p in parts])
        return layer, *(np.concatenate([p[i] for p in parts]) for i in (1, 2, 3))


def debiased(p: np.ndarray, n: int) -> np.ndarray:
    """The weights of :func:`draws.debias_weights` for draws in order."""
    s, j = len(p), np.arange(1.0, len(p) + 1)
    if s >= n:
        return np.ones(s)
    q = p / np.maximum(1 - (np.cumsum(p) - p), 1e-12)
    return n * (n - s) / (s * (n - j) * (n - j + 1)) / q + n * (s - j) / (s * (n - j))
