"""The two-layer networks per batch in numpy: forward, loss, gradients, optimisers. Same results as :mod:`model`."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np


@dataclass
class Batch:
    """Compact indices: ``inner`` and ``outer`` are (rows, cols, w) into inputs and hidden nodes; ``own`` places of each row among its columns (-1: none)."""

    x: np.ndarray
    inner: tuple[np.ndarray, np.ndarray, np.ndarray]
    outer: tuple[np.ndarray, np.ndarray, np.ndarray]
    hidden: int
    y: np.ndarray
    own_inner: np.ndarray
    own_outer: np.ndarray

    @classmethod
    def of(cls, seeds: np.ndarray, y: np.ndarray, layer: np.ndarray, dst: np.ndarray, src: np.ndarray, w: np.ndarray, inputs: np.ndarray, x: np.ndarray) -> "Batch":
        """From packaged columns: seeds and inputs are ascending ids, edges of layer 0 lead to the hidden nodes and those of layer 1 to the seeds.

        Edges from nodes without features and to nodes that are not seeds are left out.
        """
        hidden = np.unique(np.concatenate([dst[layer == 0], src[layer == 1], seeds]))
        return cls(x.reshape(len(inputs), -1), places(layer == 0, dst, src, w, hidden, inputs), places(layer == 1, dst, src, w, seeds, hidden), len(hidden), y, index_of(hidden, inputs), index_of(seeds, hidden))


def index_of(ids: np.ndarray, among: np.ndarray) -> np.ndarray:
    """Places of ``ids`` in the ascending array ``among``; -1 where absent."""
    if not len(among):
        return np.full(len(ids), -1)
    at = np.minimum(np.searchsorted(among, ids), len(among) - 1)
    return np.where(among[at] == ids, at, -1)


def places(of_layer: np.ndarray, dst: np.ndarray, src: np.ndarray, w: np.ndarray, rows: np.ndarray, cols: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    r, c = index_of(dst[of_layer], rows), index_of(src[of_layer], cols)
    held = (r >= 0) & (c >= 0)
    return r[held], c[held], w[of_layer][held]


def summed(at: np.ndarray, values: np.ndarray, rows: int) -> np.ndarray:
    """Sums of ``values`` by row number, one pass over sorted rows."""
    out = np.zeros((rows, values.shape[1]))
    if len(at):
        order = np.argsort(at, kind="stable")
        starts = np.flatnonzero(np.diff(at[order], prepend=-1))
        out[at[order][starts]] = np.add.reduceat(values[order], starts, axis=0)
    return out


def dense(coo, rows: int, cols: int) -> np.ndarray | None:
    """The entries as a matrix, where a product with it is less work than one row of values an entry."""
    r, c, w = coo
    return np.bincount(r * cols + c, w, rows * cols).reshape(rows, cols) if 0 < rows * cols <= 16 * len(r) else None


def spread(coo, h: np.ndarray, rows: int) -> np.ndarray:
    m = dense(coo, rows, len(h))
    if m is not None:
        return m @ h
    r, c, w = coo
    return summed(r, w[:, None] * h[c], rows)


def collect(coo, g: np.ndarray, cols: int) -> np.ndarray:
    m = dense(coo, len(g), cols)
    if m is not None:
        return m.T @ g
    r, c, w = coo
    return summed(c, w[:, None] * g[r], cols)


def picked(h: np.ndarray, own: np.ndarray) -> np.ndarray:
    return np.where(own[:, None] >= 0, h[np.maximum(own, 0)], 0.0)


def forward(b: Batch, params: list[np.ndarray], sage: bool = False) -> dict[str, np.ndarray]:
    a1 = spread(b.inner, b.x, b.hidden)
    if sage:
        a1 = np.hstack([a1, picked(b.x, b.own_inner)])
    z1 = a1 @ params[0]
    h1 = np.maximum(z1, 0)
    a2 = spread(b.outer, h1, len(b.y))
    if sage:
        a2 = np.hstack([a2, picked(h1, b.own_outer)])
    z2 = a2 @ params[1]
    e = np.exp(z2 - z2.max(1, keepdims=True))
    return {"a1": a1, "z1": z1, "h1": h1, "a2": a2, "p": e / e.sum(1, keepdims=True)}


def loss_and_gradients(b: Batch, params: list[np.ndarray], sage: bool = False) -> tuple[float, list[np.ndarray]]:
    """Mean cross-entropy of the batch and its gradients."""
    f, n = forward(b, params, sage), len(b.y)
    loss = float(-np.log(np.maximum(f["p"][np.arange(n), b.y], 1e-12)).mean())
    g2 = f["p"].copy()
    g2[np.arange(n), b.y] -= 1
    g2 /= n
    back = g2 @ params[1].T
    width = f["h1"].shape[1]
    dh = collect(b.outer, back[:, :width], b.hidden)
    if sage:
        held = b.own_outer >= 0
        dh += summed(b.own_outer[held], back[held, width:], b.hidden)
    g1 = dh * (f["z1"] > 0)
    return loss, [f["a1"].T @ g1, f["a2"].T @ g2]


@dataclass
class Adam:
    rate: float = 0.001
    t: int = 0
    m: list[np.ndarray] = field(default_factory=list)
    v: list[np.ndarray] = field(default_factory=list)

    def step(self, params: list[np.ndarray], grads: list[np.ndarray]) -> list[np.ndarray]:
        self.t += 1
        if not self.m:
            self.m, self.v = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params]
        out = []
        for i, (p, g) in enumerate(zip(params, grads)):  # new arrays: copies of an optimiser share theirs
            self.m[i] = 0.9 * self.m[i] + 0.1 * g
            self.v[i] = 0.999 * self.v[i] + 0.001 * g * g
            out.append(p - self.rate * (self.m[i] / (1 - 0.9**self.t)) / (np.sqrt(self.v[i] / (1 - 0.999**self.t)) + 1e-8))
        return out


def init(dims: tuple[int, ...], sage: bool = False, seed: int = 7) -> list[np.ndarray]:
    """Uniform in +-sqrt(6/(fan in + fan out)) from md5 of the place, as in the rows form."""
    import hashlib

    out = []
    for layer, (a, c) in enumerate(zip(dims, dims[1:]), 1):
        a = 2 * a if sage else a
        u = [(int(hashlib.md5(f"{seed}:w:{layer}:{i}:{j}".encode()).hexdigest()[:8], 16) + 0.5) / 4294967296 for i in range(a) for j in range(c)]
        out.append((2 * np.array(u).reshape(a, c) - 1) * (6 / (a + c)) ** 0.5)
    return out
