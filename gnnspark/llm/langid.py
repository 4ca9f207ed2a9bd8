"""Language identification with a byte convolutional network, trained and applied in numpy.

A text is lower-cased and written in UTF-8; bytes that are neither ASCII letters nor part of a longer character become spaces. The bytes are cut
into windows of fixed length. A window runs through a byte embedding, convolutions of several widths, max
pooling over positions and a softmax; a document's score is the softmax of the byte-weighted mean of its windows' log
probabilities, so whole texts count.

Training uses a bounded sample: for every label the ``per_label`` rows of least hash, a few windows of each at hashed places. Only
chosen windows are shuffled and reach the driver. Labels are the values
seen in training; their number is that of the languages known.

Defined results: null text, or text without a letter, is ``und`` with score 0; without labelled rows every document is ``und``; repeated
rows each get a result; an empty table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

UNKNOWN = "und"
LETTER = re.compile(r"[^\W\d_]")
_KEEP = bytes(b + 32 if 65 <= b <= 90 else b if 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
RUNS = re.compile(b"  +")


def text_bytes(text: str) -> bytes:
    return RUNS.sub(b" ", text.lower().encode("utf-8", "replace").translate(_KEEP))


@dataclass
class ByteCnn:
    labels: list[str]
    window: int = 256
    widths: tuple[int, ...] = (2, 3, 4)
    filters: int = 16
    dim: int = 8
    params: dict[str, np.ndarray] = field(default_factory=dict)

    def start(self, seed: int) -> None:
        rng = np.random.default_rng(seed)
        draw = lambda *shape, scale: (rng.standard_normal(shape) * scale).astype(np.float32)
        self.params = {"e": draw(256, self.dim, scale=0.5), "o": draw(self.filters * len(self.widths), len(self.labels), scale=0.2), "c": np.zeros(len(self.labels), np.float32)}
        for w in self.widths:
            self.params |= {f"w{w}": draw(w * self.dim, self.filters, scale=(1 / (w * self.dim)) ** 0.5), f"b{w}": np.zeros(self.filters, np.float32)}

    def tables(self) -> list[tuple[int, np.ndarray]]:
        """(offset, 256 x filters) per width and offset: an embedding times its slice of the filter, so a convolution is a sum of looked-up rows."""
        p, d = self.params, self.dim
        return [(w, [p["e"] @ p[f"w{w}"][j * d : (j + 1) * d] for j in range(w)]) for w in self.widths]

    def _columns(self, emb: np.ndarray, w: int) -> np.ndarray:
        n, length, d = emb.shape
        return np.lib.stride_tricks.as_strided(emb, (n, length - w + 1, w * d), emb.strides[:2] + (emb.strides[2],), writeable=False)

    def pooled(self, x: np.ndarray, keep: bool = False):
        emb = np.ascontiguousarray(self.params["e"][x])
        out, memo = [], []
        for w in self.widths:
            cols = self._columns(emb, w)
            conv = (cols.reshape(-1, w * self.dim) @ self.params[f"w{w}"]).reshape(len(x), -1, self.filters)
            if keep:
                at = conv.argmax(1)
                memo.append((cols, at))
                top = np.take_along_axis(conv, at[:, None], 1)[:, 0]
            else:
                top = conv.max(1)
            out.append(np.maximum(top + self.params[f"b{w}"], 0))
        return np.concatenate(out, 1), memo

    def log_probs(self, x: np.ndarray) -> np.ndarray:
        h, _ = self.pooled(x)
        z = h @ self.params["o"] + self.params["c"]
        z -= z.max(1, keepdims=True)
        return z - np.log(np.exp(z).sum(1, keepdims=True))

    def gradients(self, x: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        p, n = self.params, len(x)
        h, memo = self.pooled(x, keep=True)
        z = h @ p["o"] + p["c"]
        z = np.exp(z - z.max(1, keepdims=True))
        g = z / z.sum(1, keepdims=True)
        g[np.arange(n), y] -= 1
        g /= n
        out = {"o": h.T @ g, "c": g.sum(0), "e": np.zeros_like(p["e"])}
        back = (g @ p["o"].T) * (h > 0)
        for i, (w, (cols, at)) in enumerate(zip(self.widths, memo)):
            gw = back[:, i * self.filters : (i + 1) * self.filters]
            seen = cols[np.arange(n)[:, None], at]
            out[f"w{w}"] = np.einsum("nfk,nf->kf", seen, gw)
            out[f"b{w}"] = gw.sum(0)
            into = gw[:, :, None] * p[f"w{w}"].T[None]
            bytes_ = x[np.arange(n)[:, None, None], at[:, :, None] + np.arange(w)]
            np.add.at(out["e"], bytes_.reshape(-1), into.reshape(-1, self.dim))
        return out

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 6, batch: int = 64, rate: float = 0.01, seed: int = 7) -> "ByteCnn":
        self.start(seed)
        rng = np.random.default_rng(seed)
        m = {k: np.zeros_like(v) for k, v in self.params.items()}
        v = {k: np.zeros_like(a) for k, a in self.params.items()}
        t = 0
        for _ in range(epochs):
            order = rng.permutation(len(x))
            for i in range(0, len(x), batch):
                t += 1
                for k, g in self.gradients(x[order[i : i + batch]], y[order[i : i + batch]]).items():
                    m[k] = 0.9 * m[k] + 0.1 * g
                    v[k] = 0.999 * v[k] + 0.001 * g * g
                    self.params[k] -= (rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
        return self

    def windows(self, data: bytes) -> np.ndarray:
        n = max(1, -(-len(data) // self.window))
        out = np.full(n * self.window, 32, np.uint8)
        out[: len(data)] = np.frombuffer(data, np.uint8)
        return out.reshape(n, self.window)

    def predict(self, texts: list[str | None], at_once: int = 256) -> tuple[list[str], list[float]]:
        """Labels and scores; a bounded number of windows is in memory whatever the texts' lengths."""
        total = np.zeros((len(texts), len(self.labels)))
        weight = np.zeros(len(texts))
        rows: list[np.ndarray] = []
        owner: list[np.ndarray] = []
        held = 0

        def flush():
            nonlocal rows, owner, held
            if not held:
                return
            x, of = np.concatenate(rows), np.concatenate(owner)
            for i in range(0, len(x), at_once):
                part, who = x[i : i + at_once], of[i : i + at_once]
                share = (part != 32).sum(1).astype(float)
                np.add.at(total, who, self.log_probs(part) * share[:, None])
                np.add.at(weight, who, share)
            rows, owner, held = [], [], 0

        known = []
        for i, text in enumerate(texts):
            ok = bool(self.labels) and text is not None and LETTER.search(text) is not None
            known.append(ok)
            if ok:
                w = self.windows(text_bytes(text))
                rows.append(w)
                owner.append(np.full(len(w), i))
                held += len(w)
                if held >= 4 * at_once:
                    flush()
        flush()
        names, scores = [], []
        for i, ok in enumerate(known):
            if not ok:
                names.append(UNKNOWN)
                scores.append(0.0)
                continue
            z = total[i] / max(weight[i], 1.0)
            z = np.exp(z - z.max())
            k = int(z.argmax())
            names.append(self.labels[k])
            scores.append(float(z[k] / z.sum()))
        return names, scores


def fold(id_col: Column) -> Column:
    """crc32 of the id as text, modulo 3; remainder 1 is held out."""
    return F.crc32(F.coalesce(id_col.cast("string"), F.lit("")).cast("binary")) % 3


def sample(docs: DataFrame, id_col: str, text: str, label: str, per_label: int, window: int, pieces: int) -> list[tuple[str, str]]:
    """At most ``per_label`` texts per label, ``pieces`` (label, piece of text) pairs of each, chosen by hash among the rows that are not held out.

    Labels are counted first; a hash threshold then leaves a little more than ``per_label`` rows of each before any are ranked, so a frequent label
    is no larger group than a rare one.
    """
    h = F.xxhash64(F.col(id_col).cast("string"), F.lit(11))
    usable = docs.select(h.alias("h"), F.col(label).alias("label"), F.col(text).alias("text"), fold(F.col(id_col)).alias("fold")).where("fold <> 1 and label is not null and text is not null")
    counts = {r["label"]: r["n"] for r in usable.groupBy("label").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return []
    share = {k: min(1.0, (per_label + 6 * per_label**0.5) / n) for k, n in counts.items()}
    limit = F.coalesce(*[F.when(F.col("label") == k, F.lit(min(2**63 - 1, int(-(2**63) + s * 2**64)))) for k, s in share.items()])
    places = F.transform(F.sequence(F.lit(0), F.lit(pieces - 1)), lambda i: F.pmod(F.shiftright("h", 8) + i * 7919, F.greatest(F.length("text") - 2 * window, F.lit(1)).cast("long")).cast("int") + 1)
    near = usable.where(F.col("h") <= limit).select("label", "h", F.transform(places, lambda at: F.substring(F.col("text"), at, F.lit(2 * window))).alias("cut"))
    ranked = near.withColumn("r", F.row_number().over(Window.partitionBy("label").orderBy("h", "cut"))).where(F.col("r") <= per_label)
    rows = ranked.select("label", "h", F.explode(F.array_distinct("cut")).alias("piece")).orderBy("h", "label", "piece")
    return [(r["label"], r["piece"]) for r in rows.collect()]


def train(docs: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "lang", per_label: int = 1000, window: int = 256, pieces: int = 2, seed: int = 7) -> ByteCnn:
    """Fit the network to at most ``per_label`` texts per label, ``pieces`` windows of each."""
    rows = [(k, p) for k, p in sample(docs, id_col, text, label, per_label, window, pieces) if LETTER.search(p)]
    model = ByteCnn(sorted({k for k, _ in rows}), window)
    if not rows:
        return model
    x = np.stack([model.windows(text_bytes(p))[0] for _, p in rows])
    y = np.array([model.labels.index(k) for k, _ in rows])
    return model.fit(x, y, epochs=max(3, min(40, 16_000 // len(x))), seed=seed)


def identify(docs: DataFrame, model: ByteCnn, text: str = "text", keep: tuple[str, ...] = ("doc_id",), names: tuple[str, str] = ("lang_pred", "score")) -> DataFrame:
    """The kept columns and the prediction. One pass, no shuffle; the model of a few tens of kilobytes travels with the task."""
    kept = docs.select(*[F.col(f"`{c}`") for c in keep], F.col(text).alias("__text"))
    schema = kept.drop("__text").withColumn(names[0], F.lit("")).withColumn(names[1], F.lit(0.0)).schema

    def apply(batches):
        for batch in batches:
            labels, scores = model.predict(batch.column(len(keep)).to_pylist())
            yield pa.RecordBatch.from_arrays([*[batch.column(i) for i in range(len(keep))], pa.array(labels, pa.string()), pa.array(scores, pa.float64())], names=[*keep, *names])

    return kept.mapInArrow(apply, schema)
