"""Exact nearest neighbours by blocks: vectors lie once in the shared folder, and the task of a block of queries reads all blocks of them one after another.

No pair of rows is emitted and nothing is shuffled; a task holds two blocks and the k best of its queries so far. The work is quadratic by nature. Products are in single
precision with a margin; what may be among the k best is measured again in double precision, each pair by itself, so equal vectors have equal cosines wherever they lie.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .spool import Spool, piece, put

#: More than the error of a cosine in single precision, for vectors of up to some thousand components.
MARGIN = 1e-4


def _written(folder: str, block: int):
    """Vectors of a task to files of at most ``block`` rows: ids, then unit vectors."""

    def go(parts):
        for part in parts:
            for p in (part.slice(i, block) for i in range(0, part.num_rows, block)):
                v = p.column("v")
                wide = np.unique(v.value_lengths().to_numpy(zero_copy_only=False))
                if len(wide) > 1:
                    raise ValueError(f"vectors of different lengths: {wide.tolist()}")
                x = v.flatten().to_numpy(zero_copy_only=False).reshape(p.num_rows, -1)
                x = x / np.linalg.norm(x, axis=1, keepdims=True)
                name = put(folder, p.column("vec_id").to_numpy().astype("<i8"), x.astype("<f8"))
                yield pa.RecordBatch.from_pydict({"name": [name], "n": [p.num_rows], "width": [int(wide[0])]})

    return go


def best(ids: np.ndarray, x: np.ndarray, blocks, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(rows, ids, cosines) of the ``k`` best of each row of ``x`` among ``blocks`` of (ids, vectors), those of the same id left out; by row, cosine downward and id."""
    row, other, cos = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    least, short = np.full(len(x), -np.inf), x.astype(np.float32)
    for base, y in blocks:
        near = short @ y.astype(np.float32).T
        near[ids[:, None] == base[None]] = -np.inf
        bar = least
        if len(base) > k and not np.isfinite(least).all():
            bar = np.maximum(least, np.partition(near, len(base) - k, axis=1)[:, len(base) - k])
        r, c = np.nonzero((near >= (bar - MARGIN).astype(np.float32)[:, None]) & (near > -np.inf))
        row, other, cos = np.concatenate([row, r]), np.concatenate([other, base[c]]), np.concatenate([cos, (x[r] * y[c]).sum(1)])
        order = np.lexsort((other, -cos, row))
        first = np.searchsorted(row[order], np.arange(len(x)))
        kept = order[np.arange(len(order)) - first[row[order]] < k]
        row, other, cos = row[kept], other[kept], cos[kept]
        full = np.flatnonzero(np.bincount(row, minlength=len(x)) == k)
        least[full] = cos[np.searchsorted(row, full, "right") - 1]
    return row, other, cos


def nearest(vectors: DataFrame, k: int, id_col: str = "vec_id", vector: str = "embedding", block: int = 1024) -> DataFrame:
    """(vec_id, neighbour, cosine): the ``k`` other vectors of largest cosine, ties by id. Null, zero and non-finite vectors have none."""
    spark, told = vectors.sparkSession, "vec_id long, neighbour long, cosine double"
    ok = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector).cast("array<double>").alias("v")).where("vec_id is not null and v is not null and forall(v, x -> x is not null and not isnan(x) and abs(x) < double('infinity')) and exists(v, x -> x <> 0)")
    folder = Spool(spark).folder
    files = [tuple(r) for r in ok.mapInArrow(_written(folder, block), "name string, n long, width long").collect()]
    if len({w for *_, w in files}) > 1:
        raise ValueError("vectors of different lengths")

    def held(name, n, width):
        return piece(folder, name, "<i8", n), piece(folder, name, "<f8", n * width, 8 * n).reshape(n, width)

    def go(parts):
        for pdf in parts:
            for i in pdf["id"]:
                ids, x = held(*files[i])
                row, other, cos = best(ids, x, (held(*f) for f in files), k)
                yield pd.DataFrame({"vec_id": ids[row], "neighbour": other, "cosine": cos})

    return spark.range(0, len(files), 1, max(1, len(files))).mapInPandas(go, told)
