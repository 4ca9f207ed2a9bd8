"""Comparing the members of buckets of any size without emitting a bucket's pairs.

A bucket is cut into blocks by a hash of the member. Every pair of blocks is one bounded unit of work, dealt out by (bucket, block,
block); the unit compares its members in numpy and returns a spanning forest of the links that it found, or sums per member. A
member is sent once for each block of its bucket, so a bucket of thousands costs many small units in many tasks and never meets
in one.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLOCK = 512
SMALL = 8


def shared_buckets(keys: DataFrame, key: str = "key") -> DataFrame:
    """The rows of ``keys`` whose bucket has two members or more, with ``bucket_size``. Counts combine before the shuffle."""
    counts = keys.groupBy(key).agg(F.count("*").alias("bucket_size")).where("bucket_size > 1")
    return keys.join(counts, key)


def dealt(members: DataFrame, node: Column, key: str = "key", block: int = BLOCK) -> DataFrame:
    """Send each member to the units of its block: adds ``bi <= bj`` and ``own``, ordered by unit within partitions."""
    n = F.ceil(F.col("bucket_size") / block).cast("int")
    placed = members.withColumn("__n", n).withColumn("own", F.when(F.col("__n") > 1, F.pmod(F.xxhash64(node, F.lit(5)), F.col("__n")).cast("int")).otherwise(0))
    sent = placed.withColumn("__o", F.explode(F.sequence(F.lit(0), F.col("__n") - 1)))
    units = sent.withColumns({"bi": F.least("own", "__o"), "bj": F.greatest("own", "__o")}).drop("__n", "__o", "bucket_size")
    return units.repartition(key, "bi", "bj").sortWithinPartitions(key, "bi", "bj")


def whole_units(batches: Iterator[pa.RecordBatch], key: str = "key") -> Iterator[tuple[pa.Table, np.ndarray]]:
    """Tables that end where a unit ends, and the row at which each unit starts."""
    rest: pa.Table | None = None

    def cut(table: pa.Table) -> np.ndarray:
        cols = [table.column(c).to_numpy() for c in (key, "bi", "bj")]
        new = np.zeros(len(table), bool)
        new[:1] = True
        for c in cols:
            new[1:] |= c[1:] != c[:-1]
        return np.flatnonzero(new)

    for batch in batches:
        table = pa.Table.from_batches([batch])
        table = table if rest is None else pa.concat_tables([rest, table]).combine_chunks()
        starts = cut(table) if len(table) else np.array([], int)
        if len(starts) > 1:
            yield table.slice(0, starts[-1]), starts[:-1]
            rest = table.slice(starts[-1])
        else:
            rest = table
    if rest is not None and len(rest):
        yield rest, cut(rest)


def candidate_pairs(starts: np.ndarray, total: int, bi: np.ndarray, bj: np.ndarray, own: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Row numbers (a, b) to compare: all small units together by distance, then each large unit in slabs of bounded size."""
    sizes = np.diff(np.append(starts, total))
    end_of = np.repeat(starts + sizes, sizes)
    small = np.repeat(sizes <= SMALL, sizes)
    rows = np.arange(total)
    allowed = lambda a, b: (bi[a] == bj[a]) | (own[a] != own[b])
    for step in range(1, SMALL):
        a = rows[small & (rows + step < end_of)]
        a = a[allowed(a, a + step)]
        if len(a):
            yield a, a + step
    for s, n in zip(starts[sizes > SMALL], sizes[sizes > SMALL]):
        if bi[s] == bj[s]:
            left = right = rows[s : s + n]
        else:
            unit = rows[s : s + n]
            left, right = unit[own[unit] == bi[s]], unit[own[unit] != bi[s]]
        slab = max(1, 262_144 // max(1, len(right)))
        for i in range(0, len(left), slab):
            a, b = np.repeat(left[i : i + slab], len(right)), np.tile(right, len(left[i : i + slab]))
            if bi[s] == bj[s]:
                a, b = a[a < b], b[a < b]
            yield a, b


class Forest:
    """Union-find over row numbers; keeps a spanning forest of the links of a table."""

    def __init__(self, n: int):
        self.label = np.arange(n)

    def link(self, a: np.ndarray, b: np.ndarray) -> None:
        """Merge along many links at once: labels fall to the least linked label until none changes."""
        label = self.label
        while True:
            la, lb = label[a], label[b]
            if (la == lb).all():
                return
            low = np.minimum(la, lb)
            np.minimum.at(label, la, low)
            np.minimum.at(label, lb, low)
            while True:
                jumped = label[label]
                if (jumped == label).all():
                    break
                label[:] = jumped

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        rows = np.flatnonzero(self.label != np.arange(len(self.label)))
        return rows, self.label[rows]
