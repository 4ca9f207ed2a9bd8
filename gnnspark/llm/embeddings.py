"""Embedding near-duplicates: Euclidean p-stable hashing with exact cosine checks.

Vectors are normalised, so a cosine bound is a bound on Euclidean distance. Each table hashes a vector by ``projections`` random
directions, shifted and cut into cells of ``width``; vectors in one bucket of any table are candidates, and the cosine in double precision decides. Equal
vectors of a label are one node with a multiplicity. Buckets of any size are compared in bounded units (:mod:`blockpairs`); a pair counts in the first table in which it meets,
so every found link counts once without any pair being emitted.

With the defaults a pair at cosine 0.98 meets with probability 0.995, at 0.99 with 0.9999. ``projections`` should grow with
the logarithm of the rows for a label, ``tables`` with it.

Defined results: a null label, a null, zero or non-finite vector, null components, or a null id links with nothing; repeated rows are vectors of
their own and link to each other; vectors of another length than the first valid one hash in a family of their own length; an empty table gives no rows. Only the named
columns are read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .blockpairs import Forest, candidate_pairs, dealt, shared_buckets, whole_units
from .components import connected_components
from .state import checkpointed


class PStable:
    """Tables of quantised random projections for vectors of one length."""

    def __init__(self, dim: int, tables: int, projections: int, width: float, seed: int):
        rng = np.random.default_rng([seed, dim])
        self.a = rng.standard_normal((dim, tables * projections))
        self.b = rng.uniform(0, width, tables * projections)
        self.mix = rng.integers(1, 2**62, projections, dtype=np.int64) * 2 + 1
        self.width, self.tables, self.projections = width, tables, projections

    def codes(self, unit: np.ndarray) -> np.ndarray:
        """(rows, tables): 64-bit hashes of the cells."""
        cells = np.floor((unit @ self.a + self.b) / self.width).astype(np.int64)
        with np.errstate(over="ignore"):
            mixed = (cells.reshape(len(unit), self.tables, self.projections) * self.mix).sum(2)
            return mixed ^ (mixed >> 29) ^ np.arange(self.tables, dtype=np.int64) * np.int64(0x9E3779B97F4A7C15 - 2**64)


def unit_rows(vectors: list) -> np.ndarray:
    x = np.array(vectors, np.float64)
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def valid(vector, label, id_col):
    """Whether a vector can link at all."""
    v = F.col(vector)
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return F.coalesce(F.col(id_col).isNotNull() & F.col(label).isNotNull() & finite & F.exists(v, lambda x: x != 0), F.lit(False))


def near_duplicates(rows: DataFrame, id_col: str = "vec_id", vector: str = "embedding", label: str = "label", cosine: float = 0.98, tables: int = 16, projections: int = 12, width: float = 1.6, seed: int = 17) -> DataFrame:
    """(vec_id, n_links, component_id, kept) for every row."""
    kept = rows.select(F.col(id_col).alias("vec_id"), F.col(vector).cast("array<double>").alias("v"), F.col(label).alias("label"), valid(vector, label, id_col).alias("ok"))
    nodes = checkpointed(kept.where("ok").groupBy("label", "v").agg(F.min("vec_id").alias("node"), F.count("*").alias("copies")))

    def hashed(batches):
        family: dict[int, PStable] = {}
        for batch in batches:
            vectors, out = batch.column(2).to_pylist(), [b""] * batch.num_rows
            by_dim: dict[int, list[int]] = {}
            for i, v in enumerate(vectors):
                by_dim.setdefault(len(v), []).append(i)
            for dim, at in by_dim.items():
                if dim not in family:
                    family[dim] = PStable(dim, tables, projections, width, seed)
                codes = family[dim].codes(unit_rows([vectors[i] for i in at])) ^ np.int64(dim)
                for i, row in zip(at, codes):
                    out[i] = row.tolist()
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), batch.column(3), pa.array(out, pa.list_(pa.int64()))], names=["node", "copies", "v", "label", "codes"])

    schema = nodes.select("node", "copies", "v", "label").withColumn("codes", F.array(F.lit(0).cast("long"))).schema
    coded = checkpointed(nodes.select("node", "copies", "v", "label").mapInArrow(hashed, schema))
    keyed = coded.select("node", "label", F.posexplode("codes").alias("t", "code")).select("node", "t", F.xxhash64("label", "t", "code").alias("key"))
    members = shared_buckets(keyed).join(coded.select("node", "copies", "v", "codes"), "node")
    units = dealt(members, F.col("node"))

    def compared(batches):
        for table, starts in whole_units(batches):
            node, copies, t = (table.column(c).to_numpy() for c in ("node", "copies", "t"))
            place = [table.column(c).to_numpy() for c in ("bi", "bj", "own")]
            vectors = table.column("v").combine_chunks()
            lengths = np.diff(vectors.offsets.to_numpy())
            flat, at = vectors.flatten().to_numpy(), np.concatenate([[0], np.cumsum(lengths)])
            codes = table.column("codes").combine_chunks().flatten().to_numpy().reshape(len(node), tables)
            dim = lengths.max()
            if (lengths == dim).all():
                unit = unit_rows(flat.reshape(len(node), dim))
            else:
                unit = np.zeros((len(node), dim))
                for i in range(len(node)):
                    unit[i, : lengths[i]] = unit_rows([flat[at[i] : at[i + 1]]])[0]
            forest, found = Forest(len(node)), np.zeros(len(node), np.int64)
            for a, b in candidate_pairs(starts, len(node), *place):
                for i in range(0, len(a), 65_536):
                    x, y = a[i : i + 65_536], b[i : i + 65_536]
                    near = (np.einsum("ij,ij->i", unit[x], unit[y]) >= cosine) & (node[x] != node[y]) & (lengths[x] == lengths[y])
                    x, y = x[near], y[near]
                    same = codes[x] == codes[y]
                    first = same.any(1) & (same.argmax(1) == t[x])
                    x, y = x[first], y[first]
                    np.add.at(found, x, copies[y])
                    np.add.at(found, y, copies[x])
                    forest.link(x, y)
            rows_, to = forest.edges()
            least = np.zeros(len(node), np.int64)
            least[:] = node
            least[rows_] = node[to]
            some = np.flatnonzero((found > 0) | (least != node))
            yield pa.RecordBatch.from_arrays([pa.array(node[some]), pa.array(found[some]), pa.array(least[some])], names=["node", "found", "other"])

    told = checkpointed(units.mapInArrow(compared, "node long, found long, other long"))
    sums = told.groupBy("node").agg(F.sum("found").alias("found"))
    label_of = connected_components(told, "node", "other")
    ready = (
        coded.select("node", "copies", F.col("v").alias("__v"), F.col("label").alias("__label"))
        .join(sums, "node", "left")
        .join(label_of.withColumnRenamed("node", "n2"), F.col("node") == F.col("n2"), "left")
        .select("__v", "__label", (F.col("copies") - 1 + F.coalesce("found", F.lit(0))).alias("n_links"), F.coalesce("component", "node").alias("component_id"))
    )
    joined = kept.join(ready, F.col("ok") & (F.col("label") == F.col("__label")) & (F.col("v") == F.col("__v")), "left")
    component = F.coalesce("component_id", "vec_id")
    return joined.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))
