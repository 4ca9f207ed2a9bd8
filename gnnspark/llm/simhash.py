"""SimHash near-duplicates: pigeonhole blocks, a join on blocks, and a check of the Hamming distance.

A fingerprint is a majority vote over the 64-bit hashes of a text's word shingles. Equal fingerprints are one node, so exact copies cost
nothing after the first aggregate. With at most ``bits`` differing bits and ``blocks`` blocks, close fingerprints agree on some ``blocks - bits`` blocks; every choice of that many
blocks is a table, fingerprints that share a key are candidates, and the exact distance decides. Buckets of any size are
compared in bounded units (:mod:`blockpairs`), so none is capped. Components come from :mod:`components`.

Defined results: null text has no words; a text without words has fingerprint zero and is linked like any other; fewer words than a
shingle make one shingle; repeated rows each get a result and are linked to each other; a null id takes part in links,
is never a component's name unless all ids of the component are null; an empty table gives no rows. Only the named columns are read.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .blockpairs import Forest, candidate_pairs, dealt, shared_buckets, whole_units
from .components import connected_components
from .state import checkpointed


def fingerprint(text: str | None, words: int = 3, seed: int = 42, at_once: int = 100_000) -> bytes:
    """Eight bytes, most significant first. Hashes are counted in bounded slabs."""
    said = (text or "").encode("utf-8", "replace").lower().split()
    if not said:
        return bytes(8)
    joined = b" ".join(said)
    lengths = np.fromiter(map(len, said), np.int64, len(said))
    ends = np.cumsum(lengths + 1) - 1
    starts = ends - lengths
    n = max(1, len(said) - words + 1)
    last = ends[min(words, len(said)) - 1 :]
    counts = np.zeros(64, np.int64)
    digest = xxhash.xxh64_digest
    for i in range(0, n, at_once):
        spans = zip(starts[i : min(i + at_once, n)].tolist(), last[i : min(i + at_once, n)].tolist())
        raw = b"".join([digest(joined[s:e], seed) for s, e in spans])
        counts += np.unpackbits(np.frombuffer(raw, np.uint8).reshape(-1, 8), axis=1).sum(0, dtype=np.int64)
    return np.packbits(2 * counts > n).tobytes()


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words: int = 3, seed: int = 42) -> DataFrame:
    """(doc_id, fp): the fingerprint as a signed 64-bit number. One pass over whole texts."""
    kept = docs.select(F.col(id_col).alias("doc_id"), F.col(text).alias("text"))
    schema = kept.select("doc_id").withColumn("fp", F.lit(0).cast("long")).schema

    def apply(batches):
        for batch in batches:
            raw = b"".join(fingerprint(t, words, seed) for t in batch.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.frombuffer(raw, ">i8").astype(np.int64))], names=["doc_id", "fp"])

    return kept.mapInArrow(apply, schema)


def hex_of(fp: Column) -> Column:
    return F.lower(F.lpad(F.hex(fp), 16, "0"))


def block_keys(bits: int, blocks: int) -> list[Column]:
    """A key for each choice of blocks - bits blocks: the fingerprint's bits outside of them are cleared, and the choice is hashed in."""
    edges = [round(64 * i / blocks) for i in range(blocks + 1)]
    keys = []
    for t, chosen in enumerate(combinations(range(blocks), blocks - bits)):
        mask = sum(((1 << (edges[i + 1] - edges[i])) - 1) << edges[i] for i in chosen)
        mask -= (1 << 64) if mask >= 1 << 63 else 0
        keys.append(F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(mask)).alias("v")))
    return keys


def links(distinct: DataFrame, bits: int = 2, blocks: int = 4) -> DataFrame:
    """(src, dst): links between distinct fingerprints that span all pairs of at most ``bits`` differing bits.

    A bucket's key is a 64-bit hash of (table, masked value); a collision of two keys only adds candidates.
    """
    keyed = distinct.select("fp", F.explode(F.array(*block_keys(bits, blocks))).alias("k")).select("fp", F.xxhash64("k.t", "k.v").alias("key"))
    units = dealt(shared_buckets(keyed), F.col("fp"))

    def apply(batches):
        for table, starts in whole_units(batches):
            fp = table.column("fp").to_numpy().view(np.uint64)
            place = [table.column(c).to_numpy() for c in ("bi", "bj", "own")]
            forest = Forest(len(fp))
            for a, b in candidate_pairs(starts, len(fp), *place):
                near = np.bitwise_count(fp[a] ^ fp[b]) <= bits
                forest.link(a[near], b[near])
            a, b = forest.edges()
            yield pa.RecordBatch.from_arrays([pa.array(fp[a].view(np.int64)), pa.array(fp[b].view(np.int64))], names=["src", "dst"])

    return units.mapInArrow(apply, "src long, dst long").distinct()


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words: int = 3, bits: int = 2, blocks: int = 4, seed: int = 42) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row."""
    marked = checkpointed(fingerprints(docs, id_col, text, words, seed))
    groups = checkpointed(marked.groupBy("fp").agg(F.min("doc_id").alias("least")))
    label = connected_components(links(groups.select("fp"), bits, blocks))
    named = groups.join(label, groups["fp"] == label["node"], "left").select("fp", "least", F.coalesce("component", "fp").alias("component"))
    best = named.groupBy("component").agg(F.min("least").alias("component_id"))
    table = named.join(best, "component").select("fp", "component_id")
    return marked.join(table, "fp").select("doc_id", hex_of(F.col("fp")).alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words: int = 3, bits: int = 2, blocks: int = 4, seed: int = 42) -> DataFrame:
    """The documents that stay, with all their columns: of each component the row of least id.

    Of rows that share an id one stays, the first by its columns' values. Rows with a null id cannot be named and all stay.
    """
    found = near_duplicates(docs.where(F.col(id_col).isNotNull()), id_col, text, words, bits, blocks, seed)
    stay = found.where("doc_id = component_id").select(F.col("doc_id").alias("__stay")).distinct()
    mine = docs.join(stay, docs[id_col] == stay["__stay"], "left_semi")
    order = Window.partitionBy(id_col).orderBy(*[F.col(f"`{c}`").asc_nulls_first() for c in docs.columns if c != id_col])
    one = mine.withColumn("__r", F.row_number().over(order)).where("__r = 1").drop("__r")
    return one.union(docs.where(F.col(id_col).isNull()))
