"""Near-duplicates at a Jaccard similarity of word shingles: SimHash blocks and min-hash bands, then an exact check of the sets.

A text is the set of its five-word shingles, over words folded in A-Z and cut at white space. The fingerprints of :mod:`simhash` over the same shingles are linked
at two differing bits, by four blocks and a table for each two of them, and texts with linked fingerprints are candidates. Most pairs at similarity 0.8 differ by more bits, so that these are met
too, of each text 128 min-hashes are taken: 32 bands of four
hashes are the bucket keys, and the low byte of each hash is the sketch. Texts that share a bucket are candidates if their
sketches agree in ``sketch_share`` of the bytes; candidates fall into groups, and inside a group the shingle sets of all pairs that are not linked yet are compared.
A pair at similarity 0.8 meets in no band with probability 5e-8; nothing is capped. Buckets and groups of any size are compared in bounded
units (:mod:`blockpairs`).

Defined results: equal texts are one node; null text is empty text; texts without words have one shingle, the empty one, and are linked to each other; fewer words than a
shingle make one shingle; rows are told apart by all their columns, so a repeated or null id loses no row whose text is not linked; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .blockpairs import Forest, candidate_pairs, dealt, shared_buckets, whole_units
from .components import connected_components
from .mixing import beside
from .simhash import fingerprint
from .simhash import links as close_pairs
from .state import checkpointed, map_in_arrow

BANDS, ROWS = 32, 4
_rng = np.random.default_rng(20)
FLIP, FACTOR = _rng.integers(0, 2**64, BANDS * ROWS, np.uint64), _rng.integers(0, 2**64, BANDS * ROWS, np.uint64) | np.uint64(1)


def shingles(text: str | None, words: int = 5, seed: int = 42) -> np.ndarray:
    """Distinct 64-bit hashes of a text's word shingles, sorted."""
    said = (text or "").encode("utf-8", "replace").lower().split()
    joined = b" ".join(said)
    lengths = np.fromiter(map(len, said), np.int64, len(said))
    ends = np.cumsum(lengths + 1) - 1
    n = max(1, len(said) - words + 1)
    if n == 1:
        return np.array([xxhash.xxh64_intdigest(joined, seed)], np.uint64)
    digest = xxhash.xxh64_digest
    raw = b"".join([digest(joined[s:e], seed) for s, e in zip((ends - lengths)[:n].tolist(), ends[words - 1 :].tolist())])
    return np.unique(np.frombuffer(raw, ">u8").astype(np.uint64))


def min_hashes(marks: np.ndarray, at_once: int = 1024) -> np.ndarray:
    """The least value of each of the keyed hashes over a set."""
    least = np.full(len(FLIP), np.iinfo(np.uint64).max)
    for i in range(0, len(marks), at_once):
        np.minimum(least, ((marks[i : i + at_once, None] ^ FLIP) * FACTOR).min(0), out=least)
    return least


def node_of(text: str) -> Column:
    return F.xxhash64(F.coalesce(F.col(f"`{text}`"), F.lit("")))


def sketches(docs: DataFrame, text: str = "text", words: int = 5) -> DataFrame:
    """(node, keys, sketch, fp) of each text. One pass over whole texts."""

    def apply(batches):
        for batch in batches:
            said = batch.column(1).to_pylist()
            fp = np.frombuffer(b"".join(fingerprint(t, words) for t in said), ">i8").astype(np.int64)
            least = np.array([min_hashes(shingles(t, words)) for t in said], np.uint64).reshape(-1, BANDS * ROWS)
            keys = [[xxhash.xxh64_intdigest(band.tobytes(), k) for k, band in enumerate(row.reshape(BANDS, ROWS))] for row in least]
            keys = np.array(keys, np.uint64).reshape(-1).view(np.int64)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, len(keys) + 1, BANDS, dtype=np.int32)), pa.array(keys))
            yield pa.RecordBatch.from_arrays([batch.column(0), lists, pa.array([row.tobytes() for row in least.astype(np.uint8)], pa.binary()), pa.array(fp)], names=["node", "keys", "sketch", "fp"])

    return map_in_arrow(docs.select(node_of(text).alias("node"), F.col(f"`{text}`")), apply, "node long, keys array<long>, sketch binary, fp long").dropDuplicates(["node"])


def close_fingerprints(found: DataFrame, bits: int = 2, blocks: int = 4) -> DataFrame:
    """(src, dst): links that span all pairs of texts whose fingerprints differ by at most ``bits`` bits."""
    least = checkpointed(found.groupBy("fp").agg(F.min("node").alias("least"), F.count("*").alias("n")))
    equal = found.select("node", "fp").join(least.where("n > 1"), "fp").where("node <> least").select(F.col("node").alias("src"), F.col("least").alias("dst"))
    of = lambda end: least.select(F.col("fp").alias(end), F.col("least").alias(f"{end}_node"))
    near = close_pairs(least.select("fp"), bits, blocks).join(of("src"), "src").join(of("dst"), "dst")
    return equal.union(near.select("src_node", "dst_node"))


def candidates(found: DataFrame, sketch_share: float = 0.6) -> DataFrame:
    """(src, dst): links that span all pairs of texts which share a bucket and most of their sketch."""
    buckets = shared_buckets(found.select("node", F.explode("keys").alias("key")))
    units = dealt(buckets.join(found.select("node", "sketch"), "node"), F.col("node"))

    def apply(batches):
        for table, starts in whole_units(batches):
            node = table.column("node").to_numpy()
            sketch = np.frombuffer(b"".join(table.column("sketch").to_pylist()), np.uint8).reshape(len(node), -1)
            forest = Forest(len(node))
            for a, b in candidate_pairs(starts, len(node), *(table.column(c).to_numpy() for c in ("bi", "bj", "own"))):
                for i in range(0, len(a), 65_536):
                    p, q = a[i : i + 65_536], b[i : i + 65_536]
                    near = (sketch[p] == sketch[q]).sum(1) >= sketch_share * sketch.shape[1]
                    forest.link(p[near], q[near])
            a, b = forest.edges()
            yield pa.RecordBatch.from_arrays([pa.array(node[a]), pa.array(node[b])], names=["src", "dst"])

    return units.mapInArrow(apply, "src long, dst long").distinct()


def verified(texts: DataFrame, similarity: float = 0.8, words: int = 5, block: int = 256) -> DataFrame:
    """(src, dst): of (node, key, bucket_size, text), links that span all pairs of a bucket whose shingle sets have at least that Jaccard similarity."""
    units = dealt(texts, F.col("node"), block=block)

    def apply(batches):
        for table, starts in whole_units(batches):
            node = table.column("node").to_numpy()
            bi, bj, own = (table.column(c).to_numpy() for c in ("bi", "bj", "own"))
            said = table.column("text")
            forest = Forest(len(node))
            for s, e in zip(starts, np.append(starts[1:], len(node))):
                sets = [shingles(said[i].as_py(), words) for i in range(s, e)]
                sizes = np.array([len(x) for x in sets])
                for i in range(e - s - 1):
                    j = np.arange(i + 1, e - s)
                    fit = np.minimum(sizes[i], sizes[j]) >= similarity * np.maximum(sizes[i], sizes[j])
                    j = j[fit & (forest.label[s + j] != forest.label[s + i]) & ((bi[s] == bj[s]) | (own[s + j] != own[s + i]))]
                    if not len(j):
                        continue
                    flat = np.concatenate([sets[k] for k in j])
                    at = np.minimum(np.searchsorted(sets[i], flat), sizes[i] - 1)
                    both = np.add.reduceat((sets[i][at] == flat).astype(np.int64), np.append(0, np.cumsum(sizes[j])[:-1]))
                    near = j[both >= similarity * (sizes[i] + sizes[j] - both) - 1e-9]
                    forest.link(np.full(len(near), s + i), s + near)
            a, b = forest.edges()
            yield pa.RecordBatch.from_arrays([pa.array(node[a]), pa.array(node[b])], names=["src", "dst"])

    return map_in_arrow(units.select("node", "text", "bi", "bj", "own", "key"), apply, "src long, dst long").distinct()


def groups(docs: DataFrame, text: str = "text", words: int = 5, similarity: float = 0.8) -> DataFrame:
    """(node, component): the texts that are linked to another one, and the least node of their component."""
    found = checkpointed(sketches(docs, text, words))
    loose = checkpointed(connected_components(close_fingerprints(found).union(candidates(found))))
    sizes = loose.groupBy("component").agg(F.count("*").alias("bucket_size"))
    members = loose.join(sizes, "component").select("node", F.col("component").alias("key"), "bucket_size")
    texts = docs.select(node_of(text).alias("node"), F.coalesce(F.col(f"`{text}`"), F.lit("")).alias("text")).join(beside(members), "node").dropDuplicates(["node"])
    return connected_components(verified(texts, similarity, words))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text: str = "text", words: int = 5, similarity: float = 0.8) -> DataFrame:
    """The rows that stay, with all their columns: of each component of linked texts the row of least id, nulls last, ties by text and columns.

    Rows are chosen, not ids: of rows that share an id only those with linked texts go, and rows with a null id take part.
    """
    columns = [F.col(f"`{c}`") for c in docs.columns]
    row = F.xxhash64(*columns, F.array(*[c.isNull() for c in columns]))
    marked = docs.select(node_of(text).alias("node"), row.alias("row"), F.col(f"`{id_col}`").alias("id"))
    rows = marked.groupBy("node", "row").agg(F.min("id").alias("id"), F.count("*").alias("n"))
    first = rows.groupBy("node").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", F.col("node").alias("of"), "row", "n")).alias("first"))
    label = groups(docs, text, words, similarity)
    named = first.join(label, "node", "left").select(F.coalesce("component", "node").alias("component"), "first")
    best = checkpointed(named.groupBy("component").agg(F.min("first").alias("first")).select(F.col("first.of").alias("__node"), F.col("first.row").alias("__row"), (F.col("first.n") > 1).alias("__many")))
    mine = docs.withColumns({"__node": node_of(text), "__row": row}).join(best, ["__node", "__row"]).select(*docs.columns, "__many")
    many = mine.where("__many").drop("__many").distinct()
    return mine.where("not __many").drop("__many").union(many)
