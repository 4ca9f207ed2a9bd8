"""Node features as arrays of floats, or as sparse rows (node_id, pos, x)."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .graphs import key
from .tables import read


def bucket(text: Column, d: int) -> Column:
    """The position of a hashed text among ``d``; portable."""
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long") % d


def densify(sparse: DataFrame, d: int) -> DataFrame:
    """(node_id, f): arrays of width ``d`` from sparse rows; one small group per node."""
    filled = F.map_from_entries(F.collect_list(F.struct("pos", F.col("x").cast("float"))))
    return sparse.groupBy("node_id").agg(filled.alias("m")).select("node_id", F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.coalesce(F.try_element_at("m", i.cast("long")), F.lit(0.0).cast("float"))).alias("f"))


def text_features(texts: DataFrame, d: int, gram: int = 3, dense: bool = True) -> DataFrame:
    """Hashed character n-grams with unit norm. ``texts``: (node_id, text), each node once; a text shorter than a gram has none. Counted in numpy: no gram is a row or a string."""
    low = texts.select("node_id", F.lower(F.coalesce("text", F.lit(""))).alias("t")).where(F.length("t") >= gram)
    kind = low.schema["node_id"].dataType.simpleString()
    if dense:
        return low.mapInArrow(_gram_rows(d, gram), f"node_id {kind}, f array<float>")
    held = low.mapInArrow(_gram_rows(d, gram, True), f"node_id {kind}, f array<double>")
    return held.select("node_id", F.posexplode("f").alias("pos", "x")).where("x > 0").select("node_id", F.col("pos").cast("long").alias("pos"), "x")


def _gram_rows(d: int, gram: int, double: bool = False):
    """Texts (node_id, t) to rows of ``d`` places. Grams of the first 255 characters met are places of a table, the others are looked up one by one."""

    def place(text: str) -> int:
        return int(hashlib.md5(text.encode("utf-8", "surrogatepass")).hexdigest()[:8], 16) % d

    def go(parts):
        small, chars = np.zeros(0x110000, np.int64), [""]
        table, rest = np.full(256**gram if gram <= 3 else 0, -1, np.int32), {}

        def places(c: np.ndarray, starts: np.ndarray) -> np.ndarray:
            for x in np.flatnonzero(np.bincount(c) > 0)[:4096].tolist():
                if len(chars) < 256 and not small[x]:
                    small[x] = len(chars)
                    chars.append(chr(x))
            at, whole, own = np.zeros(len(starts), np.int64), np.full(len(starts), len(table) > 0), small[c]
            for k in range(gram):
                one = own[starts + k]
                whole &= one > 0
                at = at * 256 + one
            out = table[at] if len(table) else np.full(len(starts), -1, np.int32)
            new = np.flatnonzero(whole & (out < 0))
            if len(new):
                for x in np.unique(at[new]).tolist():
                    table[x] = place("".join([chars[x >> 8 * k & 255] for k in reversed(range(gram))]))
                out[new] = table[at[new]]
            for i in np.flatnonzero(~whole).tolist():
                text = "".join(map(chr, c[starts[i] : starts[i] + gram].tolist()))
                if text not in rest:
                    if len(rest) >= 1 << 18:
                        rest.clear()
                    rest[text] = place(text)
                out[i] = rest[text]
            return out

        for whole_part in parts:
            for part in (whole_part.slice(i, 256) for i in range(0, whole_part.num_rows, 256)):
                texts = part.column("t").to_pylist()
                c, sizes = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.int64), np.array([len(t) for t in texts])
                n = sizes - gram + 1
                which = np.repeat(np.arange(len(texts)), n)
                starts = np.arange(len(which)) + np.repeat(np.cumsum(sizes) - sizes - np.cumsum(n) + n, n)
                times = np.bincount(which * d + places(c, starts), minlength=len(texts) * d).reshape(-1, d).astype(float)
                f = (times / np.sqrt((times * times).sum(1, keepdims=True))).astype(np.float64 if double else np.float32)
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(texts) + 1, dtype=np.int32) * d), pa.array(f.reshape(-1)))
                yield pa.RecordBatch.from_arrays([part.column("node_id"), lists], ["node_id", "f"])

    return go


def document_trigrams(spark: SparkSession, sf_dir: str, d: int = 100, dense: bool = True) -> DataFrame:
    docs = read(spark, sf_dir, "documents", "doc_id", "text").select(key("document", "doc_id").alias("node_id"), "text")
    return text_features(docs, d, dense=dense)


def one_hot(value: Column, d: int) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: (i == value).cast("float"))


def customer_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Balance and a one-hot of the nation modulo 7."""
    c = read(spark, sf_dir, "customer")
    hashed = F.col("c_nationkey") % 7
    return c.select(key("customer", "c_custkey").alias("node_id"), F.concat(F.array((F.col("c_acctbal") / 10000.0).cast("float")), one_hot(hashed, 7)).alias("f"), hashed.alias("hash7"))


def supplier_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = read(spark, sf_dir, "supplier")
    return s.select(key("supplier", "s_suppkey").alias("node_id"), F.concat(F.array((F.col("s_acctbal") / 10000.0).cast("float")), one_hot(F.col("s_nationkey") % 7, 7)).alias("f"))


def balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node_id, x): account balances of customers and suppliers."""
    c = read(spark, sf_dir, "customer").select(key("customer", "c_custkey").alias("node_id"), F.col("c_acctbal").alias("x"))
    return c.union(read(spark, sf_dir, "supplier").select(key("supplier", "s_suppkey"), "s_acctbal"))


def standing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(node_id, x): how many deviations a balance (customers, suppliers) or a retail price (parts) lies above the mean of its kind."""
    told = (("customer", "c_custkey", "c_acctbal"), ("supplier", "s_suppkey", "s_acctbal"), ("part", "p_partkey", "p_retailprice"))
    each = [read(spark, sf_dir, t).select(key(t, k).alias("node_id"), F.lit(t).alias("kind"), F.col(v).cast("double").alias("x")) for t, k, v in told]
    every = each[0].union(each[1]).union(each[2])
    kinds = every.groupBy("kind").agg(F.avg("x").alias("mean"), F.stddev_pop("x").alias("sd"))
    x = F.when(F.col("sd") > 0, (F.col("x") - F.col("mean")) / F.col("sd")).otherwise(0.0)
    return every.join(F.broadcast(kinds), "kind").select("node_id", x.alias("x"))


def standing_features(spark: SparkSession, sf_dir: str, d: int = 16) -> DataFrame:
    """Customers, suppliers and parts: the standing, whether the node is a part, and a one-hot of ``d`` - 2 hashed places of its nation or brand."""
    told = (("customer", "c_custkey", "c_nationkey"), ("supplier", "s_suppkey", "s_nationkey"), ("part", "p_partkey", "p_brand"))
    each = [read(spark, sf_dir, t).select(key(t, k).alias("node_id"), F.lit(float(t == "part")).cast("float").alias("part"), F.coalesce(F.col(v).cast("string"), F.lit("")).alias("of")) for t, k, v in told]
    held = each[0].union(each[1]).union(each[2]).join(standing(spark, sf_dir), "node_id")
    return held.select("node_id", F.concat(F.array(F.col("x").cast("float"), "part"), one_hot(bucket(F.col("of"), d - 2), d - 2)).alias("f"))


def part_features(spark: SparkSession, sf_dir: str, d: int = 128) -> DataFrame:
    """Hashed brand, type and name words, and scaled size and price in the first two places."""
    p = read(spark, sf_dir, "part")
    words = F.array_union(F.split("p_name", " "), F.array("p_brand", "p_type"))
    hot = F.transform(words, lambda w: bucket(w, d - 2) + 2)
    dense = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda i: F.when(i == 0, F.col("p_size") / 50).when(i == 1, F.col("p_retailprice") / 2000).otherwise(F.array_contains(hot, i.cast("long")).cast("double")).cast("float"))
    return p.select(key("part", "p_partkey").alias("node_id"), dense.alias("f"))


def embedding_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("node_id"), F.col("embedding").alias("f"))


def exploded(features: DataFrame) -> DataFrame:
    """(node_id, pos, x) from arrays."""
    return features.select("node_id", F.posexplode("f").alias("pos", "x")).withColumn("x", F.col("x").cast("double"))
