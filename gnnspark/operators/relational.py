"""Joins and limits that the methods need and Spark lacks as single operators: as-of, interval overlap, salted top-k, vector mean."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def asof_join(left: DataFrame, right: DataFrame, by: str, left_time: str, right_time: str, value: str) -> DataFrame:
    """Each left row with the last ``value`` at or before its time. One union and one running window a key; no pairs are built."""
    l = left.withColumn("__t", F.col(left_time).cast("timestamp").cast("double")).withColumn("__side", F.lit(1)).withColumn("__v", F.lit(None).cast(right.schema[value].dataType))
    names = left.columns
    r = right.select(F.col(by), F.col(right_time).cast("timestamp").cast("double").alias("__t"), F.lit(0).alias("__side"), F.col(value).alias("__v"))
    both = l.unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy(by).orderBy("__t", "__side").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.withColumn(value, F.last("__v", ignorenulls=True).over(w)).where("__side = 1").select(*names, value)


def interval_overlaps(a: DataFrame, b: DataFrame, width: float) -> DataFrame:
    """Pairs of spans (id, start, end) of two tables that overlap: both are spread over cells of ``width`` and meet in the first shared cell only."""
    cells = lambda df, p: df.select(*[F.col(c).alias(f"{p}_{c}") for c in ("id", "start", "end")], F.explode(F.sequence(F.floor(F.col("start") / width), F.floor(F.col("end") / width))).alias("cell"))
    met = cells(a, "a").join(cells(b, "b"), "cell").where("a_start < b_end and b_start < a_end")
    return met.where(F.col("cell") == F.floor(F.greatest("a_start", "b_start") / width)).select("a_id", "b_id", (F.least("a_end", "b_end") - F.greatest("a_start", "b_start")).alias("overlap"))


def salted_top_k(df: DataFrame, key: str, order: list[Column], k: int, salts: int = 16, salt_by: Column | None = None) -> DataFrame:
    """The first ``k`` rows of each key in two levels: a hub's rows are limited in ``salts`` tasks before they meet."""
    salt = F.pmod(F.xxhash64(salt_by if salt_by is not None else F.struct(*df.columns)), F.lit(salts))
    first = df.withColumn("__s", salt).withColumn("__r", F.row_number().over(Window.partitionBy(key, "__s").orderBy(*order))).where(F.col("__r") <= k).drop("__s", "__r")
    return first.withColumn("__r", F.row_number().over(Window.partitionBy(key).orderBy(*order))).where(F.col("__r") <= k).drop("__r")


def vector_mean(df: DataFrame, by: str, vector: str) -> DataFrame:
    """(by, mean): element-wise mean of arrays, as sums by position that combine before the shuffle."""
    cells = df.select(by, F.posexplode(vector).alias("pos", "x")).groupBy(by, "pos").agg(F.avg(F.col("x").cast("double")).alias("x"))
    return cells.groupBy(by).agg(F.transform(F.sort_array(F.collect_list(F.struct("pos", "x"))), lambda s: s["x"]).alias("mean"))


def reachable(edges: DataFrame, seeds: DataFrame, most: int = 10) -> DataFrame:
    """(node_id, hops): breadth-first distances up to ``most`` steps; stops when nothing is added."""
    seen = seeds.select("node_id", F.lit(0).alias("hops"))
    for hop in range(1, most + 1):
        new = edges.join(seen.where(F.col("hops") == hop - 1), F.col("dst") == F.col("node_id")).select(F.col("src").alias("node_id")).distinct().join(seen, "node_id", "left_anti")
        seen = seen.union(new.select("node_id", F.lit(hop).alias("hops")))
    return seen


def pandas_norm(vector) -> Column:
    """Euclidean norms of a column of arrays by a pandas function."""

    @F.pandas_udf("double")
    def norms(v: pd.Series) -> pd.Series:
        return v.map(lambda a: None if a is None else float(np.sqrt(np.square(np.asarray(a, float)).sum())))

    return norms(vector)


def pandas_median(value, times) -> Column:
    """The median of a group's values, each ``times`` times, by a pandas aggregate. A group is the distinct values of a key."""

    @F.pandas_udf("double")
    def median(v: pd.Series, n: pd.Series) -> float:
        at = np.argsort(v.to_numpy(float), kind="stable")
        values, ends = v.to_numpy(float)[at], np.cumsum(n.to_numpy()[at])
        low, high = np.searchsorted(ends, [(ends[-1] - 1) // 2, ends[-1] // 2], side="right")
        return float((values[low] + values[high]) / 2)

    return median(value, times)


def cogrouped_totals(left: DataFrame, right: DataFrame, by: str) -> DataFrame:
    """(by, customers, suppliers): sums of ``x`` of both sides, cogrouped; a side without rows has null."""

    def totals(key: tuple, a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({by: [key[0]], "customers": [a["x"].sum() if len(a) else None], "suppliers": [b["x"].sum() if len(b) else None]})

    kind = left.schema[by].dataType.simpleString()
    return left.groupBy(by).cogroup(right.groupBy(by)).applyInPandas(totals, f"{by} {kind}, customers double, suppliers double")
