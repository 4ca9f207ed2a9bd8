"""Running sums in two levels: cells of an order, and rows inside a cell. No window spans all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def quantile_cells(df: DataFrame, order: str, cells: int) -> Column:
    """The cell of a row by approximate quantiles of ``order``, so that cells hold alike many rows however its values lie; equal values share a cell."""
    bounds = df.agg(F.percentile_approx(order, [i / cells for i in range(1, cells)], 10_000)).first()[0] or []
    return F.size(F.filter(F.array(*map(F.lit, sorted(set(bounds)))), lambda b: b <= F.col(order))) if bounds else F.lit(0)


def with_cells(df: DataFrame, cell: Column, value: Column, order: list[str]) -> DataFrame:
    """Adds ``cell`` and ``before``: the sum of ``value`` over all rows before a row, by cell and then ``order``. Sums of cells are a small table."""
    placed = df.withColumns({"cell": cell, "__value": value})
    above = Window.orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    zero = F.lit(0).cast(placed.select(F.sum("__value").alias("s")).schema["s"].dataType)
    offset = placed.groupBy("cell").agg(F.sum("__value").alias("s")).select("cell", F.coalesce(F.sum("s").over(above), zero).alias("__offset"))
    inside = Window.partitionBy("cell").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    summed = placed.withColumn("__in", F.coalesce(F.sum("__value").over(inside), zero)).join(F.broadcast(offset), "cell")
    return summed.withColumn("before", F.col("__offset") + F.col("__in")).drop("__offset", "__in", "__value")


def places(df: DataFrame, by: str, order: str, cells: int = 64) -> DataFrame:
    """Adds ``at``: the place of a row, from 1, among those of its ``by`` in the order of numeric ``order``. A hot key is ranked cell by cell; its offsets are at most ``cells`` rows."""
    placed = df.withColumn("cell", quantile_cells(df, order, cells))
    above = Window.partitionBy(by).orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    offset = placed.groupBy(by, "cell").agg(F.count("*").alias("n")).select(by, "cell", F.coalesce(F.sum("n").over(above), F.lit(0)).alias("offset"))
    inside = F.row_number().over(Window.partitionBy(by, "cell").orderBy(order))
    ranked = placed.withColumn("inside", inside).join(offset, [by, "cell"])
    return ranked.withColumn("at", F.col("offset") + F.col("inside")).drop("cell", "offset", "inside")


def running(df: DataFrame, order: list[str], value: Column, cells: int = 64) -> DataFrame:
    """Adds ``before``: the sum of ``value`` over the rows before, in the order of numeric ``order[0]``, then the others."""
    return with_cells(df, quantile_cells(df, order[0], cells), value, order).drop("cell")
