"""User edge lists in other formats, sinks for spools and adjacency, and a data source for binary feature shards."""

from __future__ import annotations

import struct
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

EDGE_SCHEMA = "src long, dst long, weight double, ts timestamp"


def read_edges(spark: SparkSession, path: str, form: str = "parquet") -> DataFrame:
    """Edges (src, dst, weight, ts) from parquet, csv (with header), json or orc; schemas are fixed, not inferred."""
    if form not in ("parquet", "csv", "json", "orc"):
        raise ValueError(f"unknown format {form}")
    reader = spark.read.schema(EDGE_SCHEMA)
    return reader.option("header", True).csv(path) if form == "csv" else reader.format(form).load(path)


def write_batches(blocks: DataFrame, path: str) -> None:
    """Spool blocks partitioned by epoch, so a window reads its own files only."""
    blocks.write.mode("overwrite").partitionBy("epoch").parquet(path)


def write_adjacency(edges: DataFrame, table: str, buckets: int = 64) -> None:
    """Bucketed by receiver: joins of frontiers with the adjacency need no shuffle of edges."""
    edges.write.mode("overwrite").bucketBy(buckets, "dst").sortBy("dst").saveAsTable(table)


class _Shard(InputPartition):
    def __init__(self, path: str):
        self.path = path


class FeatureShards(DataSource):
    """``gnn_features``: files of records (int64 node id, d float32 values), little-endian. Options: path (comma-separated files), width."""

    @classmethod
    def name(cls) -> str:
        return "gnn_features"

    def schema(self) -> str:
        return "node_id long, f array<float>"

    def reader(self, schema) -> DataSourceReader:
        return _ShardReader(self.options["path"].split(","), int(self.options["width"]))


class _ShardReader(DataSourceReader):
    def __init__(self, paths: list[str], width: int):
        self.paths, self.width = paths, width

    def partitions(self) -> list[InputPartition]:
        return [_Shard(p) for p in self.paths]

    def read(self, partition: _Shard) -> Iterator[tuple]:
        size = 8 + 4 * self.width
        with open(partition.path, "rb") as f:
            while record := f.read(size):
                node, *values = struct.unpack(f"<q{self.width}f", record)
                yield node, list(values)


def write_shard(path: str, rows, width: int) -> None:
    with open(path, "wb") as f:
        for node, values in rows:
            f.write(struct.pack(f"<q{width}f", node, *values))
