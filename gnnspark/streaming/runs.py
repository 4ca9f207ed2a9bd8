"""Streams over edge arrivals: windows, late data, deduplication, degree state, gradient queues, joins.

Each function takes a streaming table and returns one; :func:`drain` runs it to the end of its input.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..sources.spool import scratch

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/event[s].parquet")


def spooled(spark: SparkSession, folder: str, schema: str) -> DataFrame:
    """A stream over files in name order, one a trigger."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(folder)


def drain(spark: SparkSession, stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all present input. Appended rows go to a Parquet sink; in the other modes each trigger's result is a folder, of which ``complete`` reads the last and ``update`` all."""
    where = scratch(spark, "stream")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", f"{where}/out").option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{where}/out")
    done = []

    def put(rows: DataFrame, number: int) -> None:
        rows.write.mode("overwrite").parquet(f"{where}/out/{number}")
        done.append(f"{where}/out/{number}")

    stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{where}/state").trigger(availableNow=True).start().awaitTermination()
    kept = done[-1:] if mode == "complete" else sorted(set(done))
    return spark.read.schema(stream.schema).parquet(*kept) if kept else spark.createDataFrame([], stream.schema)


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", slide: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.window("ts", width, slide).alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, delay: str = "60 days") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def degree_state(events: DataFrame) -> DataFrame:
    """(user_id, degree): the running number of events a user, in a state that outlives batches."""

    def count(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"user_id": [key[0]], "degree": [n]})

    return events.groupBy("user_id").applyInPandasWithState(count, "user_id long, degree long", "n long", "update", GroupStateTimeout.NoTimeout)


def streamed_degrees(events: DataFrame) -> DataFrame:
    """(node_id, deg): arrivals a user so far; the masses of the cache's degree probabilities follow each trigger."""
    return events.groupBy(F.col("user_id").alias("node_id")).agg(F.count("*").alias("deg"))


def batch_queue(batches: DataFrame, workers: int) -> DataFrame:
    """(batch_id, worker, n, first): what each worker takes from a queue of packaged batches (batch_id, seeds); a file is a slot of the queue."""
    worker = (F.col("batch_id") % workers).cast("int")
    return batches.select("batch_id", worker.alias("worker"), F.size("seeds").cast("long").alias("n"), F.array_min("seeds").alias("first"))


def gradient_queue(arrivals: DataFrame, workers: int) -> DataFrame:
    """(receiver, iter, mean): folds gradients (iter, sender, receiver, g) as they come; a row leaves when all workers' have."""

    def fold(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, mean = state.get if state.exists else (0, 0.0)
        for b in batches:
            for g in b["g"]:
                n += 1
                mean += (g - mean) / n
        if n >= workers:
            state.remove()
            yield pd.DataFrame({"receiver": [key[0]], "iter": [key[1]], "mean": [mean]})
        else:
            state.update((n, mean))

    return arrivals.groupBy("receiver", "iter").applyInPandasWithState(fold, "receiver int, iter int, mean double", "n long, mean double", "append", GroupStateTimeout.NoTimeout)


def with_static(events: DataFrame, nations: DataFrame) -> DataFrame:
    """Events with a static table, counted by its name."""
    return events.withColumn("n_nationkey", (F.col("user_id") % 25).cast("int")).join(nations, "n_nationkey").groupBy("n_name").agg(F.count("*").alias("n"))


def interval(events: DataFrame, first: str, then: str, most: str = "1 hour") -> DataFrame:
    """(first_id, then_id): events of one user of two types, the second within ``most`` after the first; both sides keep bounded state."""
    a = events.where(F.col("event_type") == first).select(F.col("user_id").alias("u"), F.col("ts").alias("ta"), F.col("event_id").alias("first_id")).withWatermark("ta", "2 hours")
    b = events.where(F.col("event_type") == then).select("user_id", F.col("ts").alias("tb"), F.col("event_id").alias("then_id")).withWatermark("tb", "2 hours")
    return a.join(b, F.expr(f"u = user_id and tb >= ta and tb <= ta + interval {most}")).select("first_id", "then_id")
