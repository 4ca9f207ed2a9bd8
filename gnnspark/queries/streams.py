"""Streaming queries: runs to the end of the input must equal the batch answers."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import cache as C
from ..operators.batching import make_batches
from ..operators.prefix import quantile_cells
from ..operators.propagation import split_of
from ..sources.graphs import load_graph
from ..sources.spool import spool
from ..sources.tables import read
from ..streaming import runs as R
from .base import graph_sql, query, u_sql
from .caching import draw_sql, train_sql
from .running import EX, WORKERS, arrived, r6, sql


@query("SELECT date_trunc('day', ts)::TIMESTAMP AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    return R.drain(spark, R.tumbling(R.event_stream(spark, d)), "complete")


@query("SELECT s::TIMESTAMP AS start, sum(n)::BIGINT AS n FROM (SELECT date_trunc('day', ts) AS s, count(*) AS n FROM events GROUP BY 1 UNION ALL SELECT date_trunc('day', ts) - INTERVAL 1 DAY, count(*) FROM events GROUP BY 1) GROUP BY s")
def stream_sliding(spark, d):
    return R.drain(spark, R.sliding(R.event_stream(spark, d)), "complete")


@query("SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS s FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events)) GROUP BY user_id, s")
def stream_session(spark, d):
    return R.drain(spark, R.sessions(R.event_stream(spark, d)), "complete")


@query("SELECT event_id, user_id FROM events")
def stream_dedup(spark, d):
    """Two deliveries of every event, one kept."""
    twice = R.event_stream(spark, d).union(R.event_stream(spark, d))
    return R.drain(spark, R.deduplicated(twice).select("event_id", "user_id"))


@query("SELECT user_id, count(*) AS degree FROM events GROUP BY user_id")
def stream_degree_state(spark, d):
    """Events arrive in three files; the last state of each user is its batch degree."""
    where = R.scratch(spark, "spool")
    read(spark, d, "events").repartition(3, "event_id").write.parquet(where)
    states = R.drain(spark, R.degree_state(R.spooled(spark, where, R.EVENTS)), "update")
    return states.groupBy("user_id").agg(F.max("degree").alias("degree"))


@query(sql(EX, f"SELECT r::INT AS receiver, iter, round(g, 6) AS mean FROM gm, (SELECT unnest(range({WORKERS})) AS r)"))
def stream_grad_queue(spark, d):
    where = R.scratch(spark, "spool")
    arrived(spark).repartition(4, "sender").write.parquet(where)
    out = R.drain(spark, R.gradient_queue(R.spooled(spark, where, "iter int, sender int, receiver int, delay int, arrive int, g double"), WORKERS))
    return out.withColumn("mean", r6("mean"))


@query(sql(["n AS (SELECT DISTINCT user_id AS node_id FROM events)", "cprob AS (SELECT user_id AS node_id, count(*)::DOUBLE / (SELECT count(*) FROM events) AS p FROM events GROUP BY user_id)", draw_sql("ch", "(SELECT greatest(1, floor(0.01 * count(*) + 1e-9)) FROM n)")], "SELECT node_id, round(p, 9) AS p, ord::INT AS ord FROM ch"))
def stream_cache_probs(spark, d):
    """Degrees come from arriving events, in three files; the cache drawn from the last trigger's probabilities is that of the whole table."""
    where = R.scratch(spark, "spool")
    read(spark, d, "events").repartition(3, "event_id").write.parquet(where)
    deg = R.drain(spark, R.streamed_degrees(R.spooled(spark, where, R.EVENTS)), "complete")
    sums = deg.agg(F.count("*").alias("n"), F.sum("deg").alias("m")).first()
    probs = deg.select("node_id", (F.col("deg") / F.lit(sums["m"] or 1)).alias("p"))
    return C.build_cache(probs, C.cache_size(sums["n"], 0.01)).select("node_id", F.round("p", 9).alias("p"), "ord")


@query(sql([*graph_sql("cust_supp"), train_sql("cust_supp"), f"lt AS (SELECT greatest(1, ceil(count(*) / 64.0))::BIGINT AS lots FROM tr)", f"q AS (SELECT floor({u_sql(7, chr(39) + 'batch' + chr(39), 0, 'node_id')} * lots)::BIGINT AS batch_id, node_id FROM tr, lt)"], f"SELECT batch_id, (batch_id % {WORKERS})::INT AS worker, count(*) AS n, min(node_id) AS first FROM q GROUP BY batch_id"))
def stream_batch_queue(spark, d):
    """The training batches of an epoch as files, taken one file a trigger."""
    train = load_graph(spark, d, "cust_supp").nodes.where(split_of(F.col("node_id"), "cust_supp") == "train").select("node_id")
    packed = make_batches(train, 64).groupBy("batch_id").agg(F.collect_list("node_id").alias("seeds"))
    where = R.scratch(spark, "spool")
    packed.repartitionByRange(4, "batch_id").write.parquet(where)
    return R.drain(spark, R.batch_queue(R.spooled(spark, where, "batch_id long, seeds array<long>"), WORKERS))


@query("SELECT n_name, count(*) AS n FROM events JOIN nation ON n_nationkey = user_id % 25 GROUP BY n_name")
def stream_static(spark, d):
    return R.drain(spark, R.with_static(R.event_stream(spark, d), read(spark, d, "nation", "n_nationkey", "n_name")), "complete")


@query("SELECT a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_interval(spark, d):
    return R.drain(spark, R.interval(R.event_stream(spark, d), "view", "click"))


@query("SELECT 0 AS late_in_result, 1 AS on_time_kept")
def stream_late(spark, d):
    """Nine files in time order and one of early rows at the end: the watermark drops the late rows and nothing else."""
    events = read(spark, d, "events", "event_id", "ts", "user_id").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    parts = spool(events.withColumn("part", quantile_cells(events, "us", 10) + 1).drop("us"))
    where = R.scratch(spark, "spool")
    for i in [*range(2, 11), 1]:
        parts.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(where)
    stream = R.spooled(spark, where, "event_id long, ts timestamp, user_id long").withWatermark("ts", "1 hour")
    seen = R.drain(spark, stream.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "n"))
    first = parts.where("part = 1").groupBy(F.date_trunc("day", "ts").alias("start")).agg(F.count("*").alias("early"))
    rest = parts.where("part > 1").groupBy(F.date_trunc("day", "ts").alias("start")).agg(F.count("*").alias("timely"))
    told = seen.join(rest, "start", "left").join(first, "start", "left")
    late = F.sum(F.greatest(F.col("n") - F.coalesce("timely", F.lit(0)), F.lit(0)))
    kept = F.min((F.col("n") >= F.coalesce("timely", F.lit(0))).cast("int"))
    return told.agg(late.cast("int").alias("late_in_result"), kept.alias("on_time_kept"))
