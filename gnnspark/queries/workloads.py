"""Experiment workloads on the cost clock, ablations, and measured training."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import metrics as M
from ..plans import queues as Q
from ..plans import schedule as S
from ..plans import workloads as W
from .base import query, r6
from .caching import POLICIES, cache_policy_bytes, _policy_sql
from .running import DELAYS_SQL, ITERS, PUBLISHED, WORKERS, _QSIZE, costs_sql, graph_sizes, piped_sql, rounded, sizes_sql, stats_sql
from .sampling import ERR_VARIANTS, _err_sql, estimator_runs

FAMILIES = {"ns": ("gcn", "graphsage"), "fastgcn": ("fastgcn", "fastgcn_f", "fastgcn_d", "fastgcn_fd"), "ladies": ("ladies", "ladies_f", "ladies_d", "ladies_fd")}


def workload_sql(models, workers, datasets=W.DATASETS) -> str:
    """Statistics once a model and dataset, then costs and schedules for each number of workers."""
    ctes, parts = [], []
    for dataset in datasets:
        for model in models:
            st, width = f"st_{dataset}_{model}", W.SHAPES[dataset][0]
            ctes.append(f"{st} AS MATERIALIZED ({stats_sql(dataset, model, models)})")
            for g in (workers,) if isinstance(workers, int) else workers:
                base, piped = costs_sql(f"SELECT * FROM {st}", width, g, False), costs_sql(f"SELECT * FROM {st}", width, g, True)
                head = f"SELECT '{model}' AS model, '{dataset}' AS dataset, {g} AS workers"
                share = W.SHARE_MS * (g - 1)
                parts.append(f"{head}, 0 AS piped, sum(n)::BIGINT AS batches, (sum(t) + count(*) * {share}) / sum(n) AS batch_ms, sum(t) + count(*) * {share} AS training_ms, sum(b)::BIGINT AS bytes FROM (SELECT k, max(sampling + transfer + compute) AS t, count(*) AS n, sum(bytes) AS b FROM ({base}) GROUP BY k)")
                parts.append(f"{head}, 1, count(*), max(finish_share) / count(*), max(finish_share), sum(bytes)::BIGINT FROM ({piped_sql(piped, (*S.STAGES, 'share'))})")
    return f"WITH {', '.join(ctes)} " + " UNION ALL ".join(parts)


ROUNDED = "SELECT model, dataset, workers, piped, batches, round(batch_ms, 9) AS batch_ms, round(training_ms, 6) AS training_ms, bytes FROM ({})"

for _family, _models in FAMILIES.items():
    for _g in range(1, 5):

        @query(ROUNDED.format(workload_sql(_models, _g)), f"wl_{_family}_g{_g}")
        def _workload(spark, d, models=_models, workers=_g):
            return rounded(W.workload(spark, d, models, workers), "training_ms").withColumn("batch_ms", F.round("batch_ms", 9))


SMALL, TWO = ("cust_supp", "emb_knn"), ("gcn", "graphsage")


EVERY = (1, 2, 3, 4)


def all_workers(spark, d, models=TWO, datasets=SMALL):
    return W.workload(spark, d, models, EVERY, datasets)


def all_workers_sql(models=TWO, datasets=SMALL) -> str:
    return workload_sql(models, EVERY, datasets)


SPEEDUPS = f"SELECT model, dataset, workers, max(training_ms) FILTER (piped = 0) / max(training_ms) FILTER (piped = 1) AS speedup FROM ({all_workers_sql()}) GROUP BY model, dataset, workers"


@query(f"SELECT model, dataset, workers, round(speedup, 6) AS speedup FROM ({SPEEDUPS})")
def speedup(spark, d):
    return rounded(M.speedup(all_workers(spark, d)), "speedup")


@query(f"SELECT model, dataset, workers, round(avg(speedup), 6) AS speedup FROM ({SPEEDUPS}) GROUP BY ROLLUP (model, dataset, workers)")
def wl_speedup_rollup(spark, d):
    return rounded(M.speedup(all_workers(spark, d)).rollup("model", "dataset", "workers").agg(F.avg("speedup").alias("speedup")), "speedup")


_TIME = f"SELECT model, dataset, max(training_ms) FILTER (workers = 1) AS t1, max(training_ms) FILTER (workers = 2) AS t2, max(training_ms) FILTER (workers = 3) AS t3, max(training_ms) FILTER (workers = 4) AS t4 FROM ({all_workers_sql()}) WHERE piped = 1 GROUP BY model, dataset"


@query(f"SELECT model, dataset, round(t1, 6) AS t1, round(t2, 6) AS t2, round(t3, 6) AS t3, round(t4, 6) AS t4, round(t1 / (4 * t4), 6) AS eff4 FROM ({_TIME})")
def scaling_pivot(spark, d):
    return rounded(M.scaling(all_workers(spark, d).where("piped = 1")), "t1", "t2", "t3", "t4", "eff4")


for _name, _how in (("results_cube", "CUBE (model, dataset)"), ("results_rollup", "ROLLUP (model, dataset)"), ("results_sets", "GROUPING SETS ((model), (dataset), ())")):

    @query(f"SELECT model, dataset, count(*) AS n, round(avg(training_ms), 6) AS ms FROM ({all_workers_sql()}) GROUP BY {_how}", _name)
    def _sets(spark, d, how=_name):
        r = all_workers(spark, d)
        if how == "results_sets":
            r.createOrReplaceTempView("gs_results")
            return rounded(spark.sql("SELECT model, dataset, count(*) AS n, avg(training_ms) AS ms FROM gs_results GROUP BY GROUPING SETS ((model), (dataset), ())"), "ms")
        g = r.cube("model", "dataset") if how == "results_cube" else r.rollup("model", "dataset")
        return rounded(g.agg(F.count("*").alias("n"), F.avg("training_ms").alias("ms")), "ms")


@query(f"SELECT model, piped, round(max(training_ms) FILTER (dataset = 'cust_supp'), 6) AS cust_supp, round(max(training_ms) FILTER (dataset = 'emb_knn'), 6) AS emb_knn FROM ({workload_sql(TWO, 2, SMALL)}) GROUP BY model, piped")
def results_pivot(spark, d):
    r = W.workload(spark, d, TWO, 2, SMALL)
    return rounded(r.groupBy("model", "piped").pivot("dataset", list(SMALL)).agg(F.max("training_ms")), *SMALL)


@query(f"SELECT model, piped, dataset, round(ms, 6) AS ms FROM (SELECT model, piped, dataset, training_ms AS ms FROM ({workload_sql(TWO, 2, SMALL)}))")
def results_unpivot(spark, d):
    wide = W.workload(spark, d, TWO, 2, SMALL).groupBy("model", "piped").pivot("dataset", list(SMALL)).agg(F.max("training_ms"))
    return rounded(wide.unpivot(["model", "piped"], list(SMALL), "dataset", "ms"), "ms")


def _util_sql(piped: bool) -> str:
    c = costs_sql(stats_sql("part_pair", "gcn"), W.SHAPES["part_pair"][0], 1, piped)
    if piped:
        return f"SELECT 1 AS piped, sum(compute) / max(finish_compute) AS busy, max(finish_compute) AS makespan FROM ({piped_sql(c, S.STAGES)})"
    return f"SELECT 0 AS piped, sum(compute) / max(finish_rest) AS busy, max(finish_rest) AS makespan FROM ({piped_sql(f'SELECT *, transfer + compute AS rest FROM ({c})', ('sampling', 'rest'))})"


@query(f"SELECT piped, round(busy, 6) AS busy, round(makespan, 6) AS makespan FROM ({_util_sql(False)} UNION ALL {_util_sql(True)})")
def wl_utilisation(spark, d):
    """Compute utilisation of a framework that only prefetches samples, and of the full pipeline with its cache."""
    stats, out = W.one_model(spark, d, "part_pair", "gcn"), None
    for piped in (False, True):
        c = W.costs_of(stats, W.SHAPES["part_pair"][0], 1, piped)
        f = S.schedule(c, "pipelined" if piped else "prefetch").join(c.select("k", "compute"), "k")
        one = f.agg((F.sum("compute") / F.max("finish_compute")).alias("busy"), F.max("finish_compute").alias("makespan")).select(F.lit(int(piped)).alias("piped"), "busy", "makespan")
        out = one if out is None else out.union(one)
    return rounded(out, "busy", "makespan")


@query(" UNION ALL ".join(f"SELECT '{n}' AS run, raw, size, memory_bound FROM ({_QSIZE.format(cap=16, src=costs_sql(stats_sql(n, 'gcn'), W.SHAPES[n][0], 1, False))})" for n in W.DATASETS))
def wl_queue_sizes(spark, d):
    out = None
    for n, stats in zip(W.DATASETS, W.all_stats(spark, d, W.DATASETS, ("gcn",))):
        c = W.costs_of(stats, W.SHAPES[n][0], 1, False).withColumn("run", F.lit(n))
        one = Q.queue_size(c, 16)
        out = one if out is None else out.union(one)
    return out


STALE_GRAPHS = ("turns", "geo_tree", "part_pair")


def _stale_sql() -> str:
    """Staleness under each graph's own period; the factor 3 makes periods above 1 occur on sparse graphs."""
    sizes = f"SELECT * FROM ({sizes_sql()}) WHERE graph IN {STALE_GRAPHS}"
    return f"WITH z AS MATERIALIZED (SELECT graph, greatest(1, ceil(3.0 * sqrt(n / (1.0 * m))))::INT AS period FROM ({sizes})), dl AS MATERIALIZED ({DELAYS_SQL}), rd AS (SELECT iter, receiver, max(iter + delay) AS ready FROM dl GROUP BY iter, receiver) SELECT graph, period, round(avg(least(ready, (ceil(iter / period) * period)::INT) - iter), 6) AS mean_staleness, max(least(ready, (ceil(iter / period) * period)::INT) - iter)::INT AS most FROM z, rd GROUP BY graph, period"


@query(_stale_sql())
def wl_staleness(spark, d):
    from ..operators import exchange as X

    z = graph_sizes(spark, d).where(F.col("graph").isin(*STALE_GRAPHS)).select("graph", F.greatest(F.lit(1), F.ceil(3.0 * F.sqrt(F.col("n") / F.col("m")))).cast("int").alias("period")).withColumn("one", F.lit(1))
    ready = X.update_schedule(X.arrivals(X.delay_table(spark, WORKERS, ITERS))).select("iter", "receiver", "ready").withColumn("one", F.lit(1))
    s = F.least(F.col("ready"), (F.ceil(F.col("iter") / F.col("period")) * F.col("period")).cast("int")) - F.col("iter")
    return z.join(ready, "one").groupBy("graph", "period").agg(F.round(F.avg(s), 6).alias("mean_staleness"), F.max(s).cast("int").alias("most"))


@query(" UNION ALL ".join(f"SELECT '{k}' AS graph, g::INT AS workers, p::INT AS p, round(p * {m}::BIGINT + {n}::DOUBLE / (p * g), 6) AS cost FROM (SELECT unnest(range(1, 5)) AS g), (SELECT unnest(range(1, 6)) AS p)" for k, (n, m) in PUBLISHED.items()))
def wl_period_cost(spark, d):
    out = None
    for k, (n, m) in PUBLISHED.items():
        one = spark.range(20).select(F.lit(k).alias("graph"), (F.col("id") % 4 + 1).cast("int").alias("workers"), (F.floor(F.col("id") / 4) + 1).cast("int").alias("p"))
        one = one.select("graph", "workers", "p", F.round(F.col("p") * F.lit(m).cast("long") + F.lit(float(n)) / (F.col("p") * F.col("workers")), 6).alias("cost"))
        out = one if out is None else out.union(one)
    return out


@query(f"SELECT policy, bytes, round(1 - bytes / max(bytes) OVER (), 6) AS saved FROM ({_policy_sql()})")
def wl_cache_ablation(spark, d):
    from pyspark.sql import Window

    p = cache_policy_bytes(spark, d)
    return p.select("policy", "bytes", F.round(1 - F.col("bytes") / F.max("bytes").over(Window.partitionBy()), 6).alias("saved"))


@query(f"SELECT variant, round(rmse, 4) AS rmse, round(bias, 4) AS bias FROM ({_err_sql(ERR_VARIANTS)})")
def wl_variant_error(spark, d):
    return estimator_runs(spark, d, ERR_VARIANTS).select("variant", F.round(r6("rmse"), 4).alias("rmse"), F.round(r6("bias"), 4).alias("bias"))
