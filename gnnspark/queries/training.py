"""Measured training: the ten samplers, plain and piped, metrics, staleness, repeats, a control, and the pipeline of one run."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import metrics as M
from ..operators.propagation import planted_label, smoothed_label
from ..plans.batches import MODELS, Sizes, kept
from ..plans.grid import Course, Run, train_grid
from ..plans.train import train
from ..sources.features import balance, customer_features, embedding_features, part_features, standing, standing_features, supplier_features, text_features
from ..sources.graphs import key, load_graph
from ..sources.spool import Spool
from ..sources.tables import read
from .base import graph_sql, query, split_sql, sql, u_sql

BATCH, EPOCHS, CLASSES_BOUND = 64, 5, 4096


def numbered(df: DataFrame, column: str) -> tuple[DataFrame, int]:
    """``df`` with ``y``, the place of its column's value among the distinct ones; all rows with a value stay.

    Distinct labels become outputs of the network, so more than :data:`CLASSES_BOUND` of them are an error.
    """
    names = df.where(F.col(column).isNotNull()).groupBy(column).count()
    n = names.count()
    if n > CLASSES_BOUND:
        raise ValueError(f"{n} labels: the network has at most {CLASSES_BOUND} outputs")
    placed = names.select(column, (F.row_number().over(Window.orderBy(column)) - 1).alias("y"))
    return df.join(F.broadcast(placed), column), n


def documents(spark: SparkSession, d: str, keep: Spool, width: int = 100):
    """(graph, trigram features, (node_id, y) with languages, classes) of the document graph."""
    docs = read(spark, d, "documents", "doc_id", "text", "lang").select(key("document", "doc_id").alias("node_id"), "text", "lang")
    feats = keep(text_features(docs.select("node_id", "text").repartition(spark.sparkContext.defaultParallelism), width))
    labels, n = numbered(docs.select("node_id", "lang"), "lang")
    return load_graph(spark, d, "docs_lex"), feats, keep(labels.select("node_id", "y")), n


def document_runs(spark: SparkSession, d: str, runs: list[Run], epochs: int = EPOCHS, layer: int = 64, patience: int = 200) -> DataFrame:
    keep = Spool(spark)
    g, feats, labels, n = documents(spark, d, keep)
    return train_grid(g, feats, labels, runs, Course((100, 32, n), rate=0.03, patience=patience), Sizes(BATCH, 5, layer, epochs), keep)


def named(runs: list[Run]):
    """(run, model, piped, workers, period) as a table: as many rows as there are runs."""
    each = [F.struct(F.lit(i).alias("run"), F.lit(r.model).alias("model"), F.lit(int(r.piped)).alias("piped"), F.lit(r.workers).alias("workers"), F.lit(r.period).alias("period"), F.lit(r.seed).alias("seed")) for i, r in enumerate(runs)]
    return lambda told: told.join(F.broadcast(told.sparkSession.range(1).select(F.inline(F.array(*each)))), "run")


def scores(told: DataFrame) -> DataFrame:
    """(run, test_rows, accuracy, f1_micro, f1_macro) from the scored test nodes."""
    pred = told.where("kind = 'test'").select("run", F.col("b").alias("y"), F.col("c").alias("yhat"))
    ends = pred.select("run", F.col("y").alias("k"), F.lit(1).alias("t"), F.lit(0).alias("p"), (F.col("y") == F.col("yhat")).cast("int").alias("tp")).union(pred.select("run", "yhat", F.lit(0), F.lit(1), F.lit(0)))
    per = ends.groupBy("run", "k").agg(F.sum("t").alias("t"), F.sum("p").alias("p"), F.sum("tp").alias("tp"))
    f1 = per.groupBy("run").agg((2.0 * F.sum("tp") / F.sum(F.col("t") + F.col("p"))).alias("f1_micro"), F.avg(2.0 * F.col("tp") / (F.col("t") + F.col("p"))).alias("f1_macro"))
    hit = pred.groupBy("run").agg(F.count("*").alias("test_rows"), F.avg((F.col("y") == F.col("yhat")).cast("double")).alias("accuracy"))
    return hit.join(f1, "run")


def courses(told: DataFrame) -> DataFrame:
    """(run, epochs, batches, best_epoch, val, stop_step, batch_ms, batch_sd, train_ms); batch times without the first and last 20 where there are more than 40."""
    val = told.where("kind = 'val'").groupBy("run").agg(F.count("*").alias("epochs"), F.max("a").alias("batches"), F.max("value").alias("val"))
    best = told.where("kind = 'best'").select("run", F.col("a").alias("best_epoch"))
    stop = told.where("kind = 'stop'").select("run", F.col("a").alias("stop_step"))
    ms = told.where("kind = 'ms'").select("run", "a", F.col("value").alias("ms"), F.count("*").over(Window.partitionBy("run")).alias("n"))
    steady = (F.col("n") <= 40) | F.col("a").between(20, F.col("n") - 21)
    time = ms.groupBy("run").agg(F.avg(F.when(steady, F.col("ms"))).alias("batch_ms"), F.stddev_samp(F.when(steady, F.col("ms"))).alias("batch_sd"), F.sum("ms").alias("train_ms"))
    return val.join(best, "run").join(stop, "run", "left").join(time, "run")


TWENTY = [Run(m, piped, 1 + piped, 1 + 2 * piped) for m in MODELS for piped in (False, True)]
_LABELLED = f"SELECT node_id, {split_sql('docs_lex')} AS split, lang FROM (SELECT doc_id + 6 * 1099511627776 AS node_id, lang FROM documents WHERE lang IS NOT NULL)"


def _models_sql() -> str:
    rows = ", ".join(f"('{r.model}', {int(r.piped)}, {r.workers})" for r in TWENTY)
    return f"SELECT model, piped, workers, (SELECT count(*) FROM ({_LABELLED}) WHERE split = 'test') AS test_rows, 1 AS above_majority, 1 AS batches_grow FROM (VALUES {rows}) v(model, piped, workers)"


@query(_models_sql())
def wl_train_accuracy(spark, d):
    """The ten samplers, plain with one worker and piped with two (late gradients, resync every three iterations), trained over whole epochs of the document graph.

    ``above_majority``: accuracy over all labelled test nodes lies more than 0.1 above the share of the most frequent language there.
    ``batches_grow``: every epoch has at least as many batches as the training split has lots of 64, but for empty hash buckets.
    """
    told = document_runs(spark, d, TWENTY)
    test = told.where("kind = 'test'")
    most = test.groupBy("run", "b").agg(F.count("*").alias("n")).groupBy("run").agg((F.max("n") / F.sum("n")).alias("majority"))
    lots = told.where("kind = 'val'").groupBy("run").agg((F.max("a") / F.count("*")).alias("per_epoch"))
    t = scores(told).join(most, "run").join(lots, "run")
    n = read(spark, d, "documents", "lang").where("lang is not null").count()
    checks = t.select("run", "test_rows", (F.col("accuracy") > F.col("majority") + 0.1).cast("int").alias("above_majority"), (F.col("per_epoch") >= 0.5 * n * 0.9 / BATCH).cast("int").alias("batches_grow"))
    return named(TWENTY)(checks).select("model", "piped", "workers", "test_rows", "above_majority", "batches_grow")


@query()
def wl_measured(spark, d):
    """Metric, F1, best epoch, early stop, and batch and training time of the twenty runs; the last two depend on the machine, so there is no SQL."""
    told = document_runs(spark, d, TWENTY)
    return named(TWENTY)(scores(told).join(courses(told), "run")).drop("run")


@query()
def metric_change(spark, d):
    """(model, dataset, workers, points): measured accuracy of the piped run less that of the plain run, in points, for two to four workers."""
    plain = [Run(m) for m in ("fastgcn", "ladies", "ladies_fd")]
    runs = plain + [Run(r.model, True, w, 3) for r in plain for w in (2, 3, 4)]
    t = named(runs)(scores(document_runs(spark, d, runs))).withColumn("metric", 100 * F.col("accuracy"))
    spread = t.where("piped = 0").drop("workers").withColumn("workers", F.explode(F.array(*map(F.lit, (2, 3, 4)))))
    both = spread.unionByName(t.where("piped = 1")).withColumn("dataset", F.lit("docs_lex"))
    return M.metric_change(both.select("model", "dataset", "workers", "piped", "metric"))


STALE = [Run("ladies", True, w, p) for w in (2, 3, 4) for p in (1, 2, 4, 8)]


def _stale_sql() -> str:
    """Staleness from the delays alone: iterations of an epoch have as many senders as batches are left for them."""
    n = f"(SELECT greatest(1, ceil(count(*) / {BATCH}.0))::BIGINT FROM ({_LABELLED}) WHERE split = 'train')"
    delay = f"CASE WHEN i = j THEN 0 ELSE floor(3 * {u_sql(7, chr(39) + 'delay' + chr(39), 't', 'i', 'j')})::BIGINT + CASE WHEN i = g - 1 THEN 2 ELSE 0 END END"
    ctes = [
        "v AS (SELECT * FROM (VALUES " + ", ".join(f"({r.workers}, {r.period})" for r in STALE) + ") v(g, p))",
        f"z AS MATERIALIZED (SELECT g, p, {n} AS n, ceil({n} / g::DOUBLE)::BIGINT AS per FROM v)",
        f"it AS (SELECT *, unnest(range(1, {EPOCHS} * per + 1)) AS t FROM z)",
        "snd AS (SELECT *, unnest(range(CASE WHEN t % per = 0 THEN n - (per - 1) * g ELSE g END)) AS i FROM it)",
        "rcv AS (SELECT *, unnest(range(g)) AS j FROM snd)",
        f"rd AS (SELECT g, p, t, j, any_value(per) AS per, max(t + {delay}) AS ready FROM rcv GROUP BY g, p, t, j)",
        "ap AS (SELECT g, p, t, per, least(ready, (ceil(t / p::DOUBLE) * p)::BIGINT) AS applied FROM rd)",
    ]
    return sql(ctes, f"SELECT g AS workers, p AS period, count(*) AS means, max(applied - t) AS most, round(avg(applied - t), 6) AS mean_staleness, 1 AS equal_after_resync, (p = 1)::INT AS always_equal FROM ap WHERE applied <= {EPOCHS} * per GROUP BY g, p")


@query(_stale_sql())
def wl_stale_training(spark, d):
    """Late gradients in real training runs, by workers and resync period: how stale the applied means were, and that models are equal after a resync.

    Means whose last gradient would arrive after the run's end are not applied.
    """
    told = document_runs(spark, d, STALE, patience=10**9)
    applied = told.where("kind = 'applied'").withColumn("late", F.col("c") - F.col("a"))
    stale = applied.groupBy("run").agg(F.count("*").alias("means"), F.max("late").alias("most"), F.round(F.avg("late"), 6).alias("mean_staleness"))
    with_run = named(STALE)
    spread = with_run(told.where("kind = 'spread'")).groupBy("run").agg(F.max(F.when(F.col("a") % F.col("period") == 0, F.col("value"))).alias("after"), F.max("value").alias("ever"))
    both = with_run(stale.join(spread, "run"))
    return both.select("workers", "period", "means", "most", "mean_staleness", (F.col("after") == 0).cast("int").alias("equal_after_resync"), (F.col("ever") == 0).cast("int").alias("always_equal"))


@query()
def wl_ten_runs(spark, d):
    """(model, piped, runs, accuracy mean and sd, batch ms mean and sd) over seeds 0 to 9."""
    runs = [Run("ladies", piped, 1 + piped, 1 + 2 * piped, seed) for piped in (False, True) for seed in range(10)]
    told = document_runs(spark, d, runs)
    t = named(runs)(scores(told).join(courses(told), "run"))
    mean = [f(c).alias(f"{c}_{n}") for c in ("accuracy", "f1_macro", "batch_ms", "train_ms") for f, n in ((F.avg, "mean"), (F.stddev_samp, "sd"))]
    return t.groupBy("model", "piped").agg(F.count("*").alias("runs"), *mean)


CONTROL = [Run("gcn"), Run("graphsage"), Run("ladies_fd", True, 2, 3)]


@query(f"SELECT model, piped, 1 AS near_chance FROM (VALUES {', '.join(f'({chr(39)}{r.model}{chr(39)}, {int(r.piped)})' for r in CONTROL)}) v(model, piped)")
def wl_control(spark, d):
    """Labels of the embeddings carry no signal: accuracy lies within four deviations of one in ten. A positive result would be a leak."""
    keep = Spool(spark)
    labels, n = numbered(read(spark, d, "embeddings", "vec_id", "label").select(F.col("vec_id").alias("node_id"), "label"), "label")
    told = train_grid(load_graph(spark, d, "emb_knn"), embedding_features(spark, d), labels.select("node_id", "y"), CONTROL, Course((64, 32, n), rate=0.01), Sizes(BATCH, 5, 64, 3), keep)
    t = named(CONTROL)(scores(told))
    chance, sd = 1.0 / n, F.sqrt(F.lit((1.0 / n) * (1 - 1.0 / n)) / F.col("test_rows"))
    return t.select("model", "piped", (F.abs(F.col("accuracy") - chance) < 4 * sd + 0.02).cast("int").alias("near_chance"))


def aucs(told: DataFrame, bins: int = 1024) -> DataFrame:
    """(run, test_rows, auc) from the scored test nodes of runs with two classes, by histograms of scores."""
    test = told.where("kind = 'test'").select("run", F.col("b").alias("y"), F.floor(F.col("value") * bins).alias("score"))
    by = test.groupBy("run", "score").agg(F.sum("y").alias("pos"), F.count("*").alias("n"))
    below = F.coalesce(F.sum("n").over(Window.partitionBy("run").orderBy("score").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = by.withColumn("rank", below + (F.col("n") + 1) / 2.0).groupBy("run")
    sums = ranked.agg(F.sum(F.col("rank") * F.col("pos")).alias("r"), F.sum("pos").alias("p"), F.sum("n").alias("test_rows"))
    pairs = F.col("p") * (F.col("test_rows") - F.col("p"))
    return sums.select("run", "test_rows", F.when(pairs > 0, (F.col("r") - F.col("p") * (F.col("p") + 1) / 2.0) / pairs).otherwise(0.5).alias("auc"))


@query()
def wl_planted_auc(spark, d):
    """(model, piped, val_auc, auc, test_rows) on customers and suppliers with the planted label: the measure of the imbalanced data set."""
    keep, runs = Spool(spark), [Run("graphsage"), Run("graphsage", True, 2, 3), Run("ladies"), Run("ladies", True, 2, 3)]
    g = kept(load_graph(spark, d, "cust_supp"), keep)
    feats = customer_features(spark, d).select("node_id", "f").union(supplier_features(spark, d).select("node_id", "f"))
    told = train_grid(g, keep(feats), keep(planted_label(g, balance(spark, d))), runs, Course((8, 32, 2), rate=0.02, metric="auc"), Sizes(BATCH, 5, 128, EPOCHS), keep, is_kept=True)
    val = told.where("kind = 'best'").select("run", F.col("value").alias("val_auc"))
    return named(runs)(aucs(told).join(val, "run")).select("model", "piped", "val_auc", "auc", "test_rows")


def experiment(spark: SparkSession, d: str, name: str, keep: Spool):
    """(graph, features, (node_id, y), course) of one of the four data sets: smoothed labels by AUC, the embeddings' own labels by accuracy."""
    g = kept(load_graph(spark, d, name), keep)
    if name == "emb_knn":
        labels, n = numbered(read(spark, d, "embeddings", "vec_id", "label").select(F.col("vec_id").alias("node_id"), "label"), "label")
        return g, keep(embedding_features(spark, d)), keep(labels.select("node_id", "y")), Course((64, 32, n), rate=0.01)
    width, high = {"cust_supp": 8, "cust_part": 16, "part_pair": 128}[name], standing(spark, d)
    feats = standing_features(spark, d, width) if name != "part_pair" else part_features(spark, d, width - 1).join(high, "node_id").select("node_id", F.concat(F.array(F.col("x").cast("float")), "f").alias("f"))
    return g, keep(feats), keep(smoothed_label(g, None, high)), Course((width, 32, 2), rate=0.02, metric="auc")


GRID = [Run(m, piped, w, 3 if piped else 1) for m in MODELS for w in (1, 2, 3, 4) for piped in (False, True)]


def worker_time(told: DataFrame, runs: list[Run]) -> DataFrame:
    """(run, train_ms): computation of a run on its workers. Plain runs wait for the slowest worker in every iteration, piped ones only at the end."""
    ms = named(runs)(told.where("kind = 'ms'").select("run", "epoch", F.col("a").alias("batch"), F.col("b").alias("worker"), F.col("value").alias("ms")))
    first = F.min("batch").over(Window.partitionBy("run", "epoch"))
    turn = F.when(F.col("piped") == 0, F.struct("epoch", F.floor((F.col("batch") - first) / F.col("workers")).alias("turn")))
    steps = ms.withColumn("turn", turn).groupBy("run", "turn", "worker").agg(F.sum("ms").alias("ms"))
    return steps.groupBy("run", "turn").agg(F.max("ms").alias("ms")).groupBy("run").agg(F.sum("ms").alias("train_ms"))


def measured(spark: SparkSession, d: str, name: str, runs: list[Run], epochs: int, layer: int = 512) -> DataFrame:
    """(model, workers, piped, test_rows, metric, epochs, batches, best_epoch, val, stop_step, batch_ms, batch_sd, train_ms) of training runs on one data set, in one job."""
    keep = Spool(spark)
    g, feats, labels, course = experiment(spark, d, name, keep)
    told = train_grid(g, feats, labels, runs, course, Sizes(BATCH, 5, layer, epochs), keep, is_kept=True)
    metric = aucs(told).withColumnRenamed("auc", "metric") if course.metric == "auc" else scores(told).select("run", "test_rows", F.col("accuracy").alias("metric"))
    t = metric.join(courses(told).drop("train_ms"), "run").join(worker_time(told, runs), "run")
    return named(runs)(t).drop("run", "period", "seed")


# epochs: the split of customers and parts trains on a tenth of the nodes, so its epochs are short
LENGTHS = {"cust_supp": 3, "emb_knn": 3, "part_pair": 3, "cust_part": 8}

for _name, _epochs in LENGTHS.items():

    @query(name=f"wl_measured_{_name}")
    def _measured(spark, d, name=_name, epochs=_epochs):
        """The ten samplers, plain and piped, on one to four workers of one data set, trained and measured; times depend on the machine, so there is no SQL."""
        return measured(spark, d, name, GRID, epochs)


LEARNS = [Run(m, piped, 1 + piped, 1 + 2 * piped) for m in ("graphsage", "ladies") for piped in (False, True)]


def _learns_sql() -> str:
    rows = ", ".join(f"('{r.model}', {int(r.piped)}, {r.workers})" for r in LEARNS)
    return sql([*graph_sql("cust_part"), f"k AS (SELECT {split_sql('cust_part')} AS split FROM n)"], f"SELECT model, piped, workers, (SELECT count(*) FROM k WHERE split = 'test') AS test_rows, 1 AS above_chance FROM (VALUES {rows}) v(model, piped, workers)")


@query(_learns_sql())
def wl_learns_cust_part(spark, d):
    """On customers and parts every test node is scored, and the area under the curve lies above 0.5 by more than four deviations of a ranking by chance (two classes of one half each)."""
    t = measured(spark, d, "cust_part", LEARNS, LENGTHS["cust_part"])
    sd = F.sqrt((F.col("test_rows") + 1) / (3.0 * F.col("test_rows") * F.col("test_rows")))
    return t.select("model", "piped", "workers", "test_rows", (F.col("metric") > 0.5 + 4 * sd).cast("int").alias("above_chance"))


@query()
def wl_train_pipeline(spark, d):
    """(piped, seconds, busy, peak, queue_size, peak_mb, val, test): one run of the cluster form, stage after stage and with overlapped stages.

    ``busy`` is the share of the compute stage in the run's time, ``peak`` the largest mean over 150 ms; both from measured spans.
    """
    out = None
    for piped in (False, True):
        keep = Spool(spark)
        g, feats, labels, n = documents(spark, d, keep)
        run = train(g, feats, labels, (100, 32, n), "ladies", piped, 1, epochs=4, span=1, batch=BATCH, size=64, rate=0.03)
        end = max(t[4] for t in run.timings)
        spans = spark.createDataFrame([(0, 1000 * a, 1000 * b) for _, _, stage, a, b in run.timings if stage == "compute"], "run int, start_ms double, end_ms double")
        told = {k: v for _, k, v in run.history}
        one = M.utilisation(spans, 10, 150).select(F.lit(int(piped)).alias("piped"), F.lit(end).alias("seconds"), "mean", "peak", F.lit(run.queue_sizes[-1]).alias("queue_size"), F.lit(run.peak_bytes / 2**20).alias("peak_mb"), F.lit(told["val"]).alias("val"), F.lit(told["test"]).alias("test")).withColumnRenamed("mean", "busy")
        out = one if out is None else out.union(one)
    return out
