"""Schedules, queues, model rows, exchange, period and measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import exchange as X
from ..operators import metrics as M
from ..operators import model as N
from ..operators import sync
from ..operators.propagation import propagation
from ..plans import queues as Q
from ..plans import schedule as S
from ..plans import workloads as W
from ..sources.features import embedding_features, exploded
from ..sources.graphs import NAMES, load_graph
from ..sources.tables import read
from .base import graph_sql, prop_sql, query, r6, sql, u_sql
from .caching import DEG, ONE_PERCENT, degree_sql, draw_sql, train_sql
from .sampling import TWO_HOPS, layers_sql

# ---- batch statistics and the cost clock ----


def stats_sql(dataset: str, model: str, models: tuple[str, ...] | None = None) -> str:
    """A query for (batch_id, touched, edges, inputs, missing, act, flops) of an epoch."""
    (d0, classes), m, models = W.SHAPES[dataset], 2 if model == "graphsage" else 1, models or (model,)
    node = model in ("gcn", "graphsage")
    i = next(k for k, x in enumerate(models) if x == model or node and x in ("gcn", "graphsage"))
    lots = f"(SELECT greatest(1, ceil(count(*) / {W.BATCH}.0))::BIGINT FROM tr)"
    seeds = f"s AS MATERIALIZED (SELECT {i} * {lots} + floor({u_sql(7, chr(39) + 'batch' + chr(39), 0, 'node_id')} * {lots})::BIGINT AS batch_id, node_id FROM tr)"
    ctes = [*(graph_sql(dataset) if node else prop_sql(dataset)), train_sql(dataset), seeds, DEG, degree_sql(), draw_sql("ch", ONE_PERCENT), *(TWO_HOPS if node else layers_sql(model, size=W.SIZE))]
    b1, b0, rows, inputs, extra = ("b1", "b0", "f1", "f0", 0) if node else ("k1", "k0", "c1", "c0", 1)
    per = lambda t, n="count(*)", more="": f"(SELECT batch_id, {n} AS n FROM {t} {more} GROUP BY batch_id)"
    touched = f"(SELECT batch_id, sum(coalesce(deg, 0) + {extra}) AS n FROM (SELECT batch_id, node_id FROM s UNION ALL SELECT batch_id, node_id FROM {rows}) LEFT JOIN dg USING (node_id) GROUP BY batch_id)"
    names = {"t": touched, "e1": per(b1), "e0": per(b0), "r1": per("s"), "r0": per(rows), "i": per(inputs), "ms": per(inputs, more="WHERE node_id NOT IN (SELECT node_id FROM ch)")}
    joins = " ".join(f"LEFT JOIN {q} {k} ON {k}.batch_id = z.batch_id" for k, q in names.items())
    c = {k: f"coalesce({k}.n, 0)" for k in names}
    flops = f"{c['e0']} * {d0} + {c['r0']} * {m * d0 * W.HIDDEN} + {c['e1']} * {W.HIDDEN} + {c['r1']} * {m * W.HIDDEN * classes}"
    return sql(ctes, f"SELECT z.batch_id % {lots} AS batch_id, {c['t']}::BIGINT AS touched, {c['e1']} + {c['e0']} AS edges, {c['i']} AS inputs, {c['ms']} AS missing, {c['r0']} * {W.HIDDEN} + {c['r1']} * {classes} AS act, ({flops})::BIGINT AS flops FROM (SELECT DISTINCT batch_id FROM s) z {joins}")


def costs_sql(stats: str, width: int, workers: int, piped: bool) -> str:
    b = f"{'missing' if piped else 'inputs'} * {width * 4}"
    return f"SELECT 0 AS run, (batch_id % {workers})::INT AS worker, batch_id // {workers} AS k, 1.0::DOUBLE + touched * 1e-4 AS sampling, 0.5::DOUBLE + ({b}) / 1e6 AS transfer, 0.5::DOUBLE + flops * 3e-6 AS compute, {W.SHARE_MS * (workers - 1)}::DOUBLE AS share, ({b})::BIGINT AS bytes FROM ({stats})"


def piped_sql(costs: str, stages) -> str:
    """The max-plus recurrence as nested windows; finish_<stage> columns."""
    q, ready = costs, "0.0"
    for s in stages:
        w = "OVER (PARTITION BY run, worker ORDER BY k)"
        q = f"SELECT *, c_{s} + max(rd_{s} - (c_{s} - {s})) {w} AS finish_{s} FROM (SELECT *, sum({s}) {w} AS c_{s}, {ready} AS rd_{s} FROM ({q}))"
        ready = f"finish_{s}"
    return q


COST = costs_sql(stats_sql("cust_part", "gcn"), 16, 2, False)
FINISH = "SELECT run, worker, k, " + ", ".join(f"round(finish_{s}, 6) AS finish_{s}" for s in S.STAGES)


def costs(spark, d, workers: int = 2):
    return W.costs_of(W.one_model(spark, d, "cust_part", "gcn"), 16, workers, False)


def rounded(df, *names):
    return df.withColumns({n: r6(n) for n in names})


def finishes(df):
    return rounded(df, *[f"finish_{s}" for s in S.STAGES])


@query(f"SELECT run, worker, k, round(sampling, 6) AS sampling, round(transfer, 6) AS transfer, round(compute, 6) AS compute, bytes FROM ({COST})")
def stage_costs(spark, d):
    return rounded(costs(spark, d), *S.STAGES).drop("share")


_W = "OVER (PARTITION BY run, worker ORDER BY k)"


@query(f"{FINISH} FROM (SELECT run, worker, k, b + sampling AS finish_sampling, b + sampling + transfer AS finish_transfer, b + sampling + transfer + compute AS finish_compute FROM (SELECT *, sum(sampling + transfer + compute) {_W} - (sampling + transfer + compute) AS b FROM ({COST})))")
def sched_serial(spark, d):
    return finishes(S.schedule(costs(spark, d), "serial"))


@query(f"{FINISH} FROM (SELECT *, finish_rest - compute AS finish_transfer, finish_rest AS finish_compute FROM ({piped_sql(f'SELECT *, transfer + compute AS rest FROM ({COST})', ('sampling', 'rest'))}))")
def sched_prefetch(spark, d):
    return finishes(S.schedule(costs(spark, d), "prefetch"))


@query(f"{FINISH} FROM ({piped_sql(COST, S.STAGES)})")
def sched_pipelined(spark, d):
    return finishes(S.schedule(costs(spark, d), "pipelined"))


def bounded_sql(costs_: str, q: int) -> str:
    """Recursive CTE that carries the start times of the later stages."""
    slot = lambda name: f"CASE WHEN r.i >= {q} THEN r.{name}[r.i - {q} + 1] ELSE 0.0 END"
    return f"""WITH RECURSIVE c AS MATERIALIZED ({costs_}),
    a AS (SELECT *, (row_number() {_W}) - 1 AS i FROM c),
    r AS (
      SELECT run, worker, i + 1 AS i, k, sampling AS f0, sampling + transfer AS f1, sampling + transfer + compute AS f2, [sampling] AS s1, [sampling + transfer] AS s2 FROM a WHERE i = 0
      UNION ALL
      SELECT run, worker, i + 1, k, f0, f1, x2 + compute, list_append(s1, x1), list_append(s2, x2) FROM (
        SELECT *, greatest(f1, p2) AS x2 FROM (
          SELECT *, x1 + transfer AS f1 FROM (
            SELECT *, greatest(f0, p1, z2) AS x1 FROM (
              SELECT r.run, r.worker, r.i, a.k, greatest(r.f0, {slot('s1')}) + a.sampling AS f0, r.f1 AS p1, r.f2 AS p2, {slot('s2')} AS z2, r.s1, r.s2, a.transfer, a.compute
              FROM r JOIN a ON a.run = r.run AND a.worker = r.worker AND a.i = r.i)))))
    SELECT run, worker, k, f0 AS finish_sampling, f1 AS finish_transfer, f2 AS finish_compute FROM r"""


@query(f"{FINISH} FROM ({bounded_sql(COST, 2)})")
def sched_bounded_q2(spark, d):
    return finishes(S.schedule(costs(spark, d), "pipelined", 2))


F4_PREP, F4_COMPUTE = [2, 2, 2, 2, 2, 14, 2, 2], 5
F4_SQL = f"SELECT 0 AS run, 0 AS worker, k - 1 AS k, [{', '.join(map(str, F4_PREP))}][k]::DOUBLE AS sampling, 0.0::DOUBLE AS transfer, {F4_COMPUTE}.0::DOUBLE AS compute FROM (SELECT unnest(range(1, 9)) AS k)"


def f4_costs(spark):
    k = F.col("id").cast("int")
    return spark.range(8).select(F.lit(0).alias("run"), F.lit(0).alias("worker"), F.col("id").alias("k"), F.element_at(F.array(*[F.lit(float(x)) for x in F4_PREP]), k + 1).alias("sampling"), F.lit(0.0).alias("transfer"), F.lit(float(F4_COMPUTE)).alias("compute"))


@query(f"SELECT k, round(finish_compute, 6) AS finish FROM ({piped_sql(F4_SQL, S.STAGES)})")
def sched_bounded_formula(spark, d):
    """With the formula's queue size the worked example reaches the unbounded times."""
    return S.schedule(f4_costs(spark), "pipelined", 3, ("sampling", "compute")).select("k", r6("finish_compute").alias("finish"))


@query("SELECT * FROM (VALUES (1, 51.0::DOUBLE, 11.0::DOUBLE), (2, 46.0, 6.0), (3, 42.0, 2.0), (4, 42.0, 2.0), (5, 42.0, 2.0), (6, 42.0, 2.0), (7, 42.0, 2.0), (8, 42.0, 2.0)) v(queue, makespan, waiting)")
def queue_sweep(spark, d):
    swept = None
    for q in range(1, 9):
        one = S.makespans(S.schedule(f4_costs(spark), "pipelined", q, ("sampling", "compute"))).select(F.lit(q).alias("queue"), "makespan", (F.col("makespan") - 40.0).alias("waiting"))
        swept = one if swept is None else swept.union(one)
    return swept


_QSIZE = "SELECT run, ceil(max(sampling + transfer) / avg(compute))::BIGINT AS raw, greatest(1, least({cap}, greatest(2, ceil(max(sampling + transfer) / avg(compute))::BIGINT))) AS size, ({cap} < greatest(2, ceil(max(sampling + transfer) / avg(compute))))::INT AS memory_bound FROM ({src}) GROUP BY run"


_SPENT = "(SELECT '{k}' || l_returnflag AS run, l_quantity::DOUBLE AS sampling, l_tax::DOUBLE AS transfer, {c}::DOUBLE + l_quantity::DOUBLE / 5 AS compute FROM lineitem)"
_CASES = {"open": (1.0, 99), "floor": (60.0, 9), "cap": (1.0, 3)}


@query(" UNION ALL ".join(_QSIZE.format(cap=cap, src=_SPENT.format(k=k, c=c)) for k, (c, cap) in _CASES.items()))
def queue_size(spark, d):
    """Lines of orders as batches, a run for each return flag: with room, at the least size, and bound by memory."""
    lines, out = read(spark, d, "lineitem", "l_returnflag", "l_quantity", "l_tax"), None
    for k, (c, cap) in _CASES.items():
        t = lines.select(F.concat(F.lit(k), "l_returnflag").alias("run"), F.col("l_quantity").cast("double").alias("sampling"), F.col("l_tax").cast("double").alias("transfer"), (c + F.col("l_quantity").cast("double") / 5).alias("compute"))
        one = Q.queue_size(t, cap)
        out = one if out is None else out.union(one)
    return out


@query(f"SELECT 0 AS run, floor((1e6 - 2e5 * 1.1) / max(inputs * 64 + edges * 20 + act * 4))::BIGINT AS cap FROM ({stats_sql('cust_part', 'gcn')}) UNION ALL SELECT 1, floor((24576 - 730.95 * 1.1) / 100.0)::BIGINT")
def queue_cap(spark, d):
    stats = Q.batch_memory(W.one_model(spark, d, "cust_part", "gcn").withColumn("run", F.lit(0)), 16)
    literal = spark.range(1).select(F.lit(1).alias("run"), F.lit(100.0).alias("mem"))
    return Q.queue_cap(stats, 1e6, 2e5).union(Q.queue_cap(literal, 24576, 730.95))


@query(f"SELECT 0 AS run, 0 AS epoch, 2::BIGINT AS size UNION ALL SELECT run, 1, size FROM ({_QSIZE.format(cap=9, src=COST)})")
def queue_adapt(spark, d):
    return Q.adapt_queue(costs(spark, d).withColumn("epoch", F.lit(0)), 9)


@query(f"SELECT batch_id, inputs * 64 + edges * 20 + act * 4 AS mem FROM ({stats_sql('cust_part', 'gcn')})")
def batch_memory(spark, d):
    return Q.batch_memory(W.one_model(spark, d, "cust_part", "gcn"), 16).select("batch_id", "mem")


@query("SELECT 1 AS queue_bound_ok")
def queue_bound_ok(spark, d):
    """Real producers and consumers of batches of orders never hold more than the bound, and no order is lost."""
    import threading

    q, got = Q.BoundedQueues(3, 2), 0
    batch = (F.col("o_orderkey") % 40).cast("int").alias("batch")
    orders = {r["batch"]: r["n"] for r in read(spark, d, "orders", "o_orderkey").groupBy(batch).agg(F.count("*").alias("n")).collect()}
    workers = [threading.Thread(target=lambda w=w: [q.put("host", w, orders.get(2 * i + w, 0)) for i in range(20)]) for w in range(2)]
    for t in workers:
        t.start()
    for w in range(2):
        for _ in range(20):
            got += q.get("host", w)
    for t in workers:
        t.join()
    return spark.range(1).select(F.lit(int(max(q.most.values()) <= 3 and got == sum(orders.values()))).alias("queue_bound_ok"))


@query(f"SELECT run, round(sum(sampling + transfer) / sum(sampling + transfer + compute), 6) AS loading FROM ({COST}) GROUP BY run")
def stage_share(spark, d):
    return rounded(M.stage_share(costs(spark, d)), "loading")


# ---- model in rows ----

DIM, HID, CLASSES = 4, 3, 10
NET = [*prop_sql("emb_knn"), f"s AS MATERIALIZED (SELECT node_id FROM n ORDER BY {u_sql(7, chr(39) + 'net' + chr(39), 'node_id')}, node_id LIMIT 16)", "hid AS MATERIALIZED (SELECT DISTINCT col AS node_id FROM p JOIN s ON row = s.node_id)", f"x AS MATERIALIZED (SELECT node_id, i - 1 AS pos, v::DOUBLE AS x FROM (SELECT vec_id AS node_id, generate_subscripts(embedding, 1) AS i, unnest(embedding) AS v FROM embeddings) WHERE i <= {DIM})", f"w AS MATERIALIZED (SELECT layer, i, j, (2 * {u_sql(7, chr(39) + 'w' + chr(39), 'layer', 'i', 'j')} - 1) * sqrt(6.0::DOUBLE / (a + b)) AS w FROM (SELECT 1 AS layer, {DIM} AS a, {HID} AS b, unnest(range({DIM * HID})) AS c UNION ALL SELECT 2, {HID}, {CLASSES}, unnest(range({HID * CLASSES}))) q, LATERAL (SELECT (c // b)::INT AS i, (c % b)::INT AS j))", "inner_ AS MATERIALIZED (SELECT row AS dst, col AS src, w FROM p JOIN hid ON row = hid.node_id)", "outer_ AS MATERIALIZED (SELECT row AS dst, col AS src, w FROM p JOIN s ON row = s.node_id)", "ax AS MATERIALIZED (SELECT dst AS node_id, pos, sum(w * x) AS x FROM inner_ JOIN x ON src = x.node_id GROUP BY ALL)", "z1 AS MATERIALIZED (SELECT node_id, j AS pos, sum(x * w) AS x FROM ax JOIN w ON layer = 1 AND pos = i GROUP BY ALL)", "h1 AS MATERIALIZED (SELECT node_id, pos, greatest(x, 0.0) AS x FROM z1)", "ahh AS MATERIALIZED (SELECT dst AS node_id, pos, sum(w * x) AS x FROM outer_ JOIN h1 ON src = h1.node_id GROUP BY ALL)", "z2 AS MATERIALIZED (SELECT node_id, j AS pos, sum(x * w) AS x FROM ahh JOIN w ON layer = 2 AND pos = i GROUP BY ALL)", "sm AS MATERIALIZED (SELECT node_id, pos, e / sum(e) OVER (PARTITION BY node_id) AS p FROM (SELECT *, exp(x - max(x) OVER (PARTITION BY node_id)) AS e FROM z2))", "y AS (SELECT vec_id AS node_id, label AS y FROM embeddings JOIN s ON vec_id = node_id)", "g2 AS MATERIALIZED (SELECT node_id, pos, (p - (pos = y)::INT) / 16.0::DOUBLE AS x FROM sm JOIN y USING (node_id))", "dhid AS MATERIALIZED (SELECT src AS node_id, i AS pos, sum(o.w * g2.x * w.w) AS x FROM outer_ o JOIN g2 ON o.dst = g2.node_id JOIN w ON w.layer = 2 AND w.j = g2.pos GROUP BY ALL)", "g1 AS MATERIALIZED (SELECT dhid.* FROM dhid JOIN z1 USING (node_id, pos) WHERE z1.x > 0)", "gr AS MATERIALIZED (SELECT 1 AS layer, ax.pos AS i, g1.pos AS j, sum(ax.x * g1.x) AS g FROM ax JOIN g1 USING (node_id) GROUP BY ALL UNION ALL SELECT 2, ahh.pos, g2.pos, sum(ahh.x * g2.x) FROM ahh JOIN g2 USING (node_id) GROUP BY ALL)"]


def shape(spark, d) -> tuple[int, int]:
    """(width of the embeddings, number of their labels)."""
    return tuple(read(spark, d, "embeddings", "embedding", "label").agg(F.max(F.size("embedding")), F.countDistinct("label")).first())


class Net:
    def __init__(self, spark, d):
        from ..functions.hashing import uniform

        g = load_graph(spark, d, "emb_knn")
        prop = propagation(g).select(F.col("row").alias("dst"), F.col("col").alias("src"), "w")
        self.seeds = g.nodes.select("node_id").orderBy(uniform(7, "net", F.col("node_id")), "node_id").limit(16)
        self.outer = prop.join(self.seeds.withColumnRenamed("node_id", "dst"), "dst", "left_semi")
        self.rows = self.outer.select(F.col("src").alias("node_id")).distinct()
        self.inner = prop.join(self.rows.withColumnRenamed("node_id", "dst"), "dst", "left_semi")
        self.x = exploded(embedding_features(spark, d)).where(F.col("pos") < DIM)
        self.params = N.init_params(spark, (DIM, HID, CLASSES))
        self.labels = read(spark, d, "embeddings", "vec_id", "label").select(F.col("vec_id").alias("node_id"), F.col("label").alias("y")).join(self.seeds, "node_id", "left_semi")


INIT = ["sh AS MATERIALIZED (SELECT max(len(embedding)) AS wide, count(DISTINCT label) AS classes FROM embeddings)", f"w AS (SELECT layer, i, j, (2 * {u_sql(7, chr(39) + 'w' + chr(39), 'layer', 'i', 'j')} - 1) * sqrt(6.0::DOUBLE / (a + b)) AS w FROM (SELECT 1 AS layer, wide AS a, {HID} AS b, unnest(range(wide * {HID})) AS c FROM sh UNION ALL SELECT 2, {HID}, classes, unnest(range({HID} * classes)) FROM sh) q, LATERAL (SELECT (c // b)::INT AS i, (c % b)::INT AS j))"]


@query(sql(INIT, "SELECT layer, i, j, round(w, 6) AS w FROM w"))
def params_init(spark, d):
    """The network over whole embeddings, with an output for each of their labels."""
    width, classes = shape(spark, d)
    return rounded(N.init_params(spark, (width, HID, classes)), "w")


@query(sql(NET, "SELECT node_id, pos, round(x, 6) AS x FROM ax"))
def gather_only(spark, d):
    n = Net(spark, d)
    return rounded(N.gather(n.inner, n.x), "x")


@query(sql(NET, "SELECT node_id, pos, round(x, 6) AS x FROM z2"))
def gcn_forward(spark, d):
    n = Net(spark, d)
    return rounded(N.gcn_forward(n.inner, n.outer, n.x, n.params)["z2"], "x")


@query(sql([*NET, "mn AS (SELECT dst, 1.0::DOUBLE / count(*) AS w FROM a JOIN s ON dst = s.node_id GROUP BY dst)", "cc AS (SELECT a.dst AS node_id, pos, sum(mn.w * x) AS x FROM a JOIN mn USING (dst) JOIN x ON src = x.node_id GROUP BY ALL UNION ALL SELECT x.node_id, pos + 4, x FROM x JOIN s USING (node_id))", f"w8 AS (SELECT i, j, (2 * {u_sql(7, chr(39) + 'w' + chr(39), 1, 'i', 'j')} - 1) * sqrt(6.0::DOUBLE / 11) AS w FROM (SELECT unnest(range(24)) AS c) q, LATERAL (SELECT (c // 3)::INT AS i, (c % 3)::INT AS j))"], "SELECT node_id, j AS pos, round(sum(x * w), 6) AS x FROM cc JOIN w8 ON pos = i GROUP BY node_id, j"))
def sage_forward(spark, d):
    n = Net(spark, d)
    g = load_graph(spark, d, "emb_knn")
    near = g.edges.select("dst", "src").join(n.seeds.withColumnRenamed("node_id", "dst"), "dst", "left_semi")
    deg = near.groupBy("dst").agg((F.lit(1.0) / F.count("*")).alias("w"))
    w = N.weights(N.init_params(spark, (2 * DIM, HID)), 1)
    return rounded(N.sage_layer(near.join(deg, "dst"), n.x, n.seeds, w, DIM), "x")


@query(sql(NET, "SELECT round(sum(-ln(greatest(p, 1e-12))), 6) AS loss, count(*) AS n FROM sm JOIN y USING (node_id) WHERE pos = y"))
def softmax_loss(spark, d):
    n = Net(spark, d)
    return rounded(N.softmax_loss(N.gcn_forward(n.inner, n.outer, n.x, n.params)["z2"], n.labels), "loss")


@query("SELECT round(avg(-CASE WHEN l_returnflag = 'R' THEN ln(p) ELSE ln(1 - p) END), 6) AS loss, count(*) AS n FROM (SELECT l_returnflag, l_quantity::DOUBLE / 51 AS p FROM lineitem)")
def bce_loss(spark, d):
    """How well a line's quantity, as a probability, tells that it was returned."""
    rows = read(spark, d, "lineitem", "l_returnflag", "l_quantity").select((F.col("l_returnflag") == "R").cast("int").alias("y"), (F.col("l_quantity").cast("double") / 51).alias("p"))
    return rounded(N.bce_loss(rows, "mean"), "loss")


@query(sql(NET, "SELECT layer, i, j, round(g, 6) AS g FROM gr"))
def grad_one_step(spark, d):
    n = Net(spark, d)
    return rounded(N.gcn_gradients(n.inner, n.outer, n.x, n.params, n.labels), "g")


@query(sql(NET, "SELECT layer, i, j, round(w - 0.1 * coalesce(g, 0), 6) AS w FROM w LEFT JOIN gr USING (layer, i, j)"))
def sgd_step(spark, d):
    n = Net(spark, d)
    return rounded(N.sgd_step(n.params, N.gcn_gradients(n.inner, n.outer, n.x, n.params, n.labels), 0.1), "w")


@query(sql(NET, "SELECT layer, i, j, round(w - 0.001 * gg / (abs(gg) + 1e-8), 6) AS w FROM (SELECT w.*, round(coalesce(g, 0), 9) AS gg FROM w LEFT JOIN gr USING (layer, i, j))"))
def adam_step(spark, d):
    n = Net(spark, d)
    g = N.gcn_gradients(n.inner, n.outer, n.x, n.params, n.labels).withColumn("g", F.round("g", 9))
    return rounded(N.adam_step(n.params, g).select("layer", "i", "j", "w"), "w")


@query(sql(NET, "SELECT node_id, pos, round(x, 6) AS x FROM z2"))
def udf_forward(spark, d):
    """The same logits by a numpy kernel over one packaged batch."""
    import numpy as np
    import pandas as pd

    from ..operators import kernels
    from ..plans.batches import packed, unpacked

    n = Net(spark, d)
    e = n.inner.select(F.lit(0).alias("layer"), "dst", "src", "w").union(n.outer.select(F.lit(1), "dst", "src", "w")).agg(F.sort_array(F.collect_list(F.struct("layer", "dst", "src", "w"))).alias("blocks"))
    needed = n.inner.select(F.col("src").alias("node_id")).union(n.rows).distinct()
    f = embedding_features(spark, d).join(needed, "node_id", "left_semi").select("node_id", F.slice("f", 1, DIM).alias("f")).agg(F.sort_array(F.collect_list(F.struct("node_id", "f"))).alias("x"))
    s = n.labels.agg(F.sort_array(F.collect_list(F.struct("node_id", "y"))).alias("seeds"))
    one = e.withColumn("k", F.lit(1)).join(f.withColumn("k", F.lit(1)), "k").join(s.withColumn("k", F.lit(1)), "k").select(*packed())
    params = kernels.init((DIM, HID, CLASSES))

    def go(batches):
        for pdf in batches:
            for row in pdf.itertuples():
                b = unpacked(row)
                out = kernels.forward(b, params)
                z = out["a2"] @ params[1]
                ids = row.seeds
                yield pd.DataFrame({"node_id": np.repeat(ids, CLASSES), "pos": np.tile(np.arange(CLASSES), len(ids)).astype("int32"), "x": z.ravel()})

    return rounded(one.mapInPandas(go, "node_id long, pos int, x double"), "x")


# ---- exchange ----

WORKERS, ITERS, PERIOD = 4, 20, 5
DELAYS_SQL = f"SELECT iter::INT AS iter, sender::INT AS sender, receiver::INT AS receiver, (CASE WHEN sender = receiver THEN 0 ELSE floor(3 * {u_sql(7, chr(39) + 'delay' + chr(39), 'iter', 'sender', 'receiver')})::INT + CASE WHEN sender = {WORKERS - 1} THEN 2 ELSE 0 END END)::INT AS delay FROM (SELECT unnest(range(1, {ITERS + 1})) AS iter), (SELECT unnest(range({WORKERS})) AS sender), (SELECT unnest(range({WORKERS})) AS receiver)"
GRAD = u_sql(7, "'g'", "iter", "sender")
EX = [f"dl AS MATERIALIZED ({DELAYS_SQL})", f"ar AS MATERIALIZED (SELECT *, iter + delay AS arrive, {GRAD} AS g FROM dl)", "gm AS (SELECT iter, avg(g) AS g FROM ar WHERE receiver = 0 GROUP BY iter)", f"us AS MATERIALIZED (SELECT iter, receiver, max(arrive) AS ready, least(max(arrive), (ceil(iter / {PERIOD}) * {PERIOD})::INT) AS applied FROM ar GROUP BY iter, receiver)"]


LOADS_SQL = f"ld AS MATERIALIZED (SELECT (l_partkey % {ITERS} + 1)::INT AS iter, (l_suppkey % {WORKERS})::INT AS sender, sum(l_quantity::BIGINT)::BIGINT AS load, avg(l_discount::DOUBLE) AS g FROM lineitem GROUP BY ALL)"
WORK_SQL = f"(SELECT i::INT AS iter, s::INT AS sender, r::INT AS receiver, (CASE WHEN s = r THEN 0 ELSE (coalesce(load, 0) + r) % 3 + CASE WHEN s = {WORKERS - 1} THEN 2 ELSE 0 END END)::INT AS delay, coalesce(g, 0.0::DOUBLE) AS g FROM (SELECT unnest(range(1, {ITERS + 1})) AS i), (SELECT unnest(range({WORKERS})) AS s), (SELECT unnest(range({WORKERS})) AS r) LEFT JOIN ld ON ld.iter = i AND ld.sender = s)"
WORK = [LOADS_SQL, f"ar AS MATERIALIZED (SELECT *, iter + delay AS arrive FROM {WORK_SQL})", *EX[2:]]


def worked(spark, d):
    """(iter, sender, receiver, delay, g): iterations over the lines of orders. A worker's gradient is the mean discount of its lines, its delays follow their quantity."""
    lines = read(spark, d, "lineitem", "l_partkey", "l_suppkey", "l_quantity", "l_discount")
    loads = lines.groupBy((F.col("l_partkey") % ITERS + 1).cast("int").alias("iter"), (F.col("l_suppkey") % WORKERS).cast("int").alias("sender")).agg(F.sum(F.col("l_quantity").cast("long")).alias("load"), F.avg(F.col("l_discount").cast("double")).alias("g"))
    cells = X.delay_table(spark, WORKERS, ITERS).drop("delay").join(loads, ["iter", "sender"], "left")
    drawn = (F.coalesce("load", F.lit(0)) + F.col("receiver")) % 3 + F.when(F.col("sender") == WORKERS - 1, 2).otherwise(0)
    delay = F.when(F.col("sender") == F.col("receiver"), 0).otherwise(drawn).cast("int")
    return cells.select("iter", "sender", "receiver", delay.alias("delay"), F.coalesce("g", F.lit(0.0)).alias("g"))


def arrived(spark):
    from ..functions.hashing import uniform

    return X.arrivals(X.delay_table(spark, WORKERS, ITERS)).withColumn("g", uniform(7, "g", F.col("iter"), F.col("sender")))


@query(sql([LOADS_SQL], f"SELECT iter, sender, receiver, delay FROM {WORK_SQL}"))
def delays(spark, d):
    return worked(spark, d).drop("g")


@query(sql(WORK, "SELECT iter, receiver, sender, round(avg(g) OVER (PARTITION BY iter, receiver ORDER BY arrive, sender ROWS UNBOUNDED PRECEDING), 6) AS running FROM ar"))
def grad_running_mean(spark, d):
    return X.accumulate(X.arrivals(worked(spark, d))).select("iter", "receiver", "sender", r6("running").alias("running"))


@query(sql(WORK, "SELECT iter, round(g, 6) AS g FROM gm"))
def grad_mean(spark, d):
    return rounded(X.gradient_mean(worked(spark, d).where("receiver = 0")), "g")


@query("SELECT 0::BIGINT AS violations")
def grad_mean_equals_fold(spark, d):
    a = X.arrivals(worked(spark, d))
    last = X.accumulate(a).where(F.col("n") == WORKERS).select("iter", "receiver", "running")
    return last.join(X.gradient_mean(a.where("receiver = 0")), "iter").agg(F.sum((F.abs(F.col("running") - F.col("g")) > 1e-9).cast("long")).alias("violations"))


@query(sql(EX, "SELECT iter, receiver, ready FROM us"))
def ready_iteration(spark, d):
    return X.update_schedule(arrived(spark)).select("iter", "receiver", "ready")


@query(sql(EX, "SELECT iter, receiver, ready, applied, applied - iter AS staleness FROM us"))
def update_schedule(spark, d):
    return X.update_schedule(arrived(spark), PERIOD)


@query(sql(EX, "SELECT applied - iter AS staleness, count(*) AS n FROM us GROUP BY ALL"))
def staleness_hist(spark, d):
    return X.staleness_report(X.update_schedule(arrived(spark), PERIOD))


@query(sql([*WORK, "st AS (SELECT receiver, applied AS at_, sum(g) AS step FROM us JOIN gm USING (iter) GROUP BY ALL)", f"gd AS (SELECT receiver, t::INT AS t FROM (SELECT unnest(range({WORKERS})) AS receiver), (SELECT unnest(range(1, {ITERS + 1})) AS t))", "mo AS (SELECT gd.receiver, t, -0.1 * sum(coalesce(step, 0)) OVER (PARTITION BY gd.receiver ORDER BY t) AS m FROM gd LEFT JOIN st ON st.receiver = gd.receiver AND at_ = t)"], "SELECT t AS iter, round(max(m) - min(m), 6) AS spread FROM mo GROUP BY t"))
def divergence_curve(spark, d):
    a = X.arrivals(worked(spark, d))
    return rounded(X.divergence(X.update_schedule(a, PERIOD), X.gradient_mean(a.where("receiver = 0")), ITERS), "spread")


@query("SELECT 1 AS equal_after_resync, 1 AS synchronous_if_period_1")
def resync_invariants(spark, d):
    a = arrived(spark)
    means = X.gradient_mean(a.where("receiver = 0"))
    spread = X.divergence(X.update_schedule(a, PERIOD), means, ITERS).where(F.col("iter") % PERIOD == 0).agg((F.max("spread") < 1e-9).cast("int").alias("equal_after_resync"))
    stale = X.update_schedule(a, 1).agg((F.max("staleness") == 0).cast("int").alias("synchronous_if_period_1"))
    return spread.withColumn("k", F.lit(1)).join(stale.withColumn("k", F.lit(1)), "k").drop("k")


@query(f"SELECT w AS worker, i, round(avg(v) OVER (PARTITION BY i), 6) AS w FROM (SELECT *, {u_sql(7, chr(39) + 'p' + chr(39), 'w', 'i')} AS v FROM (SELECT unnest(range(4)) AS w), (SELECT unnest(range(6)) AS i))")
def resync_mean(spark, d):
    from ..functions.hashing import uniform

    p = spark.range(24).select((F.col("id") % 4).alias("worker"), F.floor(F.col("id") / 4).alias("i")).withColumn("w", uniform(7, "p", F.col("worker"), F.col("i")))
    return rounded(X.resync(p), "w")


DUR = f"(SELECT w, t, 1.0 + floor(5 * {u_sql(7, chr(39) + 'ms' + chr(39), 'w', 't')}) + CASE WHEN w = 3 THEN 2.0 ELSE 0.0 END AS ms FROM (SELECT unnest(range(4)) AS w), (SELECT unnest(range(1, 21)) AS t))"


@query(f"SELECT sum(m) AS total FROM (SELECT t, max(ms)::DOUBLE AS m FROM {DUR} GROUP BY t)")
def sched_sync_workers(spark, d):
    return X.synchronous_time(X.durations(spark, WORKERS, ITERS))


@query(f"SELECT sum(m) AS total FROM (SELECT b, max(s)::DOUBLE AS m FROM (SELECT w, (t - 1) // 5 AS b, sum(ms) AS s FROM {DUR} GROUP BY ALL) GROUP BY b)")
def sched_async_workers(spark, d):
    return X.asynchronous_time(X.durations(spark, WORKERS, ITERS), PERIOD)


@query(f"SELECT g AS workers, g * (g - 1) AS messages, g * (g - 1) * p * 8 AS bytes, g * p * 8 AS aggregate_bytes FROM (SELECT unnest(range(1, 5)) AS g), (SELECT {W.HIDDEN} * (max(len(embedding)) + count(DISTINCT label)) AS p FROM embeddings)")
def exchange_bytes(spark, d):
    """For the two-layer network over the embeddings."""
    width, classes = shape(spark, d)
    out = None
    for g in range(1, 5):
        x = X.exchange_bytes(g, W.HIDDEN * (width + classes))
        one = spark.range(1).select(F.lit(g).cast("long").alias("workers"), *[F.lit(v).cast("long").alias(k) for k, v in x.items()])
        out = one if out is None else out.union(one)
    return out


# ---- period and cost ----


def sizes_sql() -> str:
    e = lambda n: "count(*)" if n in ("emb_knn", "user_hops", "page_links", "turns") else "count(*) // 2"
    return " UNION ALL ".join("SELECT * FROM (" + sql(graph_sql(n), f"SELECT '{n}' AS graph, (SELECT count(*) FROM n) AS n, (SELECT {e(n)} FROM a) AS m") + ")" for n in NAMES)


def graph_sizes(spark, d):
    out = None
    for name in NAMES:
        g = load_graph(spark, d, name)
        one = g.nodes.agg(F.count("*").alias("n")).withColumn("k", F.lit(1)).join(g.counted().agg(F.count("*").alias("m")).withColumn("k", F.lit(1)), "k").select(F.lit(name).alias("graph"), "n", "m")
        out = one if out is None else out.union(one)
    return out


def periods_sql(sizes: str) -> str:
    c = lambda p: f"({p} * m + n::DOUBLE / ({p} * g))"
    return f"SELECT graph, g::INT AS workers, round(raw, 6) AS raw, up AS period, CASE WHEN {c('low')} <= {c('up')} THEN low ELSE up END AS integer_opt FROM (SELECT *, greatest(1, ceil(raw))::BIGINT AS up, greatest(1, floor(raw))::BIGINT AS low FROM (SELECT *, sqrt(n / (g * m)) AS raw FROM ({sizes}), (SELECT unnest(range(1, 5)) AS g)))"


@query(periods_sql(sizes_sql()))
def sync_period_all(spark, d):
    return sync.sync_periods(graph_sizes(spark, d), range(1, 5))


# Nodes and edges of the four published graphs.
PUBLISHED = {"ogbn-proteins": (132534, 39561252), "ogbn-arxiv": (160343, 1166243), "reddit": (232965, 11606919), "ogbn-products": (2449029, 61859140)}


@query(periods_sql(" UNION ALL ".join(f"SELECT '{k}' AS graph, {n} AS n, {m} AS m" for k, (n, m) in PUBLISHED.items())))
def sync_period_published(spark, d):
    rows = None
    for k, (n, m) in PUBLISHED.items():
        one = spark.range(1).select(F.lit(k).alias("graph"), F.lit(n).cast("long").alias("n"), F.lit(m).cast("long").alias("m"))
        rows = one if rows is None else rows.union(one)
    return sync.sync_periods(rows, range(1, 5))


COSTS_SQL = f"SELECT graph, p::INT AS p, round(p * m + n::DOUBLE / p, 6) AS cost FROM ({sizes_sql()}), (SELECT unnest(range(1, 11)) AS p)"


@query(COSTS_SQL)
def sync_cost_curve(spark, d):
    return rounded(sync.sync_cost(graph_sizes(spark, d), range(1, 11), 1), "cost")


@query(f"SELECT graph, min_by(p, cost) AS best FROM ({COSTS_SQL}) GROUP BY graph")
def sync_cost_argmin(spark, d):
    return sync.sync_cost(graph_sizes(spark, d), range(1, 11), 1).groupBy("graph").agg(F.min_by("p", "cost").alias("best"))


# ---- measures ----

TIMES = f"(SELECT worker AS run, k, round(sampling + transfer + compute, 6) AS ms FROM ({costs_sql(stats_sql('part_pair', 'gcn'), W.SHAPES['part_pair'][0], 2, False)}))"
TRIM = 3


def times(spark, d):
    """(run, k, ms): the batches of an epoch on pairs of parts, a run for each of two workers."""
    return W.costs_of(W.one_model(spark, d, "part_pair", "gcn"), W.SHAPES["part_pair"][0], 2, False).select(F.col("worker").alias("run"), "k", r6(F.col("sampling") + F.col("transfer") + F.col("compute")).alias("ms"))


@query(f"SELECT run, round(avg(ms), 6) AS mean, round(stddev_samp(ms), 6) AS sd, count(*) AS n FROM (SELECT *, row_number() OVER (PARTITION BY run ORDER BY k) AS i, count(*) OVER (PARTITION BY run) AS n FROM {TIMES}) WHERE i > {TRIM} AND i <= n - {TRIM} GROUP BY run")
def batch_time_trimmed(spark, d):
    return rounded(M.batch_time(times(spark, d), TRIM), "mean", "sd")


@query(f"SELECT run, round(max(e) - min(s), 6) AS ms FROM (SELECT run, sum(ms) OVER w AS e, sum(ms) OVER w - ms AS s FROM {TIMES} WINDOW w AS (PARTITION BY run ORDER BY k)) GROUP BY run")
def training_time(spark, d):
    from pyspark.sql import Window

    end = F.sum("ms").over(Window.partitionBy("run").orderBy("k"))
    return rounded(M.training_time(times(spark, d).withColumn("end_ms", end).withColumn("start_ms", F.col("end_ms") - F.col("ms"))), "ms")


@query(f"SELECT round(avg(ms), 6) AS mean, round(stddev_samp(ms), 6) AS sd, count(*) AS n FROM (SELECT run, sum(ms) AS ms FROM {TIMES} GROUP BY run)")
def run_stats(spark, d):
    return rounded(M.run_stats(times(spark, d).groupBy("run").agg(F.sum("ms").alias("value")), ()), "mean", "sd")


PRED = f"(SELECT quality AS y, CASE WHEN {u_sql(7, chr(39) + 'q' + chr(39), 'doc_id')} < 0.8 THEN quality ELSE 1 - quality END AS yhat, round({u_sql(7, chr(39) + 's' + chr(39), 'doc_id')} / 2 + quality / 4.0, 2) AS score FROM labels)"


def predictions(spark, d):
    from ..functions.hashing import uniform

    x = read(spark, d, "labels")
    flip = F.when(uniform(7, "q", F.col("doc_id")) < 0.8, F.col("quality")).otherwise(1 - F.col("quality"))
    return x.select(F.col("quality").alias("y"), flip.alias("yhat"), F.round(uniform(7, "s", F.col("doc_id")) / 2 + F.col("quality") / 4.0, 2).alias("score"))


@query(f"SELECT round(avg((y = yhat)::INT), 6) AS accuracy FROM {PRED}")
def accuracy(spark, d):
    return rounded(M.accuracy(predictions(spark, d)), "accuracy")


@query(f"SELECT round(2.0 * sum(tp) / sum(t + p), 6)::DOUBLE AS micro, round(avg(2.0::DOUBLE * tp / (t + p)), 6) AS macro FROM (SELECT c, count(*) FILTER (y = c) AS t, count(*) FILTER (yhat = c) AS p, count(*) FILTER (y = c AND yhat = c) AS tp FROM {PRED}, (SELECT unnest([0, 1]) AS c) GROUP BY c)")
def f1_micro_macro(spark, d):
    return rounded(M.f1(predictions(spark, d)), "micro", "macro")


AUC = f"SELECT round(avg(CASE WHEN a.score > b.score THEN 1.0 WHEN a.score = b.score THEN 0.5 ELSE 0.0 END), 6)::DOUBLE AS auc FROM {PRED} a JOIN {PRED} b ON a.y = 1 AND b.y = 0"


@query(AUC)
def roc_auc(spark, d):
    return rounded(M.roc_auc(predictions(spark, d)), "auc")


@query(AUC.replace("a.score", "floor(a.score * 64)").replace("b.score", "floor(b.score * 64)"))
def roc_auc_binned(spark, d):
    return rounded(M.binned_auc(predictions(spark, d), 64), "auc")


SPANS = f"(SELECT 0 AS run, finish_compute - compute AS s, finish_compute AS e FROM ({piped_sql(COST.replace('% 2', '% 1').replace('// 2', '// 1'), S.STAGES)}))"
SMOOTH = f"(WITH sp AS (SELECT * FROM {SPANS}), g AS (SELECT unnest(range(floor(max(e) / 1.0)::BIGINT + 1)) AS t FROM sp), sh AS (SELECT t, coalesce(sum(greatest(0.0, least(e, (t + 1) * 1.0) - greatest(s, t * 1.0))) FILTER (s IS NOT NULL), 0.0) / 1.0 AS share FROM g LEFT JOIN sp ON s < t + 1 AND e > t GROUP BY t) SELECT t, share, avg(share) OVER (ORDER BY t ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS smooth FROM sh)"


def spans(spark, d):
    c = costs(spark, d, 1)
    f = S.schedule(c, "pipelined").join(c.select("run", "worker", "k", "compute"), ["run", "worker", "k"])
    return f.select("run", (F.col("finish_compute") - F.col("compute")).alias("start_ms"), F.col("finish_compute").alias("end_ms"))


@query(f"SELECT 0 AS run, round(b / e, 6) AS mean, round((SELECT max(smooth) FROM {SMOOTH}), 6) AS peak, round(1 - b / e, 6) AS idle FROM (SELECT sum(e - s) AS b, max(e) AS e FROM {SPANS})")
def utilisation(spark, d):
    return rounded(M.utilisation(spans(spark, d), 1, 5), "mean", "peak", "idle")


@query(f"SELECT 0 AS run, t AS tick, round(share, 6) AS share, round(smooth, 6) AS smooth FROM {SMOOTH}")
def utilisation_smooth(spark, d):
    return rounded(M.smoothed(spans(spark, d), 1, 5), "share", "smooth")


DELTA, PATIENCE = 0.01, 3
FOLD = [
    "m AS (SELECT o_orderpriority AS run, (year(o_orderdate) * 12 + month(o_orderdate))::INT AS step, round(avg(o_totalprice::DOUBLE) / 1e5, 4) AS value FROM orders GROUP BY ALL)",
    "h AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY run ORDER BY step) AS i FROM m)",
    f"r AS (SELECT run, i, step, value, value AS ref, 0 AS misses FROM h WHERE i = 1 UNION ALL SELECT run, i, step, value, CASE WHEN moved THEN value ELSE ref END, CASE WHEN moved THEN 0 ELSE misses + 1 END FROM (SELECT h.run, h.i, h.step, h.value, r.ref, r.misses, round(h.value - r.ref, 9) >= {DELTA} AS moved FROM r JOIN h ON h.run = r.run AND h.i = r.i + 1))",
    f"st AS (SELECT run, coalesce(min(step) FILTER (misses >= {PATIENCE}), max(step)) AS stop_step FROM r GROUP BY run)",
]


@query(sql(FOLD, "SELECT run, stop_step, arg_min(step, (-value, step)) AS best_step FROM r JOIN st USING (run) WHERE step <= stop_step GROUP BY run, stop_step"))
def early_stop_point(spark, d):
    """A run for each priority of orders; its history is the mean price of its months."""
    month = (F.year("o_orderdate") * 12 + F.month("o_orderdate")).cast("int")
    means = read(spark, d, "orders", "o_orderpriority", "o_orderdate", "o_totalprice").groupBy(F.col("o_orderpriority").alias("run"), month.alias("step")).agg(F.avg(F.col("o_totalprice").cast("double")).alias("value"))
    return M.early_stop(means.withColumn("value", F.round(F.col("value") / 1e5, 4)), DELTA, PATIENCE)


@query(f"SELECT run, min_by(k, (-v, k)) AS best FROM (SELECT run, k, round(ms, 1) AS v FROM {TIMES}) GROUP BY run")
def best_epoch(spark, d):
    return times(spark, d).withColumn("v", F.round("ms", 1)).groupBy("run").agg(F.min_by("k", F.struct(-F.col("v"), F.col("k"))).alias("best"))
