"""The global cache."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from ..operators import cache as C
from ..operators import nodewise
from ..operators.propagation import split_of
from ..sources.graphs import load_graph
from ..sources.spool import spool
from .base import BATCHES, FANOUT, Setup, graph_sql, query, r6, seeds_sql, split_sql, sql, u_sql
from .sampling import front_sql, ns_sql

GRAPH = "docs_tok"
DEG = "dg AS MATERIALIZED (SELECT dst AS node_id, count(*) AS deg FROM a GROUP BY dst)"


def train_sql(name: str) -> str:
    return f"tr AS MATERIALIZED (SELECT node_id FROM n WHERE {split_sql(name)} = 'train')"


def degree_sql(out: str = "cprob") -> str:
    return f"{out} AS MATERIALIZED (SELECT node_id, coalesce(deg, 0) / sum(deg) OVER () AS p FROM n LEFT JOIN dg USING (node_id))"


def walk_sql(steps: int, orientation: str, k: int = FANOUT, out: str = "cprob", normal: bool = True) -> list[str]:
    ctes = [f"rt AS MATERIALIZED (SELECT node_id, least({k}, deg)::DOUBLE / deg AS r FROM dg)", "w0 AS MATERIALIZED (SELECT node_id, 1.0::DOUBLE / count(*) OVER () AS p FROM tr)"]
    for i in range(steps):
        if orientation == "printed":
            moved = f"SELECT g.node_id, g.p * r AS p FROM (SELECT dst AS node_id, sum(p) AS p FROM a JOIN w{i} ON src = w{i}.node_id GROUP BY dst) g JOIN rt USING (node_id)"
        else:
            moved = f"SELECT src AS node_id, sum(p * r) AS p FROM a JOIN w{i} ON dst = w{i}.node_id JOIN rt ON rt.node_id = dst GROUP BY src"
        ctes.append(f"w{i + 1} AS MATERIALIZED (SELECT node_id, sum(p) AS p FROM (SELECT * FROM w{i} UNION ALL {moved}) GROUP BY node_id)")
    p = f"coalesce(p, 0) / sum(p) OVER ()" if normal else "coalesce(p, 0)"
    return [*ctes, f"{out} AS MATERIALIZED (SELECT node_id, {p} AS p FROM n LEFT JOIN w{steps} USING (node_id))"]


def draw_sql(out: str, size: str, epoch: int = 0, probs: str = "cprob") -> str:
    key = f"-ln({u_sql(7, chr(39) + 'cache' + chr(39), epoch, 'node_id')}) / p"
    return f"{out} AS MATERIALIZED (SELECT {epoch} AS epoch, node_id, p, ord FROM (SELECT node_id, p, row_number() OVER (ORDER BY {key}, node_id) AS ord FROM {probs} WHERE p > 0) WHERE ord <= {size})"


ONE_PERCENT = "(SELECT greatest(1, floor(0.01 * count(*) + 1e-9)) FROM n)"


def held_graph(spark, d, name):
    """The graph with its tables written once: every use of them is a scan."""
    g = load_graph(spark, d, name)
    return replace(g, nodes=spool(g.nodes), edges=spool(g.edges))


def graph_and_train(spark, d, name):
    g = held_graph(spark, d, name)
    return g, g.nodes.where(split_of(F.col("node_id"), name) == "train").select("node_id")


def one_percent(g, share: float = 0.01) -> int:
    return C.cache_size(g.nodes.count(), share)


@query(sql([*graph_sql(GRAPH), DEG, degree_sql()], "SELECT node_id, round(p, 9) AS p FROM cprob"))
def cache_probs_degree(spark, d):
    return C.cache_probs_degree(held_graph(spark, d, GRAPH)).select("node_id", F.round("p", 9).alias("p"))


for _name, _steps, _how in (("cache_probs_walk1", 1, "printed"), ("cache_probs_walk2", 2, "printed"), ("cache_probs_walk_expander", 2, "expander")):

    @query(sql([*graph_sql("cust_part"), DEG, train_sql("cust_part"), *walk_sql(_steps, _how)], "SELECT node_id, round(p, 9) AS p FROM cprob"), _name)
    def _walk(spark, d, steps=_steps, how=_how):
        g, train = graph_and_train(spark, d, "cust_part")
        return C.cache_probs_walk(g, train, FANOUT, steps, how).select("node_id", F.round("p", 9).alias("p"))


@query(sql([*graph_sql("part_pair"), train_sql("part_pair")], "SELECT CASE WHEN 2 * (SELECT count(*) FROM tr) > (SELECT count(*) FROM n) THEN 'degree' ELSE 'walk' END AS part_pair"))
def cache_mode_auto(spark, d):
    g, train = graph_and_train(spark, d, "part_pair")
    n = g.nodes.agg(F.count("*").alias("n")).withColumn("k", F.lit(1))
    t = train.agg(F.count("*").alias("t")).withColumn("k", F.lit(1))
    return n.join(t, "k").select(F.when(2 * F.col("t") > F.col("n"), "degree").otherwise("walk").alias("part_pair"))


@query(sql([*graph_sql(GRAPH), DEG, degree_sql(), draw_sql("ch", ONE_PERCENT)], "SELECT epoch, node_id, ord FROM ch"))
def cache_nodes(spark, d):
    g = held_graph(spark, d, GRAPH)
    return C.build_cache(C.cache_probs_degree(g), one_percent(g)).select("epoch", "node_id", "ord")


@query(sql([*graph_sql(GRAPH), DEG, degree_sql(), draw_sql("c0", ONE_PERCENT), draw_sql("c1", ONE_PERCENT, 1)], "SELECT (SELECT count(*) FROM c0) AS size, count(*) AS kept FROM c0 JOIN c1 USING (node_id)"))
def cache_refresh_overlap(spark, d):
    g = held_graph(spark, d, GRAPH)
    p, size = C.cache_probs_degree(g), one_percent(g)
    a, b = C.build_cache(p, size, 0), C.build_cache(p, size, 1)
    n = a.agg(F.count("*").alias("size")).withColumn("k", F.lit(1))
    return n.join(a.join(b, "node_id", "left_semi").agg(F.count("*").alias("kept")).withColumn("k", F.lit(1)), "k").drop("k")


def inputs_sql(prefer: bool) -> list[str]:
    order = "(src IN (SELECT node_id FROM ch)) DESC, " if prefer else ""
    return [ns_sql("b1", "s", 1, order=order), front_sql("f1", "s", "b1"), ns_sql("b0", "f1", 0, order=order), front_sql("f0", "f1", "b0")]


DOCS = "node_id > 0"
CACHED = [*graph_sql(GRAPH), DEG, degree_sql(), draw_sql("ch", ONE_PERCENT), seeds_sql(where=DOCS)]


class CacheSetup:
    def __init__(self, spark, d, prefer: bool, policy: str = "degree", share: float = 0.01):
        self.g = held_graph(spark, d, GRAPH)
        from ..operators.batching import hashed_seeds

        self.seeds = hashed_seeds(self.g.nodes.where(DOCS), BATCHES, 16)
        probs = C.cache_probs_degree(self.g) if policy == "degree" else C.cache_probs(self.g, None, policy)
        self.cache = C.build_cache(probs, one_percent(self.g, share))
        self.blocks, fronts = nodewise.node_wise_batches(self.seeds, self.g.edges, [FANOUT, FANOUT], prefer=self.cache if prefer else None)
        self.inputs = fronts[-1]


@query(sql([*CACHED, *inputs_sql(True)], "SELECT batch_id, layer, dst, src, (src IN (SELECT node_id FROM ch))::INT AS cached FROM b1"))
def ns_cached(spark, d):
    return CacheSetup(spark, d, True).blocks[0]


@query(sql([*CACHED, *inputs_sql(True)], "SELECT batch_id, count(*) AS inputs, count(*) FILTER (node_id NOT IN (SELECT node_id FROM ch)) AS missing, 400 * count(*) FILTER (node_id NOT IN (SELECT node_id FROM ch)) AS bytes FROM f0 GROUP BY batch_id"))
def transfer_bytes(spark, d):
    x = CacheSetup(spark, d, True)
    return C.transfer_bytes(x.inputs, x.cache, 100)


@query(sql([*graph_sql("cust_part"), DEG, degree_sql(), draw_sql("ch", ONE_PERCENT), seeds_sql(), *inputs_sql(False), "ft AS (SELECT node_id, node_id % 1000 AS f FROM n)"], "SELECT batch_id, node_id, (node_id IN (SELECT node_id FROM ch))::INT AS hit, f FROM f0 JOIN ft USING (node_id)"))
def gather_missing(spark, d):
    """Cached or fetched, the rows are the same."""
    x = Setup(spark, d, "cust_part")
    inputs = nodewise.node_wise_batches(x.seeds, x.g.edges, [FANOUT, FANOUT])[1][-1]
    cache = C.build_cache(C.cache_probs_degree(x.g), one_percent(x.g))
    feats = x.g.nodes.select("node_id", (F.col("node_id") % 1000).alias("f"))
    return C.gather_inputs(inputs, cache, feats).select("batch_id", "node_id", "hit", "f")


@query(sql([*CACHED], "SELECT count(*) AS nodes, sum(c)::BIGINT AS covered, round(avg(c), 6) AS share FROM (SELECT dst, max((src IN (SELECT node_id FROM ch))::INT) AS c FROM a GROUP BY dst)"))
def cache_coverage(spark, d):
    g = held_graph(spark, d, GRAPH)
    return C.coverage(g, C.build_cache(C.cache_probs_degree(g), one_percent(g)))


HIT = "SELECT count(*) AS inputs, count(*) FILTER (node_id IN (SELECT node_id FROM ch)) AS hits, round(count(*) FILTER (node_id IN (SELECT node_id FROM ch))::DOUBLE / count(*), 6) AS rate FROM f0"


@query(sql([*CACHED, *inputs_sql(True)], HIT))
def cache_hit_rate(spark, d):
    x = CacheSetup(spark, d, True)
    return C.hit_rate(x.inputs, x.cache)


@query(sql([*CACHED, *inputs_sql(False)], HIT))
def cache_hit_rate_plain(spark, d):
    x = CacheSetup(spark, d, False)
    return C.hit_rate(x.inputs, x.cache)


OVERLAP = "SELECT count(*) AS sum_inputs, count(DISTINCT node_id) AS distinct_inputs, round(count(*)::DOUBLE / count(DISTINCT node_id), 6) AS overlap FROM f0"


@query(sql([*CACHED, *inputs_sql(True)], OVERLAP))
def batch_overlap(spark, d):
    return C.batch_overlap(CacheSetup(spark, d, True).inputs)


@query(sql([*CACHED, *inputs_sql(False)], OVERLAP))
def batch_overlap_plain(spark, d):
    return C.batch_overlap(CacheSetup(spark, d, False).inputs)


POLICIES = {"none": None, "uniform": "cuni", "degree": "cdeg", "walk": "cwalk", "expander": "cexp", "full": None}


def _policy_sql() -> str:
    ctes = [*graph_sql("cust_part"), DEG, train_sql("cust_part"), degree_sql("pdeg"), "puni AS (SELECT node_id, 1.0::DOUBLE / count(*) OVER () AS p FROM n)", *walk_sql(2, "printed", out="pwalk")]
    exp = [c.replace("w0 ", "v0 ").replace("w0.", "v0.").replace(" w0", " v0").replace("w1", "v1").replace("w2", "v2") for c in walk_sql(2, "expander", out="pexp")[1:]]
    ctes += exp + [draw_sql("cuni", ONE_PERCENT, probs="puni"), draw_sql("cdeg", ONE_PERCENT, probs="pdeg"), draw_sql("cwalk", ONE_PERCENT, probs="pwalk"), draw_sql("cexp", ONE_PERCENT, probs="pexp"), seeds_sql(), *inputs_sql(False)]
    one = lambda name, hit: f"SELECT '{name}' AS policy, count(*) AS inputs, count(*) FILTER (NOT ({hit})) AS missing, 64 * count(*) FILTER (NOT ({hit})) AS bytes FROM f0"
    hits = {"none": "false", "full": "true"}
    return sql(ctes, " UNION ALL ".join(one(k, hits.get(k) or f"node_id IN (SELECT node_id FROM {v})") for k, v in POLICIES.items()))


@query(_policy_sql())
def cache_policy_bytes(spark, d):
    x = Setup(spark, d, "cust_part")
    _, train = graph_and_train(spark, d, "cust_part")
    inputs = nodewise.node_wise_batches(x.seeds, x.g.edges, [FANOUT, FANOUT])[1][-1]
    size = one_percent(x.g)
    probs = {"uniform": C.cache_probs(x.g, train, "uniform"), "degree": C.cache_probs_degree(x.g), "walk": C.cache_probs_walk(x.g, train), "expander": C.cache_probs_walk(x.g, train, orientation="expander")}
    out = None
    for name in POLICIES:
        cache = C.build_cache(probs[name], size) if name in probs else x.g.nodes.where(F.lit(name == "full"))
        per = C.transfer_bytes(inputs, cache, 16).agg(F.sum("inputs").alias("inputs"), F.sum("missing").alias("missing"), F.sum("bytes").alias("bytes"))
        one = per.select(F.lit(name).alias("policy"), "inputs", "missing", "bytes")
        out = one if out is None else out.union(one)
    return out


SHARES = (0.001, 0.005, 0.01, 0.05, 0.10)


def _sweep_sql() -> str:
    size = lambda s: f"(SELECT greatest(1, floor({s} * count(*) + 1e-9)) FROM n)"
    ctes = [*graph_sql("cust_part"), DEG, degree_sql(), *[draw_sql(f"h{i}", size(s)) for i, s in enumerate(SHARES)], seeds_sql(), *inputs_sql(False)]
    return sql(ctes, " UNION ALL ".join(f"SELECT {s}::DOUBLE AS share, (SELECT count(*) FROM h{i}) AS size, round(avg((node_id IN (SELECT node_id FROM h{i}))::INT), 6) AS rate FROM f0" for i, s in enumerate(SHARES)))


@query(_sweep_sql())
def cache_size_sweep(spark, d):
    x = Setup(spark, d, "cust_part")
    inputs = nodewise.node_wise_batches(x.seeds, x.g.edges, [FANOUT, FANOUT])[1][-1]
    probs, n, out = C.cache_probs_degree(x.g), x.g.nodes.count(), None
    for s in SHARES:
        size = C.cache_size(n, s)
        one = C.hit_rate(inputs, C.build_cache(probs, size)).select(F.lit(s).alias("share"), F.lit(size).cast("long").alias("size"), "rate")
        out = one if out is None else out.union(one)
    return out
