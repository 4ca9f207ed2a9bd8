"""Hand-computed values on a five-node graph, and literal cases."""

import math

import pytest
from pyspark.sql import functions as F

from gnnspark.operators import cache as C
from gnnspark.operators import draws, exchange, layerwise, nodewise, sync
from gnnspark.operators.propagation import propagation
from gnnspark.sources.graphs import Graph

PAIRS = [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4)]


@pytest.fixture(scope="module")
def g(spark):
    nodes = spark.range(5).select(F.col("id").alias("node_id"), F.lit("x").alias("kind"))
    both = PAIRS + [(b, a) for a, b in PAIRS]
    edges = spark.createDataFrame([(a, b, 1.0) for a, b in both], "src long, dst long, weight double").withColumn("ts", F.lit(None).cast("timestamp"))
    return Graph("five", nodes, edges, False)


def by_node(df, value="p"):
    return {r["node_id"]: r[value] for r in df.collect()}


def test_propagation(g):
    p = {(r["row"], r["col"]): r["w"] for r in propagation(g).collect()}
    assert p[0, 0] == pytest.approx(1 / 3) and p[0, 2] == pytest.approx(1 / math.sqrt(12)) and p[2, 2] == pytest.approx(0.25)
    assert p[3, 4] == pytest.approx(1 / math.sqrt(6)) and p[4, 4] == pytest.approx(0.5) and len(p) == 15
    assert all(p[a, b] == pytest.approx(p[b, a]) for a, b in p)
    rows = {r["row"]: r["s"] for r in propagation(g, "row").groupBy("row").agg(F.sum("w").alias("s")).collect()}
    assert all(v == pytest.approx(1) for v in rows.values())


@pytest.mark.parametrize("power,want", [(2, [0.179592, 0.179592, 0.183673, 0.212245, 0.244898]), (1, [0.189892, 0.189892, 0.192037, 0.206434, 0.221746])])
def test_column_probs(g, power, want):
    got = by_node(layerwise.column_probs(propagation(g), None, power))
    assert [got[i] for i in range(5)] == pytest.approx(want, abs=1e-6)


@pytest.mark.parametrize("rows,power,want", [([4], 2, [0, 0, 0, 0.4, 0.6]), ([0, 4], 2, [0.153846, 0.153846, 0.115385, 0.230769, 0.346154]), ([0, 4], 1, [0.178866, 0.178866, 0.154903, 0.219065, 0.268299])])
def test_ladies_probs(spark, g, rows, power, want):
    seeds = spark.createDataFrame([(0, r) for r in rows], "batch_id long, node_id long")
    got = by_node(layerwise.column_probs(propagation(g), seeds, power))
    assert [got.get(i, 0) for i in range(5)] == pytest.approx(want, abs=1e-6)


def test_cache_probs(spark, g):
    assert [by_node(C.cache_probs_degree(g))[i] for i in range(5)] == pytest.approx([0.2, 0.2, 0.3, 0.2, 0.1])
    train = spark.createDataFrame([(0,)], "node_id long")
    for how, one, two in (("printed", [1, 0.5, 1 / 3, 0, 0], [17 / 12, 7 / 6, 5 / 6, 1 / 6, 0]), ("expander", [1, 0.5, 0.5, 0, 0], [17 / 12, 7 / 6, 1.25, 1 / 6, 0])):
        for steps, want in ((1, one), (2, two)):
            got = by_node(C.walk_mass(g, train, 1, steps, how))
            assert [got[i] for i in range(5)] == pytest.approx(want)
    assert sum(by_node(C.walk_mass(g, train, 1, 2, "expander")).values()) == pytest.approx(4)


def test_debias_weights(spark):
    p = [0.179592, 0.179592, 0.183673, 0.212245, 0.244898]
    drawn = spark.createDataFrame([(0, 0, n, p[n], i + 1) for i, n in enumerate([2, 0, 3])], "batch_id long, layer int, node_id long, p double, ord int")
    got = {r["ord"]: r["coef"] for r in draws.debias_weights(drawn, F.lit(5)).collect()}
    assert [got[i] for i in (1, 2, 3)] == pytest.approx([1.740741, 1.818182, 1.666667], abs=1e-5)


def test_debias_is_unbiased_by_enumeration():
    """All ordered draws of 3 from 5: the weighted sum has the true expectation."""
    from itertools import permutations

    p, x, n, s = [0.1, 0.15, 0.2, 0.25, 0.3], [3.0, -1.0, 4.0, 2.0, 7.0], 5, 3
    mean = 0.0
    for order in permutations(range(n), s):
        chance, left, total = 1.0, 1.0, 0.0
        for j, i in enumerate(order, 1):
            q = p[i] / left
            chance *= q
            left -= p[i]
            total += x[i] * (n * (n - s) / (s * (n - j) * (n - j + 1)) / q + n * (s - j) / (s * (n - j)))
        mean += chance * total
    assert mean == pytest.approx(sum(x))


def test_race_takes_all_when_small(spark):
    pool = spark.range(4).select(F.lit(0).cast("long").alias("batch_id"), F.col("id").alias("node_id"), F.lit(0.25).alias("p"))
    assert draws.race(pool, 10, 0).count() == 4
    coef = draws.debias_weights(draws.race(pool, 10, 0), F.lit(4)).select("coef").collect()
    assert all(r[0] == pytest.approx(1) for r in coef)


def test_iid_frequencies(spark):
    probs = spark.createDataFrame([(0, 0.1), (1, 0.2), (2, 0.7)], "node_id long, p double")
    got = draws.iid(probs, spark.createDataFrame([(0,)], "batch_id long"), 4000, 0).groupBy("node_id").count().collect()
    share = {r["node_id"]: r["count"] / 4000 for r in got}
    assert sum(share.values()) == 1 and share[2] == pytest.approx(0.7, abs=0.03) and share[0] == pytest.approx(0.1, abs=0.03)


def test_empty_frontier(spark, g):
    none = spark.createDataFrame([], "batch_id long, node_id long")
    assert nodewise.sample_neighbors(none, g.edges, 3).count() == 0
    assert nodewise.expand_full(none, g.edges, 2).count() == 0


def test_sage_estimate_is_unbiased(spark, g):
    """Mean of the kept neighbours' values over many seeds is near the mean of all."""
    batches = spark.range(400).select(F.col("id").alias("batch_id"), F.lit(2).cast("long").alias("node_id"))
    b = nodewise.sage_weights(nodewise.sample_neighbors(batches, g.edges, 2))
    mean, sd = b.groupBy("batch_id").agg(F.sum(F.col("w") * F.col("src")).alias("z")).agg(F.avg("z"), F.stddev("z")).first()
    assert abs(mean - (0 + 1 + 3) / 3) < 4 * sd / 20


def test_sync_period():
    assert [sync.sync_period(536, 436, w) for w in (1, 2, 3, 4)] == [2, 1, 1, 1]
    assert [sync.sync_period(1630, 1625, w) for w in (1, 2)] == [2, 1]
    assert sync.sync_period(536, 436, 1, mode="integer_opt") == 1
    assert sync.sync_cost_of(1, 536, 436, 1) == 972 and sync.sync_cost_of(2, 536, 436, 1) == 1140
    for n, m in ((132534, 39561252), (160343, 1166243), (232965, 11606919), (2449029, 61859140)):
        assert all(sync.sync_period(n, m, w) == 1 for w in range(1, 5))


def test_fold(spark):
    a = spark.createDataFrame([(1, 0, 0, 1, 4.0), (1, 1, 0, 2, 1.0), (1, 2, 0, 3, 7.0)], "iter int, sender int, receiver int, arrive int, g double")
    assert [r["running"] for r in exchange.accumulate(a).orderBy("arrive").collect()] == [4.0, 2.5, 4.0]


def test_one_worker_needs_no_exchange(spark):
    d = exchange.update_schedule(exchange.arrivals(exchange.delay_table(spark, 1, 5)))
    assert d.where("staleness <> 0").count() == 0 and exchange.exchange_bytes(1, 10)["messages"] == 0
