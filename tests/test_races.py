"""Races and pools of many batches: the forms that a kept run takes draw what the plain ones draw, and do less."""

import hashlib

import pytest
from pyspark.sql import functions as F

from gnnspark.functions.md5 import pair_bits
from gnnspark.operators import draws, layerwise
from gnnspark.operators.propagation import propagation
from gnnspark.sources.graphs import load_graph
from gnnspark.sources.spool import spool


def test_pair_bits_are_those_of_md5():
    heads = [f"7:0:{b}:1:".encode() for b in (0, 9, 10, 4711, 2**62)] + [b"", b"x" * 50]
    tails = [str(v).encode() for v in (0, 7, -1, 123456, 3 * 2**40 + 5, -(2**60))]
    seen = {(h, t): int(bits[i, j]) for hs, ts, bits in pair_bits(heads, tails) for i, h in enumerate(hs) for j, t in enumerate(ts)}
    assert seen == {(h, t): int(hashlib.md5(a + b).hexdigest()[:8], 16) for h, a in enumerate(heads) for t, b in enumerate(tails)}


@pytest.mark.parametrize("impl", ["md5", "xxhash64"])
@pytest.mark.parametrize("most", ["found", "far too low", "none"])
def test_race_all_is_the_race(spark, impl, most):
    mass = spark.range(3000).select((F.col("id") - 5).alias("node_id"), F.when(F.col("id") % 10 == 0, 0.0).otherwise(F.col("id") % 7 + 0.5).alias("p"))
    probs = spool(mass.select("node_id", (F.col("p") / mass.agg(F.sum("p")).first()[0]).alias("p")))
    batches = spark.range(12).select((F.col("id") * 90).alias("batch_id"))
    n, found = draws.race_bound(probs, 40)
    assert n == 2700 and found is not None
    got = draws.race_all(probs, batches, 40, 1, spool, (n, {"found": found, "far too low": found / 3, "none": None}[most]), impl=impl)
    want = draws.race(probs.crossJoin(batches), 40, 1, impl=impl)
    rows = lambda df: sorted(map(tuple, df.select("batch_id", "layer", "node_id", "p", "ord").collect()))
    assert rows(got) == rows(want) and got.count() == 480


def test_no_bound_for_a_pool_that_is_taken_whole(spark):
    probs = spark.range(30).select(F.col("id").alias("node_id"), F.lit(1 / 30).alias("p"))
    assert draws.race_bound(probs, 40) == (30, None)


@pytest.fixture(scope="module")
def world(spark, sf):
    g = load_graph(spark, sf, "cust_part")
    seeds = spool(g.nodes.where("node_id % 3 = 0").select((F.col("node_id") % 8).alias("batch_id"), "node_id"))
    return spool(propagation(g)), seeds


@pytest.mark.parametrize("base", ["fastgcn", "ladies"])
@pytest.mark.parametrize("sent", [layerwise.SENT, 0])
def test_kept_layers_are_the_plain_ones(world, monkeypatch, base, sent):
    prop, seeds = world
    monkeypatch.setattr(layerwise, "SENT", sent)
    flat, debias = F.col("batch_id") % 2 == 1, F.col("batch_id") >= 4
    plain = layerwise.LayerSampler(base, flat, debias, sizes=(24, 24)).layers(prop, seeds)
    kept = layerwise.LayerSampler(base, flat, debias, sizes=(24, 24), keep=spool).layers(prop, seeds)
    for columns, a, b in ((("batch_id", "layer", "node_id", "ord", "coef"), plain[0], kept[0]), (("batch_id", "layer", "dst", "src", "w"), plain[1], kept[1])):
        for x, y in zip(a, b):
            rows = [sorted((*r[:-1], round(r[-1], 9)) for r in df.select(*columns).collect()) for df in (x, y)]
            assert rows[0] == rows[1] and rows[0]


def test_kept_fastgcn_ranks_few_pairs(world, monkeypatch):
    prop, seeds = world
    ranked, race = [], draws.race
    monkeypatch.setattr(draws, "race", lambda pool, *a, **b: ranked.append(pool.count()) or race(pool, *a, **b))
    layerwise.LayerSampler("fastgcn", sizes=(4,), keep=spool).layers(prop, seeds)
    nodes = prop.select("row").distinct().count()
    assert sum(ranked) < nodes * 8 / 4  # of eight batches


def test_kept_ladies_shuffles_no_pool(world, monkeypatch):
    prop, seeds = world
    plans, race = [], draws.race
    monkeypatch.setattr(draws, "race", lambda pool, *a, **b: plans.append(pool._jdf.queryExecution().executedPlan().toString()) or race(pool, *a, **b))
    layerwise.LayerSampler("ladies", sizes=(24,), keep=spool).layers(prop, seeds)
    assert len(plans) == 1 and plans[0].count("hashpartitioning(batch_id") == 1 and "REPARTITION_BY_NUM" in plans[0]
