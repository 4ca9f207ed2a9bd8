"""Errors of one layer's estimates from a graph's arrays."""

from pyspark.sql import functions as F

from gnnspark.functions.hashing import uniform
from gnnspark.operators import estimators, layerwise
from gnnspark.operators.propagation import propagation
from gnnspark.plans import errors, local
from gnnspark.plans.batches import kept
from gnnspark.queries.sampling import scalar_features
from gnnspark.sources.graphs import load_graph
from gnnspark.sources.spool import Spool


def test_errors_by_lot_equal_the_plans(spark, sf, monkeypatch):
    """Races, weights and sums of a lot are those of the plans; some texts have no length, and lots are hashed together or one by one."""
    keep, lots, size, runs = Spool(spark), 12, 16, 3
    g = kept(load_graph(spark, sf, "docs_lex"), keep)
    scalar = keep(scalar_features(spark, sf, "docs_lex").withColumn("x", F.when(F.col("node_id") % 7 > 0, F.col("x"))))
    told = errors.lot_errors(g, scalar, lots, size, runs, keep)
    prop = keep(propagation(g))
    seeds = g.nodes.select("node_id", F.explode(F.array(*map(F.lit, range(runs)))).alias("r"))
    seeds = keep(seeds.select((F.col("r") * lots + F.floor(uniform(7, "batch", 0, F.col("node_id")) * lots)).cast("long").alias("batch_id"), "node_id"))
    blocks, some = None, ("fastgcn_fd", "fastgcn", "ladies_f", "ladies_d")
    for v in some:
        cut = layerwise.block_of(prop, seeds, layerwise.LayerSampler.named(v, sizes=(size,)).draw(prop, seeds, 0), False)
        one = cut.select(F.lit(v).alias("variant"), F.floor(F.col("batch_id") / lots).alias("seed"), "dst", "src", "w")
        blocks = one if blocks is None else blocks.union(one)
    want = estimators.estimator_error(blocks, prop.select(F.col("row").alias("dst"), F.col("col").alias("src"), "w"), scalar)
    want = {r["variant"]: (r["rmse"], r["bias"]) for r in want.collect()}
    got = {r["variant"]: (r["rmse"], r["bias"]) for r in told.collect()}
    assert set(got) == set(layerwise.VARIANTS) and set(want) == set(some)
    assert all(abs(a - b) < 1e-9 for v in some for a, b in zip(got[v], want[v]))
    monkeypatch.setattr(errors, "HELD", 1)
    alone = {r["variant"]: (r["rmse"], r["bias"]) for r in errors.lot_errors(g, scalar, lots, size, runs, Spool(spark)).collect()}
    assert all(abs(a - b) < 1e-12 for v in got for a, b in zip(got[v], alone[v]))
    monkeypatch.setattr(local, "fits", lambda *_: False)
    assert errors.lot_errors(g, scalar, lots, size, runs, keep) is None
