"""The facade, sinks, and the pieces of streams that queries do not show."""

import pytest
from pyspark.sql import functions as F

from gnnspark.engine import Engine
from gnnspark.operators import relational as R
from gnnspark.operators.estimators import estimator_error
from gnnspark.operators.layerwise import VARIANTS
from gnnspark.operators.prefix import places
from gnnspark.sources import formats
from gnnspark.streaming import runs


@pytest.fixture(scope="module")
def opened(spark, sf):
    return Engine(spark, sf).graph("cust_supp")


def test_samples_of_all_models(opened):
    lots = opened.batches(64)
    rows = {(r["batch_id"], r["node_id"]) for r in lots.collect()}
    for model in ("gcn", "graphsage", *VARIANTS):
        s = opened.sample(model, lots, size=32)
        got = s.blocks.collect()
        assert got and {r["layer"] for r in got} == {0, 1}
        assert {(r["batch_id"], r["dst"]) for r in got if r["layer"] == 1} <= rows
        ins = {(r["batch_id"], r["node_id"]) for r in s.inputs.collect()}
        assert {(r["batch_id"], r["src"]) for r in got if r["layer"] == 0} <= ins
    with pytest.raises(ValueError):
        opened.sample("other", lots)


def test_views_and_cache(spark, opened):
    opened.views(opened.batches(64))
    n = opened.g.nodes.count()
    assert spark.sql("SELECT count(*) AS n FROM gs_nodes").first()["n"] == n
    assert spark.sql("SELECT count(DISTINCT b.node_id) AS n FROM gs_batches b JOIN gs_prop p ON p.row = b.node_id").first()["n"] == opened.split().count()
    assert opened.cache(0.1).count() == max(1, int(0.1 * n + 1e-9))
    with pytest.raises(ValueError):
        Engine(spark, "nowhere").graph("other")


def test_sinks(spark, opened, tmp_path):
    blocks = opened.sample("ladies", opened.batches(64), size=16).blocks
    two = blocks.withColumn("epoch", F.lit(0)).union(blocks.withColumn("epoch", F.lit(1)))
    formats.write_batches(two, f"{tmp_path}/spool")
    back = spark.read.parquet(f"{tmp_path}/spool")
    assert back.where("epoch = 1").count() == blocks.count() and back.count() == 2 * blocks.count()
    plan = back.where("epoch = 1")._jdf.queryExecution().toString()
    assert "PartitionFilters: [isnotnull(epoch" in plan
    formats.write_adjacency(opened.g.edges.select("dst", "src"), "gs_adjacency", 4)
    try:
        table = spark.table("gs_adjacency")
        assert table.count() == opened.g.edges.count()
        assert "hashpartitioning(dst" not in table.groupBy("dst").count()._jdf.queryExecution().toString()
    finally:
        spark.sql("DROP TABLE gs_adjacency")


def test_places_of_a_hub(spark):
    df = spark.range(500).select(F.when(F.col("id") < 400, 0).otherwise(F.col("id") % 3).alias("dst"), (F.col("id") * 7919 % 100003).alias("src"))
    got = {(r["dst"], r["src"]): r["at"] for r in places(df, "dst", "src", 8).collect()}
    for key in {d for d, _ in got}:
        assert [got[key, s] for s in sorted(s for d, s in got if d == key)] == list(range(1, sum(d == key for d, _ in got) + 1))


def test_estimator_error_against_enumeration(spark):
    """Two rows, two seeds; the second row is never estimated."""
    blocks = spark.createDataFrame([("v", 0, 1, 5, 2.0), ("v", 1, 1, 6, 1.0)], "variant string, seed int, dst long, src long, w double")
    exact = spark.createDataFrame([(1, 5, 1.0), (1, 6, 0.5), (2, 5, 1.0)], "dst long, src long, w double")
    x = spark.createDataFrame([(5, 0, 1.0), (6, 0, 2.0)], "node_id long, pos int, x double")
    r = estimator_error(blocks, exact, x).first()  # truth 2 and 1, estimates 2, 2 and 0, 0
    assert r["rmse"] == pytest.approx((1 / 5) ** 0.5) and r["bias"] == pytest.approx((1 / 5) ** 0.5) and r["spread"] == pytest.approx(0, abs=1e-6)


def test_pandas_forms(spark):
    a = spark.createDataFrame([(1, 1.0), (1, 2.0), (2, 5.0)], "k int, x double")
    b = spark.createDataFrame([(2, 1.0), (3, 4.0)], "k int, x double")
    got = sorted(tuple(r) for r in R.cogrouped_totals(a, b, "k").collect())
    assert got == [(1, 3.0, None), (2, 5.0, 1.0), (3, None, 4.0)]
    odd = spark.createDataFrame([([3.0, 4.0],), (None,), ([],)], "v array<double>").select(R.pandas_norm("v").alias("n"))
    assert [r["n"] for r in odd.collect()] == [5.0, None, 0.0]
    m = spark.createDataFrame([(1.0, 3), (9.0, 1), (4.0, 2)], "v double, n long").agg(R.pandas_median("v", "n").alias("m")).first()
    assert m["m"] == 2.5


def test_drain_modes_and_empty_input(spark, tmp_path):
    spark.createDataFrame([(1, 2)], "batch_id long, n long").write.parquet(f"{tmp_path}/a")
    stream = runs.spooled(spark, f"{tmp_path}/a", "batch_id long, n long")
    for mode in ("complete", "update"):
        assert [tuple(r) for r in runs.drain(spark, stream.groupBy("batch_id").agg(F.sum("n").alias("n")), mode).collect()] == [(1, 2)]
    (tmp_path / "none").mkdir()
    none = runs.spooled(spark, f"{tmp_path}/none", "batch_id long, n long")
    assert runs.drain(spark, none.groupBy("batch_id").agg(F.sum("n").alias("n")), "update").count() == 0
