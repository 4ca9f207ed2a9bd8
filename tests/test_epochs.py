"""Counts of an epoch's batches from a graph's arrays."""

import hashlib
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from gnnspark.functions.md5 import Tails
from gnnspark.operators import layerwise
from gnnspark.plans import epochs, local
from gnnspark.plans import workloads as W
from gnnspark.plans.batches import Sizes
from gnnspark.sources.graphs import load_graph
from gnnspark.sources.spool import Spool, spool


@pytest.mark.parametrize("ids", [[3 * 2**40 + i for i in range(50)], [-(2**60), -1, 0, 7, 123456, 2**62], [5]])
def test_bits_of_free_pairs_are_those_of_md5(ids):
    heads = [f"7:0:{b}:1:".encode() for b in (0, 9, 10, 4711, 2**62)] + [b"", b"x" * 50]
    rng, tails = np.random.default_rng(1), Tails(np.array(ids))
    which, at = rng.integers(0, len(heads), 300), rng.integers(0, len(ids), 300)
    want = lambda h, t: int(hashlib.md5(h + str(ids[t]).encode()).hexdigest()[:8], 16)
    assert tails.bits(heads, which, at).tolist() == [want(heads[h], t) for h, t in zip(which, at)]
    for h in heads:
        assert tails.bits([h], None, at).tolist() == [want(h, t) for t in at]
    assert not len(tails.bits([b"a"], None, at[:0]))


def both(spark, g, name, models, monkeypatch):
    """Rows of the plans and of the arrays."""
    keep = Spool(spark)
    g = replace(g, nodes=spool(g.nodes))
    train = g.nodes.where(W.split_of(F.col("node_id"), name) == "train").select("node_id")
    n = max(1, -(-train.count() // W.BATCH))
    want = W.planned(g, train, n, models).select(*epochs.TOLD).collect()
    with monkeypatch.context() as m:
        m.setattr(W, "planned", None)
        m.setattr(local, "PIECE", 500)
        got = epochs.counts(g, train, n, models, Sizes(W.BATCH, W.FANOUT, W.SIZE), W.CACHE_SHARE, keep)
        return sorted(map(tuple, want)), got and sorted(map(tuple, got.collect()))


@pytest.mark.parametrize("name", ["cust_supp", "emb_knn", "part_pair"])
def test_counts_here_are_those_of_the_plans(spark, sf, name, monkeypatch):
    """Every number of every batch, for node-wise models and both layer-wise bases, plain and flat; some models share samples, layers are smaller than their pools."""
    monkeypatch.setattr(W, "SIZE", 24)
    monkeypatch.setattr(W, "BATCH", 16)
    models = ("ladies", "gcn", "fastgcn_f", "graphsage", "ladies_fd", "fastgcn")
    want, got = both(spark, load_graph(spark, sf, name), name, models, monkeypatch)
    assert got == want and len(got) >= 6


def test_repeated_nodes_and_large_graphs_take_the_plans(spark, sf, monkeypatch):
    g = load_graph(spark, sf, "cust_supp")
    want, got = both(spark, replace(g, nodes=g.nodes.union(g.nodes.limit(3))), "cust_supp", ("gcn",), monkeypatch)
    assert got is None and want
    monkeypatch.setattr(local, "ENTRIES", 10)
    assert both(spark, g, "cust_supp", ("gcn",), monkeypatch)[1] is None


def test_workloads_read_no_neighbours_as_rows(spark, sf, monkeypatch):
    """The registered workloads count batches from arrays: no plan of the samplers runs, and the arrays are gone after it."""
    kept = []
    monkeypatch.setattr(W, "planned", None)
    monkeypatch.setattr(layerwise.LayerSampler, "layers", None)
    monkeypatch.setattr(W, "Spool", lambda s: kept.append(Spool(s)) or kept[-1])
    stats = W.epoch_stats(spark, sf, "cust_supp", ("gcn", "ladies"))
    assert stats.groupBy("model").count().count() == 2
    path = spark._jvm.org.apache.hadoop.fs.Path(kept[0].folder)
    assert not path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(path)


def test_data_sets_go_one_after_another(spark, sf, monkeypatch):
    """A graph's files are let go before the next one is read, and graphs of 140 million entries lie in arrays."""
    seen = []
    monkeypatch.setattr(W, "load_graph", lambda s, d, name: seen.append(name) or load_graph(s, d, name))
    monkeypatch.setattr(W, "let_go", lambda s: seen.append("gone"))
    assert len(W.all_stats(spark, sf, ("cust_supp", "emb_knn"), ("gcn",))) == 2
    assert seen == ["cust_supp", "gone", "emb_knn", "gone"] and local.ENTRIES >= 140_000_000
