"""Batches that tasks sample from a graph's arrays, and text features in numpy."""

import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from gnnspark.plans import batches as B
from gnnspark.plans import grid, local
from gnnspark.queries import training as T
from gnnspark.sources.features import text_features
from gnnspark.sources.spool import Spool


def test_text_features_count_grams(spark):
    """Rows are counts of md5 places over their norm, whatever the alphabet; short texts have none."""
    texts = ["ab", "", None, "abc", "aAaAa b\n", "".join(map(chr, range(300, 700))) * 2, "\U0001f600xy\U0001f600xy"]
    got = {r["node_id"]: r["f"] for r in text_features(spark.createDataFrame(list(enumerate(texts)), "node_id long, text string"), 10).collect()}
    assert sorted(got) == [3, 4, 5, 6]
    for i, f in got.items():
        t, want = texts[i].lower(), np.zeros(10)
        for k in range(len(t) - 2):
            want[int(hashlib.md5(t[k : k + 3].encode()).hexdigest()[:8], 16) % 10] += 1
        assert np.allclose(f, want / np.sqrt((want**2).sum()), atol=1e-6)


@pytest.fixture(scope="module")
def made(spark, sf):
    """All streams of a graph by Spark's plans, and a sampler over its arrays."""
    keep, sizes = Spool(spark), B.Sizes(16, 3, 24, 2)
    g, feats, labels, _ = T.documents(spark, sf, keep, 12)
    g = B.kept(g, keep)
    streams = [B.Stream(m, c) for m in B.MODELS for c in (False, True) if not c or m in B.NODE_WISE]
    x = B.prepare(g, labels, sizes, keep)
    cache = keep(B.C.build_cache(x.cache_p, 20, 0, 7))
    seeds, ids, _ = B.seeds_of(x.known, streams, sizes)
    seeds = keep(seeds)
    edges, inputs = B.sampled(x.g, x.prop, seeds, ids, streams, sizes, cache, keep)
    rows = {r["batch_id"]: r for r in B.package(seeds, edges, inputs, feats, x.known.select("node_id", "y")).collect()}
    return rows, ids, streams, local.Sampler(local.arrays(g, x.known, cache, feats, f"{keep.folder}/arrays"), streams, sizes), g


def test_sampled_here_equals_the_plans(made):
    """Every batch of every stream, epoch and split: seeds, labels, edges, weights, inputs and features."""
    rows, ids, streams, sampler, _ = made
    assert (sampler.id_form.epochs, sampler.id_form.width) == (ids.epochs, ids.width)
    told = [r for s in range(len(streams)) for e in range(4) for r in sampler.batches(s, e)]
    assert len(told) == len(rows) > 100
    for mine, b in zip(told, sorted(rows)):
        r = rows[b]
        assert mine.seeds.tolist() == r["seeds"] and mine.y.tolist() == r["y"] and mine.inputs.tolist() == r["inputs"]
        assert np.allclose(mine.x.reshape(-1), r["x"])
        assert list(zip(mine.layer.tolist(), mine.dst.tolist(), mine.src.tolist())) == list(zip(*(r[c] or [] for c in ("layer", "dst", "src"))))
        assert np.allclose(mine.w, r["w"] or [], rtol=1e-9)


def test_large_graphs_and_repeated_ids_take_the_plans(spark, made, monkeypatch):
    g = made[4]
    feats = spark.createDataFrame([(1, [0.5])], "node_id long, f array<float>")
    twice = g.nodes.limit(1).select("node_id", F.explode(F.array(F.lit(0), F.lit(1))).alias("y"), F.lit("train").alias("split"))
    assert local.arrays(g, twice, None, feats, Spool(spark).folder) is None
    assert local.fits(g, 100)
    monkeypatch.setattr(local, "ENTRIES", 10)
    assert not local.fits(g, 100)


def test_runs_end_alike_on_both_paths(spark, sf, monkeypatch):
    """The same metrics whether batches are packaged by plans or sampled by the tasks; an epoch after all stops is not sampled."""
    runs = [grid.Run("gcn", True, 2, 3), grid.Run("ladies_fd"), grid.Run("ladies_fd", True, 2, 3)]
    here = T.document_runs(spark, sf, runs, epochs=6, layer=24, patience=1)
    monkeypatch.setattr(local, "fits", lambda *_: False)
    plans = T.document_runs(spark, sf, runs, epochs=6, layer=24, patience=1)
    for kind in ("val", "stop", "best", "test", "applied", "loss"):
        a, b = ({(r["run"], r["epoch"], r["a"], r["b"], r["c"]): r["value"] for r in t.where(F.col("kind") == kind).collect()} for t in (here, plans))
        assert a.keys() == b.keys() and all(abs(a[k] - b[k]) < 1e-6 for k in a), kind


def test_runs_are_dealt_by_stream():
    runs = [grid.Run("ladies", True, w, p) for w in (2, 3) for p in (1, 2)] + [grid.Run("gcn")]
    streams = list(dict.fromkeys(r.stream for r in runs))
    for tasks in (1, 4, 100):
        dealt = grid.shares(runs, streams, tasks)
        assert sorted(sum(dealt, [])) == list(range(5)) and all(len({runs[n].stream for n in d}) == 1 for d in dealt)


def test_document_links_keep_the_bound(spark, tmp_path):
    """Tokens of 2 to 20 documents link them, both ways and once; the bits let tokens by, the join does not."""
    from gnnspark.sources.graphs import docs_lex

    texts = ["all one", "all one two", "all two two", None, "all"] + [f"all many{i % 2}" for i in range(42)]
    frame = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(99, f"x{i}") for i in range(1)], "doc_id long, text string")
    frame.write.parquet(f"{tmp_path}/documents.parquet")
    g = docs_lex(spark, str(tmp_path))
    assert sorted((r["src"] & 0xFF, r["dst"] & 0xFF) for r in g.edges.collect()) == [(0, 1), (1, 0), (1, 2), (2, 1)]


def test_dense_products_equal_sums():
    """Blocks with many entries for their size are matrices; both forms give the same sums."""
    from gnnspark.operators import kernels

    rng = np.random.default_rng(3)
    for n in (5, 400):
        coo = rng.integers(0, 12, n), rng.integers(0, 15, n), rng.random(n)
        h, g = rng.random((15, 4)), rng.random((12, 4))
        assert (kernels.dense(coo, 12, 15) is None) == (n == 5)
        assert np.allclose(kernels.spread(coo, h, 12), kernels.summed(coo[0], coo[2][:, None] * h[coo[1]], 12))
        assert np.allclose(kernels.collect(coo, g, 15), kernels.summed(coo[1], coo[2][:, None] * g[coo[0]], 15))


def test_hashes_in_pieces_equal_single_ones(monkeypatch):
    """Long arrays are hashed in pieces; what reaches a bound is found without the uniforms of the rest."""
    from gnnspark.functions import xxhash

    part, head = xxhash.long_part(np.arange(1000)), xxhash.with_int(7, xxhash.START)
    one = np.concatenate([xxhash.with_part(part[i : i + 1], head) for i in range(1000)])
    monkeypatch.setattr(xxhash, "PIECE", 64)
    assert (xxhash.with_part(part, head) == one).all() and (xxhash.with_part(part, np.repeat(head, 1000)) == one).all()
    u, bound = xxhash.uniforms(one), np.linspace(0, 1, 1000)
    at, h = xxhash.reaching(part, head, xxhash.least_hash(bound))
    assert (h == one[at]).all() and set(np.flatnonzero(u >= bound)) <= set(at.tolist()) and len(at) < 520
    assert (one <= xxhash.most_hash(bound))[u <= bound].all() and (one <= xxhash.most_hash(bound)).sum() < 520


def test_rows_with_too_few_early_entries_are_taken_whole(made, monkeypatch):
    """A first look that finds nothing changes no batch."""
    sampler, streams = made[3], made[2]
    mine = [s for s in range(len(streams)) if streams[s].model in B.NODE_WISE]
    want = [(r.src.tolist(), r.w.tolist()) for s in mine for r in sampler.batches(s, 0)]
    early = local.Sampler.early
    monkeypatch.setattr(local.Sampler, "early", lambda self, s, rows, heads, most: early(self, s, rows, heads, np.where(most < 1, 0.0, 1.0)))
    assert [(r.src.tolist(), r.w.tolist()) for s in mine for r in sampler.batches(s, 0)] == want


def test_nearest_neighbours_need_no_shuffle(spark):
    """Blocks of any size give the same neighbours as all cosines do, equal vectors by id; vectors with infinite components have none."""
    from gnnspark.sources.knn import nearest

    rng = np.random.default_rng(5)
    x = rng.normal(size=(60, 8))
    x[20:40] = x[0]
    ids = rng.permutation(60)
    frame = spark.createDataFrame([*((int(i), v.tolist()) for i, v in zip(ids, x)), (99, [float("inf")] * 8), (98, None), (97, [0.0] * 8)], "vec_id long, embedding array<double>")
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    cos = np.array([[(a * b).sum() for b in unit] for a in unit])
    want = {int(ids[i]): [int(ids[j]) for j in sorted((j for j in range(60) if j != i), key=lambda j: (-cos[i, j], ids[j]))[:7]] for i in range(60)}
    for block in (5, 1024):
        found = nearest(frame.repartition(3), 7, block=block)
        assert "Exchange" not in found._jdf.queryExecution().executedPlan().toString()
        got = {}
        for r in sorted(found.collect(), key=lambda r: (r["vec_id"], -r["cosine"], r["neighbour"])):
            got.setdefault(r["vec_id"], []).append(r["neighbour"])
        assert got == want
