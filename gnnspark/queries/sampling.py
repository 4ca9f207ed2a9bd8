"""Node-wise and layer-wise sampling, draws, weights and estimator error."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import draws, estimators, layerwise, model, nodewise
from ..operators.propagation import degrees, propagation
from ..functions.hashing import uniform
from ..plans.batches import kept
from ..plans.errors import lot_errors
from ..sources.features import embedding_features, exploded
from ..sources.graphs import key, load_graph
from ..sources.spool import Spool, spool
from ..sources.tables import read
from .base import BATCHES, FANOUT, SEEDS, SIZE, Setup, k_sql, prop_sql, query, r6, seeds_sql, sql, u_sql

BASE = "cust_part"
SQL = [*prop_sql(BASE), seeds_sql()]


def ns_sql(out: str, frontier: str, layer: int, k: int = FANOUT, order: str = "") -> str:
    u = u_sql(7, 0, "batch_id", layer, "dst", "src")
    return f"{out} AS MATERIALIZED (SELECT batch_id, {layer} AS layer, dst, src FROM (SELECT f.batch_id, dst, src, row_number() OVER (PARTITION BY f.batch_id, dst ORDER BY {order}{u}, src) AS r FROM {frontier} f JOIN a ON dst = f.node_id) WHERE r <= {k})"


def front_sql(out: str, frontier: str, block: str) -> str:
    return f"{out} AS MATERIALIZED (SELECT batch_id, node_id FROM {frontier} UNION SELECT batch_id, src FROM {block})"


TWO_HOPS = [ns_sql("b1", "s", 1), front_sql("f1", "s", "b1"), ns_sql("b0", "f1", 0), front_sql("f0", "f1", "b0")]


@query(sql([*SQL, ns_sql("b1", "s", 1)], "SELECT * FROM b1"))
def ns_one_hop(spark, d):
    x = Setup(spark, d, BASE)
    return nodewise.sample_neighbors(x.seeds, x.g.edges, FANOUT, 1)


@query(sql([*SQL, *TWO_HOPS], "SELECT * FROM b0"))
def ns_two_hop(spark, d):
    x = Setup(spark, d, BASE)
    return nodewise.node_wise_batches(x.seeds, x.g.edges, [FANOUT, FANOUT])[0][1]


@query(sql([*SQL, "ra AS (SELECT dst, src, row_number() OVER (PARTITION BY dst ORDER BY src) - 1 AS at0, count(*) OVER (PARTITION BY dst) AS deg FROM a)"], f"SELECT batch_id, 1 AS layer, dst, src, t::INT AS t FROM (SELECT batch_id, node_id, unnest(range({FANOUT})) AS t FROM s) JOIN ra ON dst = node_id AND at0 = floor({u_sql(7, 0, 'batch_id', 1, 'dst', 't')} * deg)"))
def ns_replace(spark, d):
    x = Setup(spark, d, BASE)
    return nodewise.sample_neighbors(x.seeds, x.g.edges, FANOUT, 1, replace=True)


@query(sql([*SQL, ns_sql("b1", "s", 1)], "SELECT batch_id, layer, dst, src, round(1.0::DOUBLE / count(*) OVER (PARTITION BY batch_id, dst), 6) AS w FROM b1"))
def sage_weights(spark, d):
    x = Setup(spark, d, BASE)
    return nodewise.sage_weights(nodewise.sample_neighbors(x.seeds, x.g.edges, FANOUT, 1)).withColumn("w", r6("w"))


@query(sql([*SQL, ns_sql("b1", "s", 1)], "SELECT b.batch_id, 1 AS layer, dst, src, round(w * deg / count(*) OVER (PARTITION BY b.batch_id, dst), 6) AS w FROM b1 b JOIN p ON row = dst AND col = src JOIN (SELECT dst AS v, count(*) AS deg FROM a GROUP BY dst) ON v = dst UNION ALL SELECT batch_id, 1, node_id, node_id, round(w, 6) FROM s JOIN p ON row = node_id AND col = node_id"))
def gcn_block(spark, d):
    x = Setup(spark, d, BASE)
    return nodewise.gcn_block(nodewise.sample_neighbors(x.seeds, x.g.edges, FANOUT, 1), x.seeds, x.prop, 1).withColumn("w", r6("w"))


FULL = ["h1 AS MATERIALIZED (SELECT batch_id, node_id FROM s UNION SELECT batch_id, src FROM s JOIN a ON dst = node_id)", "h2 AS MATERIALIZED (SELECT batch_id, node_id FROM h1 UNION SELECT batch_id, src FROM h1 JOIN a ON dst = node_id)"]


@query(sql([*SQL, *FULL], "SELECT batch_id, 0 AS hop, count(*) AS n FROM s GROUP BY batch_id UNION ALL SELECT batch_id, 1, count(*) FROM h1 GROUP BY batch_id UNION ALL SELECT batch_id, 2, count(*) FROM h2 GROUP BY batch_id"))
def full_two_hop(spark, d):
    x = Setup(spark, d, BASE)
    return nodewise.expand_full(x.seeds, x.g.edges, 2).groupBy("batch_id", "hop").agg(F.count("*").alias("n"))


@query(sql([*SQL, *FULL, *TWO_HOPS], "SELECT round((SELECT count(*) FROM h2)::DOUBLE / (SELECT count(*) FROM f0), 6) AS ratio"))
def explosion_ratio(spark, d):
    x = Setup(spark, d, BASE)
    full = nodewise.expand_full(x.seeds, x.g.edges, 2).where("hop = 2").agg(F.count("*").alias("a"))
    kept = nodewise.node_wise_batches(x.seeds, x.g.edges, [FANOUT, FANOUT])[1][-1].agg(F.count("*").alias("b"))
    return full.withColumn("k", F.lit(1)).join(kept.withColumn("k", F.lit(1)), "k").select(r6(F.col("a") / F.col("b")).alias("ratio"))


@query(sql([*SQL, *TWO_HOPS], "SELECT batch_id, layer, count(*) AS edges, count(DISTINCT src) AS sources FROM (SELECT * FROM b1 UNION ALL SELECT * FROM b0) GROUP BY batch_id, layer"))
def ns_batch_sizes(spark, d):
    x = Setup(spark, d, BASE)
    blocks, _ = nodewise.node_wise_batches(x.seeds, x.g.edges, [FANOUT, FANOUT])
    return blocks[0].union(blocks[1]).groupBy("batch_id", "layer").agg(F.count("*").alias("edges"), F.countDistinct("src").alias("sources"))


@query("SELECT 0 AS violations")
def ns_invariants(spark, d):
    """Fan-out kept, sampled rows are edges, none repeated, small neighbourhoods whole."""
    x = Setup(spark, d, BASE)
    b = nodewise.sample_neighbors(x.seeds, x.g.edges, FANOUT, 1)
    deg = degrees(x.g).select(F.col("node_id").alias("dst"), "deg_in")
    per = b.groupBy("batch_id", "dst").agg(F.count("*").alias("n"), F.countDistinct("src").alias("u")).join(deg, "dst")
    wrong = per.select((F.col("n") != F.least("deg_in", F.lit(FANOUT))).cast("int").alias("v") + (F.col("n") != F.col("u")).cast("int"))
    foreign = b.join(x.g.edges, ["dst", "src"], "left_anti").select(F.lit(1))
    return wrong.toDF("v").union(foreign).agg(F.coalesce(F.sum("v"), F.lit(0)).cast("int").alias("violations"))


# ---- layer-wise ----


def colp_sql(power: int, flat_name: str = "cp") -> str:
    q = "sum(w * w)" if power == 2 else "sqrt(sum(w * w))"
    return f"{flat_name} AS MATERIALIZED (SELECT col AS node_id, {q} / sum({q}) OVER () AS p FROM p GROUP BY col)"


def race_sql(out: str, pool: str, layer: int, size: int = SIZE) -> str:
    return f"{out} AS MATERIALIZED (SELECT batch_id, {layer} AS layer, node_id, p, r AS ord FROM (SELECT batch_id, node_id, p, row_number() OVER (PARTITION BY batch_id ORDER BY -ln({u_sql(7, 0, 'batch_id', layer, 'node_id')}) / p, node_id) AS r FROM {pool} WHERE p > 0) WHERE r <= {size})"


def pool_sql(out: str, rows: str, base: str, power: int) -> str:
    if base == "fastgcn":
        return f"{out} AS (SELECT batch_id, node_id, p FROM cp, (SELECT DISTINCT batch_id FROM s))"
    q = "sum(w * w)" if power == 2 else "sqrt(sum(w * w))"
    return f"{out} AS MATERIALIZED (SELECT batch_id, node_id, q / sum(q) OVER (PARTITION BY batch_id) AS p FROM (SELECT r.batch_id, col AS node_id, {q} AS q FROM {rows} r JOIN p ON row = r.node_id GROUP BY ALL))"


def coef_sql(out: str, drawn: str, pool: str, debias: bool) -> str:
    if not debias:
        return f"{out} AS MATERIALIZED (SELECT *, 1.0::DOUBLE / (count(*) OVER (PARTITION BY batch_id) * p) AS coef FROM {drawn})"
    n, s, j = "c.n::DOUBLE", "count(*) OVER (PARTITION BY d.batch_id)::DOUBLE", "d.ord::DOUBLE"
    q = "p / greatest(1 - coalesce(sum(p) OVER (PARTITION BY d.batch_id ORDER BY d.ord ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0), 1e-12)"
    return f"{out} AS MATERIALIZED (SELECT batch_id, layer, node_id, p, ord, CASE WHEN s < n THEN n * (n - s) / (s * (n - j) * (n - j + 1)) / q + n * (s - j) / (s * (n - j)) ELSE 1.0 END AS coef FROM (SELECT d.*, {n} AS n, {s} AS s, {j} AS j, {q} AS q FROM {drawn} d JOIN (SELECT batch_id, count(*) AS n FROM {pool} WHERE p > 0 GROUP BY batch_id) c USING (batch_id)))"


def block_sql(out: str, rows: str, chosen: str, normalise: bool) -> str:
    w = "x.w * c.coef"
    text = f"SELECT r.batch_id, c.layer, row AS dst, col AS src, {w} AS w FROM {rows} r JOIN p x ON row = r.node_id JOIN {chosen} c ON c.batch_id = r.batch_id AND c.node_id = col"
    if normalise:
        text = f"SELECT batch_id, layer, dst, src, w / sum(w) OVER (PARTITION BY batch_id, dst) AS w FROM ({text})"
    return f"{out} AS MATERIALIZED ({text})"


def layers_sql(variant: str, layers: int = 2, size: int = SIZE) -> list[str]:
    """CTEs c1, k1 (chosen and block below the seeds), c0, k0."""
    base, flat, debias = layerwise.VARIANTS[variant]
    power, normalise = (1 if flat else 2), base == "ladies" and not debias
    out, rows = ([colp_sql(power)] if base == "fastgcn" else []), "s"
    for layer in reversed(range(layers)):
        out += [pool_sql(f"q{layer}", rows, base, power), race_sql(f"d{layer}", f"q{layer}", layer, size), coef_sql(f"c{layer}", f"d{layer}", f"q{layer}", debias), block_sql(f"k{layer}", rows, f"c{layer}", normalise)]
        rows = f"c{layer}"
    return out


def sampler(variant: str, **more) -> layerwise.LayerSampler:
    return layerwise.LayerSampler.named(variant, sizes=(SIZE, SIZE), **more)


for _name, _power in (("fastgcn_probs", 2), ("fastgcn_flat_probs", 1)):

    @query(sql([*prop_sql(BASE), colp_sql(_power)], "SELECT node_id, round(p, 9) AS p FROM cp"), _name)
    def _probs(spark, d, power=_power):
        return layerwise.column_probs(Setup(spark, d, BASE).prop, None, power).select("node_id", F.round("p", 9).alias("p"))


for _name, _power in (("ladies_probs", 2), ("ladies_flat_probs", 1)):

    @query(sql([*SQL, pool_sql("q", "s", "ladies", _power)], "SELECT batch_id, node_id, round(p, 9) AS p FROM q"), _name)
    def _lprobs(spark, d, power=_power):
        x = Setup(spark, d, BASE)
        return layerwise.column_probs(x.prop, x.seeds, power).select("batch_id", "node_id", F.round("p", 9).alias("p"))


@query(sql([*SQL, "f AS (SELECT DISTINCT batch_id, col AS node_id FROM s JOIN p ON row = s.node_id)"], "SELECT batch_id, node_id, round(1.0::DOUBLE / count(*) OVER (PARTITION BY batch_id), 9) AS p FROM f"))
def ladies_flat_activation_uniform(spark, d):
    """Flat probabilities from activations fall to the uniform when no activations are known."""
    x = Setup(spark, d, BASE)
    return layerwise.activation_probs(x.prop, spark.range(0).select(F.col("id").alias("node_id"), F.lit(1.0).alias("h")), x.seeds).select("batch_id", "node_id", F.round("p", 9).alias("p"))


@query(sql([*SQL, "q AS (SELECT DISTINCT batch_id, col AS node_id FROM s JOIN p ON row = s.node_id)"], "SELECT batch_id, node_id FROM q"))
def ladies_candidates(spark, d):
    x = Setup(spark, d, BASE)
    return layerwise.column_probs(x.prop, x.seeds).select("batch_id", "node_id")


def _prefix_sql() -> str:
    return "ps AS (SELECT node_id, p, sum(p) OVER (ORDER BY node_id) - p AS low, sum(p) OVER (ORDER BY node_id) AS high FROM cp)"


@query(sql([*SQL, colp_sql(2), _prefix_sql(), f"dr AS (SELECT batch_id, t, {u_sql(7, 0, 'batch_id', 1, 't')} AS u FROM (SELECT DISTINCT batch_id FROM s), (SELECT unnest(range({SIZE}))::INT AS t))"], "SELECT batch_id, 1 AS layer, t, node_id FROM dr JOIN ps ON low <= u AND u < high"))
def fastgcn_draw_iid(spark, d):
    x = Setup(spark, d, BASE)
    return draws.iid(layerwise.column_probs(x.prop), x.seeds, SIZE, 1).select("batch_id", "layer", "t", "node_id")


@query(sql([*SQL, *layers_sql("fastgcn")], "SELECT batch_id, layer, node_id, ord FROM d1"))
def fastgcn_draw_wor(spark, d):
    x = Setup(spark, d, BASE)
    return sampler("fastgcn").draw(x.prop, x.seeds, 1).select("batch_id", "layer", "node_id", "ord")


@query(sql([*SQL, colp_sql(2), _prefix_sql(), f"dr AS (SELECT batch_id, t, {u_sql(7, 0, 'batch_id', 1, 't')} AS u FROM (SELECT DISTINCT batch_id FROM s), (SELECT unnest(range({4 * SIZE}))::INT AS t))", "fa AS (SELECT batch_id, node_id, min(t) AS t FROM dr JOIN ps ON low <= u AND u < high GROUP BY ALL)"], f"SELECT batch_id, 1 AS layer, node_id, ord::INT AS ord FROM (SELECT *, row_number() OVER (PARTITION BY batch_id ORDER BY t) AS ord FROM fa) WHERE ord <= {SIZE}"))
def fastgcn_draw_arrivals(spark, d):
    """Without replacement by order of arrival: no product of batches and nodes."""
    x = Setup(spark, d, BASE)
    return sampler("fastgcn", by_arrival=True).draw(x.prop, x.seeds, 1).select("batch_id", "layer", "node_id", "ord")


@query(sql([*SQL, *layers_sql("ladies")], "SELECT batch_id, layer, node_id, ord FROM d1 UNION ALL SELECT batch_id, layer, node_id, ord FROM d0"))
def ladies_draw(spark, d):
    x = Setup(spark, d, BASE)
    chosen, _ = sampler("ladies").layers(x.prop, x.seeds)
    return chosen[0].select("batch_id", "layer", "node_id", "ord").union(chosen[1].select("batch_id", "layer", "node_id", "ord"))


for _variant in layerwise.VARIANTS:

    @query(sql([*SQL, *layers_sql(_variant)], "SELECT batch_id, layer, dst, src, round(w, 6) AS w FROM (SELECT * FROM k1 UNION ALL SELECT * FROM k0)"), f"block_{_variant}")
    def _block(spark, d, variant=_variant):
        x = Setup(spark, d, BASE)
        _, blocks = sampler(variant).layers(x.prop, x.seeds)
        return blocks[0].union(blocks[1]).withColumn("w", r6("w"))


@query(" UNION ALL ".join("SELECT * FROM (" + sql([*SQL, *layers_sql(v)], f"SELECT '{v}' AS variant, layer, count(*) AS edges, count(DISTINCT (batch_id, dst)) AS rows_hit FROM (SELECT * FROM k1 UNION ALL SELECT * FROM k0) GROUP BY layer") + ")" for v in layerwise.VARIANTS))
def ls_variant_sizes(spark, d):
    x, out, keep = Setup(spark, d, BASE), None, Spool(spark)
    prop, seeds = keep(x.prop), keep(x.seeds)  # all variants read them
    for v in layerwise.VARIANTS:
        blocks = sampler(v, keep=keep).layers(prop, seeds)[1]
        one = blocks[0].union(blocks[1]).groupBy("layer").agg(F.count("*").alias("edges"), F.countDistinct("batch_id", "dst").alias("rows_hit")).select(F.lit(v).alias("variant"), "layer", "edges", "rows_hit")
        out = one if out is None else out.union(one)
    return out


@query(sql([*SQL, colp_sql(2), _prefix_sql(), f"dr AS (SELECT batch_id, {u_sql(7, 0, 'batch_id', 1, 't')} AS u FROM (SELECT DISTINCT batch_id FROM s), (SELECT unnest(range({SIZE})) AS t))", "dn AS (SELECT batch_id, 1 AS layer, node_id, any_value(p) AS p, count(*) AS times FROM dr JOIN ps ON low <= u AND u < high GROUP BY batch_id, node_id)", f"c AS (SELECT *, times / ({SIZE} * p) AS coef FROM dn)", block_sql("k", "s", "c", False)], "SELECT batch_id, layer, dst, src, round(w, 6) AS w FROM k"))
def fastgcn_block_iid(spark, d):
    x = Setup(spark, d, BASE)
    s = sampler("fastgcn", replace=True)
    return layerwise.block_of(x.prop, x.seeds, s.draw(x.prop, x.seeds, 1), False).withColumn("w", r6("w"))


@query(sql([*SQL, *layers_sql("ladies", 2)[:3]], "SELECT batch_id, node_id, round(coef, 6) AS coef FROM c1"))
def importance_coef(spark, d):
    x = Setup(spark, d, BASE)
    return sampler("ladies").draw(x.prop, x.seeds, 1).select("batch_id", "node_id", r6("coef").alias("coef"))


@query(sql([*SQL, *layers_sql("ladies_d", 2)[:3]], "SELECT batch_id, node_id, ord, round(coef, 6) AS coef FROM c1"))
def debias_coef(spark, d):
    x = Setup(spark, d, BASE)
    return sampler("ladies_d").draw(x.prop, x.seeds, 1).select("batch_id", "node_id", "ord", r6("coef").alias("coef"))


@query(sql([*SQL, "q AS (SELECT batch_id, v AS node_id, 1.0::DOUBLE / 100 AS p FROM (SELECT DISTINCT batch_id FROM s), (SELECT unnest(range(100)) AS v))", race_sql("dd", "q", 1, 20)], "SELECT batch_id, node_id, 5.0::DOUBLE AS coef FROM dd"))
def debias_uniform_is_n_over_s(spark, d):
    x = Setup(spark, d, BASE)
    pool = x.seeds.select("batch_id").distinct().select("batch_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(99).cast("long"))).alias("node_id"), (F.lit(1.0) / 100).alias("p"))
    return draws.debias_weights(draws.race(pool, 20, 1), F.lit(100)).select("batch_id", "node_id", r6("coef").alias("coef"))


def _empty_sql(name: str, variant: str) -> str:
    return sql([*prop_sql(name), seeds_sql(), *layers_sql(variant)[: 5 if variant.startswith("fast") else 4]], f"SELECT '{variant}' AS variant, count(*) AS rows, count(*) FILTER (NOT hit) AS empty, round(count(*) FILTER (NOT hit)::DOUBLE / count(*), 6) AS share FROM (SELECT s.*, EXISTS (SELECT 1 FROM k1 WHERE k1.batch_id = s.batch_id AND dst = node_id) AS hit FROM s)")


@query(" UNION ALL ".join(f"SELECT * FROM ({_empty_sql('docs_lex', v)})" for v in ("fastgcn", "fastgcn_f", "ladies", "ladies_f")))
def empty_rows_fast_vs_ladies(spark, d):
    x, out = Setup(spark, d, "docs_lex"), None
    for v in ("fastgcn", "fastgcn_f", "ladies", "ladies_f"):
        s = sampler(v)
        block = layerwise.block_of(x.prop, x.seeds, s.draw(x.prop, x.seeds, 1), False)
        one = layerwise.empty_row_share(block, x.seeds).select(F.lit(v).alias("variant"), "rows", "empty", "share")
        out = one if out is None else out.union(one)
    return out


@query(sql([*SQL, *layers_sql("fastgcn")[:4]], "SELECT batch_id, round(avg(p * 1000), 6) AS loss FROM c1 GROUP BY batch_id"))
def fastgcn_loss(spark, d):
    x = Setup(spark, d, BASE)
    top = sampler("fastgcn").draw(x.prop, x.seeds, 1).withColumn("g", F.col("p") * 1000)
    return layerwise.sampled_loss(top).select("batch_id", r6("loss").alias("loss"))


# ---- estimator error over draws ----

RUNS, ERR_SIZE, ERR_VARIANTS = 10, 64, list(layerwise.VARIANTS)


def _err_sql(variants: list[str], graph: str = "emb_knn") -> str:
    """Each of ten seeds is a batch of its own over the same rows, so that one plan serves all runs."""
    ctes = [*prop_sql(graph), f"s0 AS (SELECT node_id FROM n ORDER BY {u_sql(7, chr(39) + 'err' + chr(39), 'node_id')}, node_id LIMIT 32)", f"s AS MATERIALIZED (SELECT b AS batch_id, node_id FROM s0, (SELECT unnest(range({RUNS})) AS b))", "x AS (SELECT vec_id AS node_id, generate_subscripts(embedding, 1) AS pos, unnest(embedding)::DOUBLE AS x FROM embeddings)", "tz AS MATERIALIZED (SELECT row AS dst, pos, sum(w * x) AS z FROM s0 JOIN p ON row = s0.node_id JOIN x ON col = x.node_id GROUP BY ALL)"]
    parts = []
    for v in variants:
        base, flat, debias = layerwise.VARIANTS[v]
        power = 1 if flat else 2
        tag = v.replace("_", "")
        pre = [colp_sql(power, f"cp{tag}"), f"q{tag} AS (SELECT batch_id, node_id, p FROM cp{tag}, (SELECT DISTINCT batch_id FROM s))"] if base == "fastgcn" else [pool_sql(f"q{tag}", "s", base, power)]
        ctes += [*pre, race_sql(f"d{tag}", f"q{tag}", 0, ERR_SIZE), coef_sql(f"c{tag}", f"d{tag}", f"q{tag}", debias), block_sql(f"k{tag}", "s", f"c{tag}", False)]
        est = f"SELECT batch_id, dst, pos, sum(w * x) AS z FROM k{tag} JOIN x ON src = x.node_id GROUP BY ALL"
        cell = f"SELECT dst, pos, any_value(t.z) AS truth, sum(coalesce(e.z, 0) - t.z) AS se, sum((coalesce(e.z, 0) - t.z) * (coalesce(e.z, 0) - t.z)) AS see FROM (SELECT * FROM tz, (SELECT unnest(range({RUNS})) AS batch_id)) t LEFT JOIN ({est}) e USING (batch_id, dst, pos) GROUP BY dst, pos"
        parts.append(f"SELECT '{v}' AS variant, round(sqrt(sum(see / {RUNS}.0) / sum(truth * truth)), 6) AS rmse, round(sqrt(sum((se / {RUNS}.0) * (se / {RUNS}.0)) / sum(truth * truth)), 6) AS bias FROM ({cell})")
    return sql(ctes, " UNION ALL ".join(parts))


def estimator_runs(spark, d, variants):
    """Errors of one layer's estimate over ten seeds; features are the embeddings themselves."""
    g = load_graph(spark, d, "emb_knn")
    prop = spool(propagation(g))
    rows = g.nodes.select("node_id").orderBy(uniform(7, "err", F.col("node_id")), "node_id").limit(32)
    seeds = spool(rows.select("node_id", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(RUNS - 1).cast("long"))).alias("batch_id")))
    blocks = None
    for v in variants:
        s = layerwise.LayerSampler.named(v, sizes=(ERR_SIZE,))
        one = layerwise.block_of(prop, seeds, s.draw(prop, seeds, 0), False).select(F.lit(v).alias("variant"), F.col("batch_id").alias("seed"), "dst", "src", "w")
        blocks = one if blocks is None else blocks.union(one)
    exact = prop.join(rows, prop["row"] == rows["node_id"]).select(F.col("row").alias("dst"), F.col("col").alias("src"), "w")
    return estimators.estimator_error(blocks, exact, exploded(embedding_features(spark, d)))


@query(_err_sql(ERR_VARIANTS))
def est_error_by_variant(spark, d):
    return estimator_runs(spark, d, ERR_VARIANTS).select("variant", r6("rmse").alias("rmse"), r6("bias").alias("bias"))


@query(f"SELECT 1 AS debias_smaller FROM ({_err_sql(['fastgcn', 'fastgcn_d'])}) LIMIT 1")
def bias_debias_vs_plain(spark, d):
    """Debiased weights have the smaller bias where draws without replacement are plainly weighted."""
    told = estimator_runs(spark, d, ["fastgcn", "fastgcn_d"])
    return told.agg((F.max(F.when(F.col("variant") == "fastgcn_d", F.col("bias"))) < F.max(F.when(F.col("variant") == "fastgcn", F.col("bias")))).cast("int").alias("debias_smaller"))


WIDE, NARROW = 64, 16
HW = f"hw AS MATERIALIZED (SELECT node_id, sqrt(sum(z * z)) AS v FROM (SELECT vec_id AS node_id, j, sum(x * (2 * {u_sql(7, chr(39) + 'w' + chr(39), 1, 'i', 'j')} - 1) * sqrt(6.0::DOUBLE / {WIDE + NARROW})) AS z FROM (SELECT vec_id, generate_subscripts(embedding, 1) - 1 AS i, unnest(embedding)::DOUBLE AS x FROM embeddings), (SELECT unnest(range({NARROW})) AS j) GROUP BY ALL) GROUP BY node_id)"


def activations(spark, d):
    """(node_id, h): row norms of the embeddings times the initial weights of the first layer."""
    return layerwise.activation_norms(exploded(embedding_features(spark, d)), model.weights(model.init_params(spark, (WIDE, NARROW)), 1))


@query(sql([*prop_sql("emb_knn"), HW, "c AS (SELECT col AS node_id, sqrt(sum(w * w)) AS h FROM p GROUP BY col)"], "SELECT count(*) AS n, round(corr(h, v), 6) AS r FROM c JOIN hw USING (node_id)"))
def norm_corr(spark, d):
    """How column norms of the operator correlate with the norms of the activations: the argument for flat probabilities."""
    prop = Setup(spark, d, "emb_knn").prop
    h = prop.groupBy(F.col("col").alias("node_id")).agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("h"))
    v = activations(spark, d).withColumnRenamed("h", "v")
    return h.join(v, "node_id").agg(F.count("*").alias("n"), F.round(F.corr("h", "v"), 6).alias("r"))


@query(sql([*prop_sql("emb_knn"), seeds_sql(), HW, "q AS (SELECT DISTINCT batch_id, col AS node_id FROM s JOIN p ON row = s.node_id)"], "SELECT batch_id, node_id, round(v / sum(v) OVER (PARTITION BY batch_id), 9) AS p FROM q JOIN hw USING (node_id)"))
def ladies_flat_activation(spark, d):
    """Flat probabilities from the norms of the activations, over the columns that a batch's rows touch."""
    x = Setup(spark, d, "emb_knn")
    return layerwise.activation_probs(x.prop, activations(spark, d), x.seeds).select("batch_id", "node_id", F.round("p", 9).alias("p"))


# ---- the ablation of flat and debiased draws over all rows of two graphs ----

LOT = 512
SCALAR_SQL = {
    "cust_part": f"SELECT {k_sql('customer', 'c_custkey')} AS node_id, 0 AS pos, c_acctbal / 10000.0 AS x FROM customer UNION ALL SELECT {k_sql('part', 'p_partkey')}, 0, p_retailprice / 2000.0 FROM part",
    "docs_lex": f"SELECT {k_sql('document', 'doc_id')} AS node_id, 0 AS pos, n_chars / 1000.0 AS x FROM documents",
}


def scalar_features(spark, d, graph: str):
    """(node_id, pos, x): one value a node; balances and prices, or lengths of texts."""
    zero = F.lit(0).alias("pos")
    if graph == "docs_lex":
        return read(spark, d, "documents", "doc_id", "n_chars").select(key("document", "doc_id").alias("node_id"), zero, (F.col("n_chars") / 1000.0).alias("x"))
    customers = read(spark, d, "customer", "c_custkey", "c_acctbal").select(key("customer", "c_custkey").alias("node_id"), zero, (F.col("c_acctbal") / 10000.0).alias("x"))
    parts = read(spark, d, "part", "p_partkey", "p_retailprice").select(key("part", "p_partkey").alias("node_id"), zero, (F.col("p_retailprice") / 2000.0).alias("x"))
    return customers.union(parts)


def _ablation_sql(graph: str) -> str:
    lots = f"(SELECT greatest(1, ceil(count(*) / {LOT}.0))::BIGINT FROM n)"
    ctes = [*prop_sql(graph), f"s0 AS MATERIALIZED (SELECT node_id, floor({u_sql(7, chr(39) + 'batch' + chr(39), 0, 'node_id')} * {lots})::BIGINT AS b FROM n)", f"s AS MATERIALIZED (SELECT r * {lots} + b AS batch_id, node_id FROM s0, (SELECT unnest(range({RUNS})) AS r))", f"x AS MATERIALIZED ({SCALAR_SQL[graph]})", "tz AS MATERIALIZED (SELECT row AS dst, sum(w * x) AS z FROM p JOIN x ON col = x.node_id GROUP BY row)"]
    parts = []
    for v in ERR_VARIANTS:
        base, flat, debias = layerwise.VARIANTS[v]
        power, tag = (1 if flat else 2), v.replace("_", "")
        pre = [colp_sql(power, f"cp{tag}"), f"q{tag} AS (SELECT batch_id, node_id, p FROM cp{tag}, (SELECT DISTINCT batch_id FROM s))"] if base == "fastgcn" else [pool_sql(f"q{tag}", "s", base, power)]
        ctes += [*pre, race_sql(f"d{tag}", f"q{tag}", 0, LOT), coef_sql(f"c{tag}", f"d{tag}", f"q{tag}", debias), block_sql(f"k{tag}", "s", f"c{tag}", False)]
        est = f"SELECT batch_id // {lots} AS r, dst, sum(w * x) AS z FROM k{tag} JOIN x ON src = x.node_id GROUP BY ALL"
        cell = f"SELECT dst, any_value(t.z) AS truth, sum(coalesce(e.z, 0) - t.z) AS se, sum((coalesce(e.z, 0) - t.z) * (coalesce(e.z, 0) - t.z)) AS see FROM (SELECT * FROM tz, (SELECT unnest(range({RUNS})) AS r)) t LEFT JOIN ({est}) e USING (r, dst) GROUP BY dst"
        parts.append(f"SELECT '{v}' AS variant, round(sqrt(sum(see / {RUNS}.0) / sum(truth * truth)), 5) AS rmse, round(sqrt(sum((se / {RUNS}.0) * (se / {RUNS}.0)) / sum(truth * truth)), 5) AS bias FROM ({cell})")
    return sql(ctes, " UNION ALL ".join(parts))


for _graph in SCALAR_SQL:

    @query(_ablation_sql(_graph), f"wl_variant_error_{_graph}")
    def _ablation(spark, d, graph=_graph):
        """(variant, rmse, bias): all rows of the graph in batches of 512, with 512 draws a batch, over ten seeds."""
        keep = Spool(spark)
        g, scalar = kept(load_graph(spark, d, graph), keep), scalar_features(spark, d, graph)
        lots = max(1, -(-g.nodes.count() // LOT))
        told = lot_errors(g, scalar, lots, LOT, RUNS, keep)
        if told is not None:
            return told.select("variant", F.round("rmse", 5).alias("rmse"), F.round("bias", 5).alias("bias"))
        prop = keep(propagation(g))
        place = F.floor(uniform(7, "batch", 0, F.col("node_id")) * lots)
        turns = F.explode(F.sequence(F.lit(0), F.lit(RUNS - 1)))
        seeds = spool(g.nodes.select("node_id", place.alias("b"), turns.alias("r")).select((F.col("r") * lots + F.col("b")).cast("long").alias("batch_id"), "node_id"))
        blocks = None
        for v in ERR_VARIANTS:
            s = layerwise.LayerSampler.named(v, sizes=(LOT,))
            cut = layerwise.block_of(prop, seeds, s.draw(prop, seeds, 0), False)
            one = cut.select(F.lit(v).alias("variant"), F.floor(F.col("batch_id") / lots).alias("seed"), "dst", "src", "w")
            blocks = one if blocks is None else blocks.union(one)
        exact = prop.select(F.col("row").alias("dst"), F.col("col").alias("src"), "w")
        told = estimators.estimator_error(blocks, exact, scalar)
        return told.select("variant", F.round("rmse", 5).alias("rmse"), F.round("bias", 5).alias("bias"))
