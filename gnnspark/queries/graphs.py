"""Graphs, operator, splits, features, labels, batches."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import batching
from ..operators import propagation as P
from ..sources import features
from ..sources.graphs import NAMES, load_graph
from .base import graph_sql, k_sql, prop_sql, query, r6, split_sql, sql, u_sql

WIDTHS = {"cust_part": (16, 2), "cust_supp": (8, 2), "part_pair": (128, 2), "docs_lex": (100, 4), "docs_tok": (0, 0), "emb_knn": (64, 10), "user_hops": (5, 2), "page_links": (8, 0), "turns": (32, 3), "geo_tree": (5, 5)}

for _name in NAMES:

    @query(sql(graph_sql(_name), "SELECT src, dst FROM a"), f"graph_{_name}")
    def _graph(spark, d, name=_name):
        return load_graph(spark, d, name).edges.select("src", "dst")


def _summary_sql(name: str, seed: int = 7) -> str:
    d, c = WIDTHS[name]
    e = "count(*)" if name in ("emb_knn", "user_hops", "page_links", "turns") else "(count(*) // 2)"
    shares = ", ".join(f"count(*) FILTER (s = '{k}') AS n_{k}" for k in ("train", "val", "test"))
    return sql(graph_sql(name), f"SELECT '{name}' AS graph, v, e, round(2.0::DOUBLE * e / v, 6) AS avg_degree_und, round(e::DOUBLE / v, 6) AS edges_per_node, {d} AS width, {c} AS classes, n_train, n_val, n_test FROM (SELECT {e} AS e FROM a), (SELECT count(*) AS v, {shares} FROM (SELECT {split_sql(name, seed)} AS s FROM n))")


@query(" UNION ALL ".join(f"SELECT * FROM ({_summary_sql(n)})" for n in NAMES))
def summary_all(spark, d):
    out = None
    for name in NAMES:
        one = P.summary(load_graph(spark, d, name), *WIDTHS[name])
        out = one if out is None else out.unionByName(one)
    return out


@query(sql(graph_sql("cust_part"), "SELECT node_id, coalesce(c, 0) AS deg_in, coalesce(c, 0) AS deg_out, coalesce(c, 0) AS deg FROM n LEFT JOIN (SELECT dst, count(*) AS c FROM a GROUP BY dst) ON dst = node_id"))
def degrees_cust_part(spark, d):
    return P.degrees(load_graph(spark, d, "cust_part"))


@query(sql(graph_sql("docs_tok"), "SELECT count(*) AS nodes, count(*) FILTER (r <= k) AS top_nodes, round(sum(c) FILTER (r <= k) / sum(c), 6) AS top_share FROM (SELECT c, row_number() OVER (ORDER BY c DESC) AS r, greatest(1, floor(count(*) OVER () * 0.01)) AS k FROM (SELECT node_id, count(dst) AS c FROM n LEFT JOIN a ON dst = node_id GROUP BY node_id))"))
def degree_skew(spark, d):
    return P.degree_skew(load_graph(spark, d, "docs_tok"))


@query(sql(graph_sql("geo_tree"), "SELECT dst AS row, src AS col FROM a UNION ALL SELECT node_id, node_id FROM n"))
def self_loops(spark, d):
    return P.with_self_loops(load_graph(spark, d, "geo_tree"))


for _name, _graph_name, _operator in (("prop_sym", "cust_supp", "sym"), ("prop_row", "cust_supp", "row"), ("prop_self_loop", "geo_tree", "self_loop"), ("prop_sym_directed", "user_hops", "sym")):

    @query(sql(prop_sql(_graph_name, _operator), "SELECT row, col, round(w, 6) AS w FROM p"), _name)
    def _prop(spark, d, graph=_graph_name, operator=_operator):
        return P.propagation(load_graph(spark, d, graph), operator).select("row", "col", r6("w").alias("w"))


@query(" UNION ALL ".join(f"SELECT * FROM ({sql(graph_sql(n), f'SELECT {chr(39)}{n}{chr(39)} AS graph, {split_sql(n)} AS split, count(*) AS n FROM n GROUP BY ALL')})" for n in ("cust_supp", "emb_knn", "part_pair", "cust_part")))
def split_shares(spark, d):
    out = None
    for n in ("cust_supp", "emb_knn", "part_pair", "cust_part"):
        one = P.assign_split(load_graph(spark, d, n)).groupBy("split").agg(F.count("*").alias("n")).select(F.lit(n).alias("graph"), "split", "n")
        out = one if out is None else out.union(one)
    return out


def _feat_docs_sql(width: int) -> str:
    h = f"(('0x' || substr(md5(tri), 1, 8))::BIGINT % {width})"
    return f"WITH t AS (SELECT doc_id, lower(coalesce(text, '')) AS x FROM documents), g AS (SELECT doc_id, unnest(list_transform(range(1, greatest(length(x) - 1, 1)), lambda i: substr(x, i, 3))) AS tri FROM t), c AS (SELECT doc_id, {h} AS pos, count(*) AS c FROM g GROUP BY ALL) SELECT {k_sql('document', 'doc_id')} AS node_id, pos, round(c / sqrt(sum(c * c) OVER (PARTITION BY doc_id)), 6) AS x FROM c"


@query(_feat_docs_sql(100))
def feat_docs(spark, d):
    return features.document_trigrams(spark, d, 100, dense=False).select("node_id", "pos", r6("x").alias("x"))


@query(f"SELECT {k_sql('customer', 'c_custkey')} AS node_id, round(c_acctbal / 10000.0, 6) AS x0, c_nationkey % 7 AS hash7 FROM customer")
def feat_cust(spark, d):
    f = features.customer_features(spark, d)
    return f.select("node_id", F.round(F.element_at("f", 1).cast("double"), 6).alias("x0"), F.col("hash7"))


@query(sql([*graph_sql("cust_supp"), f"x AS (SELECT {k_sql('customer', 'c_custkey')} AS node_id, c_acctbal AS x FROM customer UNION ALL SELECT {k_sql('supplier', 's_suppkey')}, s_acctbal FROM supplier)", "m AS (SELECT dst, round(avg(x), 9) AS m FROM a JOIN x ON src = node_id GROUP BY dst)"], "SELECT node_id, (m > (SELECT quantile_cont(m, 0.5) FROM m))::INT AS y FROM n LEFT JOIN m ON dst = node_id"))
def label_planted(spark, d):
    g = load_graph(spark, d, "cust_supp")
    return P.planted_label(g, features.balance(spark, d))


@query(sql([*graph_sql("cust_part"), f"t AS (SELECT node_id FROM n WHERE {split_sql('cust_part')} = 'train')", "b AS (SELECT greatest(1, ceil(count(*) / 64)) AS b FROM t)"], f"SELECT 0 AS epoch, floor({u_sql(7, chr(39) + 'batch' + chr(39), 0, 'node_id')} * b)::BIGINT AS batch_id, (floor({u_sql(7, chr(39) + 'batch' + chr(39), 0, 'node_id')} * b)::BIGINT % 2)::INT AS worker, node_id FROM t, b"))
def batches(spark, d):
    g = load_graph(spark, d, "cust_part")
    train = g.nodes.where(P.split_of(F.col("node_id"), "cust_part") == "train")
    return batching.make_batches(train, 64, workers=2)


@query(sql([*graph_sql("cust_part"), f"t AS (SELECT node_id FROM n WHERE {split_sql('cust_part')} = 'train')"], f"SELECT 0 AS epoch, ((row_number() OVER (ORDER BY {u_sql(7, chr(39) + 'batch' + chr(39), 0, 'node_id')}, node_id) - 1) // 64)::BIGINT AS batch_id, 0 AS worker, node_id FROM t"))
def batches_exact(spark, d):
    g = load_graph(spark, d, "cust_part")
    return batching.make_batches(g.nodes.where(P.split_of(F.col("node_id"), "cust_part") == "train"), 64, exact=True)


@query(f"SELECT event_id, round({u_sql(3, chr(39) + 'e' + chr(39), 'event_id')}, 9) AS u FROM events")
def uniform_check(spark, d):
    from ..functions.hashing import uniform
    from ..sources.tables import read

    return read(spark, d, "events", "event_id").select("event_id", F.round(uniform(3, "e", F.col("event_id")), 9).alias("u"))
