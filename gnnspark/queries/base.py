"""Registry of queries and shared pieces of oracle SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.batching import hashed_seeds
from ..operators.propagation import propagation
from ..sources.graphs import KINDS, SHIFT, load_graph

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
BATCHES, SEEDS, FANOUT, SIZE = 8, 16, 5, 32


def query(oracle: str | None = None, name: str | None = None):
    """Register a function (spark, sf_dir) under its name, with its SQL if there is any."""

    def add(f):
        key = name or f.__name__
        QUERIES[key] = f
        if oracle:
            ORACLES[key] = oracle
        return f

    return add


def r6(c) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6)


def sql(ctes: list[str], select: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(ctes) + "\n" + select


def u_sql(*keys) -> str:
    return f"((('0x' || substr(md5(concat_ws(':', {', '.join(map(str, keys))})), 1, 8))::BIGINT + 0.5) / 4294967296.0)"


def tid(text: str) -> str:
    return f"(-(('0x' || substr(md5({text}), 1, 15))::BIGINT) - 1)"


def k_sql(kind: str, col: str) -> str:
    return f"({col} + {KINDS[kind] * SHIFT})"


_TOKENS = "t AS MATERIALIZED (SELECT DISTINCT doc_id, unnest(string_split(lower(coalesce(text, '')), ' ')) AS token FROM documents), tf AS (SELECT token, count(*) AS df FROM t WHERE token <> '' GROUP BY token)"


def graph_sql(name: str) -> list[str]:
    """CTEs n(node_id) and a(dst, src), the adjacency with undirected edges both ways."""
    undirected = lambda pairs: [f"e AS MATERIALIZED (SELECT DISTINCT x, y FROM ({pairs}) WHERE x <> y)", "a AS MATERIALIZED (SELECT x AS dst, y AS src FROM e UNION SELECT y, x FROM e)"]
    directed = lambda pairs: [f"e AS MATERIALIZED (SELECT DISTINCT x, y FROM ({pairs}) WHERE x <> y)", "a AS MATERIALIZED (SELECT y AS dst, x AS src FROM e)"]
    nodes = lambda *parts: "n AS MATERIALIZED (" + " UNION ALL ".join(parts) + ")"
    c, p, s, doc = (f"SELECT {k_sql(k, col)} AS node_id FROM {t}" for k, col, t in (("customer", "c_custkey", "customer"), ("part", "p_partkey", "part"), ("supplier", "s_suppkey", "supplier"), ("document", "doc_id", "documents")))
    join = "FROM orders JOIN lineitem ON o_orderkey = l_orderkey"
    if name == "cust_part":
        return [nodes(c, p), *undirected(f"SELECT {k_sql('customer', 'o_custkey')} AS x, {k_sql('part', 'l_partkey')} AS y {join}")]
    if name == "cust_supp":
        return [nodes(c, s), *undirected(f"SELECT {k_sql('customer', 'o_custkey')} AS x, {k_sql('supplier', 'l_suppkey')} AS y {join}")]
    if name == "part_pair":
        return [nodes(p), *undirected(f"SELECT {k_sql('part', 'l.l_partkey')} AS x, {k_sql('part', 'r.l_partkey')} AS y FROM lineitem l JOIN lineitem r ON l.l_orderkey = r.l_orderkey AND l.l_partkey < r.l_partkey")]
    if name == "docs_lex":
        return [nodes(doc), _TOKENS, "rare AS (SELECT doc_id, token FROM t JOIN tf USING (token) WHERE df BETWEEN 2 AND 20)", *undirected(f"SELECT {k_sql('document', 'l.doc_id')} AS x, {k_sql('document', 'r.doc_id')} AS y FROM rare l JOIN rare r ON l.token = r.token AND l.doc_id < r.doc_id")]
    if name == "docs_tok":
        return [_TOKENS, "held AS (SELECT doc_id, token FROM t JOIN tf USING (token) WHERE df >= 2)", nodes(doc, f"SELECT {tid('token')} FROM (SELECT DISTINCT token FROM held)"), *undirected(f"SELECT {k_sql('document', 'doc_id')} AS x, {tid('token')} AS y FROM held")]
    if name == "emb_knn":
        return [nodes("SELECT vec_id AS node_id FROM embeddings"), *directed("SELECT x, y FROM (SELECT l.vec_id AS x, r.vec_id AS y, row_number() OVER (PARTITION BY l.vec_id ORDER BY list_cosine_similarity(l.embedding::DOUBLE[], r.embedding::DOUBLE[]) DESC, r.vec_id) AS k FROM embeddings l JOIN embeddings r ON l.vec_id <> r.vec_id) WHERE k <= 10")]
    if name == "user_hops":
        return [nodes("SELECT DISTINCT user_id AS node_id FROM events"), *directed("SELECT user_id AS x, lead(user_id) OVER (ORDER BY ts, event_id) AS y FROM events")]
    if name == "page_links":
        links = "l AS MATERIALIZED (SELECT DISTINCT page_id, unnest(list_append(list_transform(regexp_extract_all(coalesce(html, ''), 'href=\"([^\"]*)\"', 1), lambda h: 'p:' || h), 'h:' || regexp_extract(coalesce(url, ''), '//([^/]*)/', 1))) AS target FROM pages)"
        return [links, nodes(f"SELECT {k_sql('page', 'page_id')} AS node_id FROM pages", f"SELECT {tid('target')} FROM (SELECT DISTINCT target FROM l)"), *directed(f"SELECT {k_sql('page', 'page_id')} AS x, {tid('target')} AS y FROM l")]
    if name == "turns":
        t = lambda alias: k_sql("turn", f"({alias}.conv_id * 65536 + {alias}.turn)")
        return [nodes(f"SELECT {t('c')} AS node_id FROM conversations c"), *directed(f"SELECT {t('c')} AS x, {t('d')} AS y FROM conversations c JOIN conversations d ON c.conv_id = d.conv_id AND d.turn = c.turn + 1")]
    nation, region = k_sql("nation", "n_nationkey"), k_sql("region", "r_regionkey")
    pairs = f"SELECT {k_sql('customer', 'c_custkey')} AS x, {k_sql('nation', 'c_nationkey')} AS y FROM customer UNION SELECT {k_sql('supplier', 's_suppkey')}, {k_sql('nation', 's_nationkey')} FROM supplier UNION SELECT {nation}, {k_sql('region', 'n_regionkey')} FROM nation"
    return [nodes(c, s, f"SELECT {nation} FROM nation", f"SELECT {region} FROM region"), *undirected(pairs)]


PROP_SQL = {
    "base": "ah AS MATERIALIZED (SELECT dst AS row, src AS col FROM a UNION ALL SELECT node_id, node_id FROM n), dh AS (SELECT row AS v, count(*) AS d FROM ah GROUP BY row)",
    "sym": "p AS MATERIALIZED (SELECT row, col, 1.0::DOUBLE / sqrt(r.d::DOUBLE * c.d) AS w FROM ah JOIN dh r ON row = r.v JOIN dh c ON col = c.v)",
    "row": "p AS MATERIALIZED (SELECT row, col, 1.0::DOUBLE / r.d AS w FROM ah JOIN dh r ON row = r.v)",
    "self_loop": "p AS (SELECT row, col, 1.0::DOUBLE AS w FROM ah)",
}


def prop_sql(name: str, operator: str = "sym") -> list[str]:
    return [*graph_sql(name), PROP_SQL["base"], PROP_SQL[operator]]


def seeds_sql(batches: int = BATCHES, size: int = SEEDS, seed: int = 7, where: str = "true") -> str:
    u = u_sql(seed, "'seed'", "b", "node_id")
    return f"s AS MATERIALIZED (SELECT b AS batch_id, node_id FROM (SELECT b, node_id, row_number() OVER (PARTITION BY b ORDER BY {u}, node_id) AS r FROM n, (SELECT unnest(range({batches})) AS b) WHERE {where}) WHERE r <= {size})"


def split_sql(name: str, seed: int = 7) -> str:
    from ..operators.propagation import SPLITS

    t, v = SPLITS.get(name, (54, 18))
    b = f"floor(100 * {u_sql(seed, chr(39) + 'split' + chr(39), 'node_id')})"
    return f"CASE WHEN {b} < {t} THEN 'train' WHEN {b} < {t + v} THEN 'val' ELSE 'test' END"


class Setup:
    """A graph with its operator and the seeds of the standard experiment."""

    def __init__(self, spark: SparkSession, d: str, name: str, batches: int = BATCHES, size: int = SEEDS):
        self.g = load_graph(spark, d, name)
        self.prop = propagation(self.g)
        self.seeds = hashed_seeds(self.g.nodes, batches, size)
