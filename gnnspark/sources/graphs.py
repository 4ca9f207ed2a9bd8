"""Ten graphs derived from the given tables, as node and edge tables.

Edges are ordered pairs (src sends, dst receives); an undirected graph is stored both ways. Every builder is a plan of scans, equi-joins and
distinct aggregates; none ranks nodes globally. Ids of tables are shifted by a kind code, ids of texts are hashes.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.hashing import text_id
from .knn import nearest
from .spool import spool
from .tables import read

SHIFT = 2**40
KINDS = {"customer": 1, "supplier": 2, "part": 3, "nation": 4, "region": 5, "document": 6, "page": 8, "turn": 10}
NAMES = ("cust_part", "cust_supp", "part_pair", "docs_lex", "docs_tok", "emb_knn", "user_hops", "page_links", "turns", "geo_tree")


@dataclass
class Graph:
    """nodes(node_id, kind), edges(src, dst, weight, ts)."""

    name: str
    nodes: DataFrame
    edges: DataFrame
    directed: bool

    def counted(self) -> DataFrame:
        """Edges with each undirected edge once."""
        return self.edges if self.directed else self.edges.where("src < dst")


def key(kind: str, col) -> Column:
    return (F.col(col) if isinstance(col, str) else col).cast("long") + F.lit(KINDS[kind] * SHIFT)


def _nodes(*parts: tuple[DataFrame, Column, str]) -> DataFrame:
    out = None
    for df, node, kind in parts:
        one = df.select(node.alias("node_id"), F.lit(kind).alias("kind"))
        out = one if out is None else out.unionByName(one)
    return out


def _edges(pairs: DataFrame, directed: bool) -> DataFrame:
    """Distinct pairs without self loops, both ways if undirected: those are made distinct in one order of their ends, and doubled after it."""
    some = pairs.where("src <> dst")
    if directed:
        both = some.distinct()
    else:
        one = some.select(F.least("src", "dst").alias("x"), F.greatest("src", "dst").alias("y")).distinct()
        both = one.select(F.inline(F.array(F.struct(F.col("x").alias("src"), F.col("y").alias("dst")), F.struct(F.col("y").alias("src"), F.col("x").alias("dst")))))
    return both.select("src", "dst", F.lit(1.0).alias("weight"), F.lit(None).cast("timestamp").alias("ts"))


def tokens(docs: DataFrame) -> DataFrame:
    """(doc_id, token): distinct lower-cased tokens between spaces."""
    words = F.array_distinct(F.split(F.lower(F.coalesce("text", F.lit(""))), " "))
    return docs.select("doc_id", F.explode(words).alias("token")).where("token <> ''")


def token_frequency(pairs: DataFrame, least: int, most: int | None = None) -> DataFrame:
    df = pairs.groupBy("token").agg(F.count("*").alias("df")).where(F.col("df") >= least)
    return df if most is None else df.where(F.col("df") <= most)


def cust_part(spark: SparkSession, d: str) -> Graph:
    pairs = read(spark, d, "orders", "o_orderkey", "o_custkey").join(read(spark, d, "lineitem", "l_orderkey", "l_partkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    nodes = _nodes((read(spark, d, "customer"), key("customer", "c_custkey"), "customer"), (read(spark, d, "part"), key("part", "p_partkey"), "part"))
    return Graph("cust_part", nodes, _edges(pairs.select(key("customer", "o_custkey").alias("src"), key("part", "l_partkey").alias("dst")), False), False)


def cust_supp(spark: SparkSession, d: str) -> Graph:
    pairs = read(spark, d, "orders", "o_orderkey", "o_custkey").join(read(spark, d, "lineitem", "l_orderkey", "l_suppkey"), F.col("o_orderkey") == F.col("l_orderkey"))
    nodes = _nodes((read(spark, d, "customer"), key("customer", "c_custkey"), "customer"), (read(spark, d, "supplier"), key("supplier", "s_suppkey"), "supplier"))
    return Graph("cust_supp", nodes, _edges(pairs.select(key("customer", "o_custkey").alias("src"), key("supplier", "l_suppkey").alias("dst")), False), False)


def part_pair(spark: SparkSession, d: str) -> Graph:
    lines = read(spark, d, "lineitem", "l_orderkey", "l_partkey").distinct()
    a, b = lines.alias("a"), lines.alias("b")
    pairs = a.join(b, F.col("a.l_orderkey") == F.col("b.l_orderkey")).where("a.l_partkey < b.l_partkey")
    nodes = _nodes((read(spark, d, "part"), key("part", "p_partkey"), "part"))
    return Graph("part_pair", nodes, _edges(pairs.select(key("part", "a.l_partkey").alias("src"), key("part", "b.l_partkey").alias("dst")), False), False)


def rare_tokens(docs: DataFrame, least: int, most: int) -> DataFrame:
    """(token, docs): tokens that ``least`` to ``most`` documents hold, with these documents in order.

    Frequencies are counted first. A bit for the hash of each rare token, in words that every task gets, keeps most other tokens out of the shuffle; a join with the rare tokens drops the rest.
    """
    held, rare = tokens(docs), spool(token_frequency(tokens(docs), least, most).select("token"))
    bits = min(26, max(10, (16 * rare.count()).bit_length()))
    h = F.xxhash64("token").bitwiseAND(F.lit((1 << bits) - 1))
    word, bit = F.shiftright(h, 6).alias("word"), h.bitwiseAND(F.lit(63)).cast("int").alias("bit")
    words = rare.select(word, bit).groupBy("word").agg(F.expr("bit_or(shiftleft(1L, bit))").alias("marks"))
    likely = held.select("doc_id", "token", word, bit).join(F.broadcast(words), "word").where("(shiftright(marks, bit) & 1) = 1").select("doc_id", "token")
    return likely.join(rare, "token").groupBy("token").agg(F.sort_array(F.collect_list("doc_id")).alias("docs"))


def docs_lex(spark: SparkSession, d: str) -> Graph:
    """Documents that share a token held by 2 to 20 documents: the frequency bound keeps the pairs linear."""
    docs = read(spark, d, "documents", "doc_id", "text")
    found = rare_tokens(docs, 2, 20)
    later = lambda x, i: F.transform(F.slice("docs", i + 2, 20), lambda y: F.struct(x.alias("a"), y.alias("b")))
    pairs = found.select(F.inline(F.flatten(F.transform("docs", later)))).where("a < b")
    return Graph("docs_lex", _nodes((docs, key("document", "doc_id"), "document")), _edges(pairs.select(key("document", "a").alias("src"), key("document", "b").alias("dst")), False), False)


def docs_tok(spark: SparkSession, d: str) -> Graph:
    docs = read(spark, d, "documents", "doc_id", "text")
    held = tokens(docs)
    shared = held.join(token_frequency(held, 2), "token")
    nodes = _nodes((docs, key("document", "doc_id"), "document"), (shared.select("token").distinct(), text_id(F.col("token")), "token"))
    return Graph("docs_tok", nodes, _edges(shared.select(key("document", "doc_id").alias("src"), text_id(F.col("token")).alias("dst")), False), False)


def emb_knn(spark: SparkSession, d: str, k: int = 10) -> Graph:
    vectors = read(spark, d, "embeddings", "vec_id", "embedding")
    found = nearest(vectors, k)
    return Graph("emb_knn", _nodes((vectors, F.col("vec_id"), "vector")), _edges(found.select(F.col("vec_id").alias("src"), F.col("neighbour").alias("dst")), True), True)


def user_hops(spark: SparkSession, d: str) -> Graph:
    """User to next user in time. The next event of a day's last event is the first of the next day that has events, so no window spans all events."""
    events = read(spark, d, "events", "event_id", "ts", "user_id").withColumn("day", F.date_trunc("day", "ts"))
    inside = Window.partitionBy("day").orderBy("ts", "event_id")
    heads = events.groupBy("day").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("head"))
    heads = heads.select("day", F.lead("head").over(Window.orderBy("day")).alias("next_head"))
    led = events.withColumn("within", F.lead("user_id").over(inside)).join(heads, "day")
    hops = led.select(F.col("user_id").alias("src"), F.coalesce("within", "next_head").alias("dst"), "ts").where("dst is not null and src <> dst")
    edges = hops.groupBy("src", "dst").agg(F.count("*").cast("double").alias("weight"), F.max("ts").alias("ts"))
    return Graph("user_hops", _nodes((events.select("user_id").distinct(), F.col("user_id"), "user")), edges, True)


def page_links(spark: SparkSession, d: str) -> Graph:
    pages = read(spark, d, "pages")
    host = F.array(F.concat(F.lit("h:"), F.regexp_extract(F.coalesce("url", F.lit("")), "//([^/]*)/", 1)))
    hrefs = F.transform(F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit('href="([^"]*)"'), F.lit(1)), lambda h: F.concat(F.lit("p:"), h))
    links = pages.select(key("page", "page_id").alias("src"), F.explode(F.array_union(host, hrefs)).alias("target"))
    nodes = _nodes((pages, key("page", "page_id"), "page"), (links.select("target").distinct(), text_id(F.col("target")), "link"))
    return Graph("page_links", nodes, _edges(links.select("src", text_id(F.col("target")).alias("dst")), True), True)


def turn_id(conv: str, turn: str) -> Column:
    return key("turn", F.col(conv) * 65536 + F.col(turn))


def turns(spark: SparkSession, d: str) -> Graph:
    told = read(spark, d, "conversations", "conv_id", "turn")
    step = told.withColumn("next", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))).where("next = turn + 1")
    return Graph("turns", _nodes((told, turn_id("conv_id", "turn"), "turn")), _edges(step.select(turn_id("conv_id", "turn").alias("src"), turn_id("conv_id", "next").alias("dst")), True), True)


def geo_tree(spark: SparkSession, d: str) -> Graph:
    c, s, n, r = (read(spark, d, t) for t in ("customer", "supplier", "nation", "region"))
    pairs = c.select(key("customer", "c_custkey").alias("src"), key("nation", "c_nationkey").alias("dst")).union(s.select(key("supplier", "s_suppkey"), key("nation", "s_nationkey"))).union(n.select(key("nation", "n_nationkey"), key("region", "n_regionkey")))
    nodes = _nodes((c, key("customer", "c_custkey"), "customer"), (s, key("supplier", "s_suppkey"), "supplier"), (n, key("nation", "n_nationkey"), "nation"), (r, key("region", "r_regionkey"), "region"))
    return Graph("geo_tree", nodes, _edges(pairs, False), False)


_BUILDERS = {f.__name__: f for f in (cust_part, cust_supp, part_pair, docs_lex, docs_tok, emb_knn, user_hops, page_links, turns, geo_tree)}


def load_graph(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return _BUILDERS[name](spark, sf_dir)
