"""Operators around the methods, one query each."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.hashing import dot, norm, race_key, uniform
from ..operators import cache as C
from ..operators import draws, layerwise, nodewise
from ..operators import metrics as M
from ..operators import relational as R
from ..operators.propagation import degrees, propagation
from ..sources.graphs import load_graph
from ..sources.tables import read
from .base import BATCHES, Setup, graph_sql, prop_sql, query, r6, seeds_sql, sql, u_sql
from .caching import DEG, ONE_PERCENT, degree_sql, draw_sql, one_percent
from .sampling import SIZE, _prefix_sql, colp_sql, ns_sql


@query("SELECT o_orderkey, o_custkey FROM orders WHERE o_totalprice > 100000 AND o_orderstatus = 'F'")
def proj_filter(spark, d):
    return read(spark, d, "orders").where("o_totalprice > 100000 and o_orderstatus = 'F'").select("o_orderkey", "o_custkey")


_JOIN = "SELECT n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"
for _name, _hint in (("join_broadcast", "broadcast"), ("join_merge", "merge"), ("join_shuffle_hash", "shuffle_hash")):

    @query(_JOIN, _name)
    def _join(spark, d, hint=_hint):
        n = read(spark, d, "nation", "n_nationkey", "n_name").hint(hint)
        return read(spark, d, "customer", "c_nationkey").join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


@query(sql([*prop_sql("cust_supp"), colp_sql(2), _prefix_sql()], f"SELECT t, node_id FROM (SELECT t, {u_sql(7, 0, 3, 0, 't')} AS u FROM (SELECT unnest(range({SIZE}))::INT AS t)) JOIN ps ON low <= u AND u < high"))
def join_range_draw(spark, d):
    probs = layerwise.column_probs(propagation(load_graph(spark, d, "cust_supp")))
    return draws.iid(probs, spark.range(1).select(F.lit(3).alias("batch_id")), SIZE, 0).select("t", "node_id")


_CS = [*graph_sql("cust_supp"), DEG, degree_sql(), draw_sql("ch", ONE_PERCENT)]


def _cached(spark, d):
    g = load_graph(spark, d, "cust_supp")
    return g, C.build_cache(C.cache_probs_degree(g), one_percent(g))


@query(sql(_CS, "SELECT src, dst FROM a WHERE src IN (SELECT node_id FROM ch)"))
def semi_cached(spark, d):
    g, cache = _cached(spark, d)
    return g.edges.select("src", "dst").join(cache.select(F.col("node_id").alias("src")), "src", "left_semi")


@query(sql(_CS, "SELECT count(*) AS n FROM n WHERE node_id NOT IN (SELECT node_id FROM ch)"))
def anti_missing(spark, d):
    g, cache = _cached(spark, d)
    return g.nodes.join(cache, "node_id", "left_anti").agg(F.count("*").alias("n"))


@query(sql(graph_sql("docs_lex"), "SELECT node_id FROM n WHERE node_id NOT IN (SELECT dst FROM a)"))
def outer_isolated(spark, d):
    return degrees(load_graph(spark, d, "docs_lex")).where("deg = 0").select("node_id")


_ASOF = "SELECT e.event_id, (SELECT count(*) FROM events v WHERE v.user_id = e.user_id AND v.event_type = 'purchase' AND v.ts <= e.ts) AS version FROM events e"


@query("WITH v AS (SELECT user_id, ts, row_number() OVER (PARTITION BY user_id ORDER BY ts) AS version FROM events WHERE event_type = 'purchase') SELECT e.event_id, v.version FROM events e ASOF LEFT JOIN v ON e.user_id = v.user_id AND e.ts >= v.ts")
def asof_model_version(spark, d):
    """The version in force at each event; a purchase makes a new version."""
    e = read(spark, d, "events", "event_id", "ts", "user_id", "event_type")
    v = e.where("event_type = 'purchase'").withColumn("version", F.row_number().over(Window.partitionBy("user_id").orderBy("ts")).cast("long"))
    return R.asof_join(e.select("event_id", "user_id", "ts"), v.select("user_id", "ts", "version"), "user_id", "ts", "ts", "version").select("event_id", "version")


_SPANS = {"a": "(SELECT id, s, s + 5 * (x + 1000) / 11000 AS e FROM (SELECT c_custkey AS id, c_acctbal::DOUBLE AS x, c_custkey + c_acctbal::DOUBLE / 10000 AS s FROM customer))", "b": "(SELECT id, s, s + x / 10 AS e FROM (SELECT p_partkey AS id, p_size::DOUBLE AS x, p_partkey + p_size::DOUBLE / 50 AS s FROM part))"}


@query(f"SELECT a.id AS a_id, b.id AS b_id, round(least(a.e, b.e) - greatest(a.s, b.s), 6) AS overlap FROM {_SPANS['a']} a JOIN {_SPANS['b']} b ON a.s < b.e AND b.s < a.e")
def interval_overlap(spark, d):
    """Spans on the line of keys: customers begin and last by their balance, parts by their size."""

    def side(table, key, value, begin, length):
        s = read(spark, d, table, key, value).select(F.col(key).alias("id"), F.col(value).cast("double").alias("x"))
        return s.withColumn("start", F.col("id") + begin(F.col("x"))).select("id", "start", (F.col("start") + length(F.col("x"))).alias("end"))

    a = side("customer", "c_custkey", "c_acctbal", lambda x: x / 10000, lambda x: 5 * (x + 1000) / 11000)
    return R.interval_overlaps(a, side("part", "p_partkey", "p_size", lambda x: x / 50, lambda x: x / 10), 5.0).withColumn("overlap", r6("overlap"))


@query(sql(graph_sql("turns"), "SELECT x.src AS a, x.dst AS b, y.dst AS c FROM a x JOIN a y ON x.dst = y.src"))
def two_hop_paths(spark, d):
    e = load_graph(spark, d, "turns").edges
    return e.alias("x").join(e.alias("y"), F.col("x.dst") == F.col("y.src")).select(F.col("x.src").alias("a"), F.col("x.dst").alias("b"), F.col("y.dst").alias("c"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_discount), 6) AS disc FROM lineitem GROUP BY ALL")
def agg_basic(spark, d):
    x = read(spark, d, "lineitem", "l_returnflag", "l_linestatus", "l_quantity", "l_discount")
    return x.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), r6(F.avg("l_discount")).alias("disc"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, 1 AS near FROM lineitem GROUP BY ALL")
def agg_distinct(spark, d):
    x = read(spark, d, "lineitem", "l_returnflag", "l_partkey")
    near = F.abs(F.approx_count_distinct("l_partkey", 0.02) - F.countDistinct("l_partkey")) <= 0.1 * F.countDistinct("l_partkey")
    return x.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), near.cast("int").alias("near"))


@query("SELECT o_orderstatus, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS top, min_by(o_orderkey, (o_totalprice, o_orderkey)) AS low, round(quantile_cont(o_totalprice, 0.5), 4) AS mid, round(var_samp(o_totalprice) / 1e6, 4) AS var, round(corr(o_totalprice, o_custkey), 6) AS r FROM orders GROUP BY ALL")
def agg_stats(spark, d):
    o, t = F.col("o_orderkey"), F.col("o_totalprice")
    by = F.struct(t, o)
    return read(spark, d, "orders").groupBy("o_orderstatus").agg(F.max_by(o, by).alias("top"), F.min_by(o, by).alias("low"), F.round(F.percentile(t, F.lit(0.5)), 4).alias("mid"), F.round(F.var_samp(t) / 1e6, 4).alias("var"), r6(F.corr(t, "o_custkey")).alias("r"))


_WINDOW = "(PARTITION BY c_nationkey ORDER BY c_custkey)"


@query(f"SELECT c_custkey, row_number() OVER {_WINDOW} AS rn, rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS rk, dense_rank() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS dr, ntile(4) OVER {_WINDOW} AS nt, round(percent_rank() OVER {_WINDOW}, 6) AS pr FROM customer")
def win_rank(spark, d):
    w, s = Window.partitionBy("c_nationkey").orderBy("c_custkey"), Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
    return read(spark, d, "customer").select("c_custkey", F.row_number().over(w).alias("rn"), F.rank().over(s).alias("rk"), F.dense_rank().over(s).alias("dr"), F.ntile(4).over(w).alias("nt"), r6(F.percent_rank().over(w)).alias("pr"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    every = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(every).alias("second"))


@query("SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS s3, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS day FROM events")
def win_frames(spark, d):
    e = read(spark, d, "events").withColumn("sec", F.unix_micros(F.col("ts").cast("timestamp")) / 1e6)
    rows = Window.partitionBy("user_id").orderBy("ts").rowsBetween(-2, 0)
    day = Window.partitionBy("user_id").orderBy("sec").rangeBetween(-86400, 0)
    return e.select("event_id", F.round(F.sum("value").over(rows), 4).alias("s3"), F.count("*").over(day).alias("day"))


@query("SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50")
def topk_global(spark, d):
    return read(spark, d, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(50).select("o_orderkey")


@query("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def topk_group(spark, d):
    return R.salted_top_k(read(spark, d, "orders", "o_custkey", "o_orderkey", "o_totalprice"), "o_custkey", [F.col("o_totalprice").desc(), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey")


@query("WITH a AS (SELECT c_nationkey AS k FROM customer), b AS (SELECT s_nationkey AS k FROM supplier) SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b) UNION ALL SELECT 'except_all', count(*) FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b) UNION ALL SELECT 'intersect_all', count(*) FROM (SELECT * FROM a INTERSECT ALL SELECT * FROM b)")
def set_ops(spark, d):
    a, b = read(spark, d, "customer").select(F.col("c_nationkey").alias("k")), read(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))
    ops, out = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except": a.subtract(b), "except_all": a.exceptAll(b), "intersect_all": a.intersectAll(b)}, None
    for k, df in ops.items():
        one = df.agg(F.count("*").alias("n")).select(F.lit(k).alias("op"), "n")
        out = one if out is None else out.union(one)
    return out


@query("SELECT token, count(DISTINCT doc_id) AS df FROM (SELECT doc_id, unnest(string_split(lower(coalesce(text, '')), ' ')) AS token FROM documents) WHERE token <> '' GROUP BY token HAVING count(DISTINCT doc_id) >= 2")
def str_tokens(spark, d):
    from ..sources.graphs import token_frequency, tokens

    return token_frequency(tokens(read(spark, d, "documents", "doc_id", "text")), 2)


@query("SELECT page_id, regexp_extract(url, '//([^/]*)/', 1) AS host, length(url) AS n FROM pages")
def url_host(spark, d):
    return read(spark, d, "pages", "page_id", "url").select("page_id", F.regexp_extract("url", "//([^/]*)/", 1).alias("host"), F.length("url").cast("long").alias("n"))


@query("SELECT date_trunc('hour', ts)::TIMESTAMP AS hour, count(*) AS n, min(epoch_us(ts)) AS first_us, max(date_diff('day', DATE '2020-01-01', ts::DATE)) AS day FROM events GROUP BY ALL")
def date_buckets(spark, d):
    e = read(spark, d, "events", "ts")
    return e.groupBy(F.date_trunc("hour", "ts").alias("hour")).agg(F.count("*").alias("n"), F.min(F.unix_micros(F.col("ts").cast("timestamp"))).alias("first_us"), F.max(F.datediff(F.to_date("ts"), F.lit("2020-01-01").cast("date"))).cast("long").alias("day"))


@query(f"SELECT p_partkey, round(-ln({u_sql(7, 'p_partkey')}) / p_size, 6) AS race, ceil(sqrt(p_size))::BIGINT AS root, round(pow(p_size, 1.5), 4) AS pw, round(exp(-p_size / 50.0), 6) AS ex FROM part")
def math_race(spark, d):
    p = read(spark, d, "part", "p_partkey", "p_size")
    return p.select("p_partkey", r6(race_key(uniform(7, F.col("p_partkey")), F.col("p_size"))).alias("race"), F.ceil(F.sqrt("p_size")).cast("long").alias("root"), F.round(F.pow("p_size", F.lit(1.5)), 4).alias("pw"), r6(F.exp(-F.col("p_size") / 50.0)).alias("ex"))


@query("SELECT a.vec_id AS a, round(list_inner_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS x FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def arr_dot(spark, d):
    v = read(spark, d, "embeddings", "vec_id", "embedding")
    a, b = v.alias("a"), v.alias("b")
    return a.join(b, F.col("b.vec_id") == F.col("a.vec_id") + 1).select(F.col("a.vec_id").alias("a"), r6(dot(F.col("a.embedding"), F.col("b.embedding"))).alias("x"))


@query("SELECT vec_id, round(sqrt(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 6) AS x, round(list_max(embedding::DOUBLE[]), 5) AS top FROM embeddings")
def arr_norm(spark, d):
    return read(spark, d, "embeddings").select("vec_id", r6(norm(F.col("embedding"))).alias("x"), F.round(F.array_max(F.col("embedding").cast("array<double>")), 5).alias("top"))


@query(sql([*graph_sql("cust_part"), seeds_sql(), ns_sql("b1", "s", 1)], "SELECT batch_id, dst, src, src % 7 AS f FROM b1"))
def map_pack(spark, d):
    """Batches packed into one row with arrays of structs and a map of features, and unpacked again."""
    x = Setup(spark, d, "cust_part")
    b = nodewise.sample_neighbors(x.seeds, x.g.edges, 5, 1)
    packed = b.groupBy("batch_id").agg(F.collect_list(F.struct("dst", "src")).alias("blocks"), F.map_from_entries(F.collect_set(F.struct(F.col("src").alias("k"), (F.col("src") % 7).alias("v")))).alias("x"))
    return packed.select("batch_id", F.explode("blocks").alias("e"), "x").select("batch_id", "e.dst", "e.src", F.element_at("x", F.col("e.src")).alias("f"))


@query("SELECT event_type, sum(CAST(props ->> '$.k' AS BIGINT))::BIGINT AS k, count(*) AS n FROM events GROUP BY event_type")
def json_props(spark, d):
    e = read(spark, d, "events", "event_type", "props")
    return e.withColumn("j", F.from_json("props", "k bigint")).groupBy("event_type").agg(F.sum("j.k").alias("k"), F.count("*").alias("n"))


@query(f"SELECT o_orderkey FROM orders WHERE {u_sql(11, 'o_orderkey')} < 0.05")
def hash_sample(spark, d):
    return read(spark, d, "orders", "o_orderkey").where(uniform(11, F.col("o_orderkey")) < 0.05)


@query(sql([*graph_sql("geo_tree"), "sd AS (SELECT min(node_id) AS node_id FROM n)", "rc AS (SELECT node_id, 0 AS hops FROM sd UNION SELECT src, hops + 1 FROM rc JOIN a ON dst = node_id WHERE hops < 4)"], "SELECT node_id, min(hops)::INT AS hops FROM rc GROUP BY node_id"))
def reach_geo_tree(spark, d):
    g = load_graph(spark, d, "geo_tree")
    return R.reachable(g.edges, g.nodes.agg(F.min("node_id").alias("node_id")), 4)


@query("SELECT label, i - 1 AS pos, round(avg(v), 5) AS x FROM (SELECT label, generate_subscripts(embedding, 1) AS i, unnest(embedding)::DOUBLE AS v FROM embeddings) GROUP BY label, i")
def udaf_vec_mean(spark, d):
    m = R.vector_mean(read(spark, d, "embeddings"), "label", "embedding")
    return m.select("label", F.posexplode("mean").alias("pos", "x")).select("label", F.col("pos").cast("long").alias("pos"), F.round("x", 5).alias("x"))


@query("SELECT * FROM (VALUES (0, 7.0::DOUBLE), (1, 12.0), (2, 17.0), (3, 22.0), (4, 27.0), (5, 36.0), (6, 41.0), (7, 46.0)) v(k, finish)")
def udtf_schedule(spark, d):
    """The bounded schedule as a table function, on the worked example with two slots."""
    from pyspark.sql.functions import udtf

    from .running import F4_COMPUTE, F4_PREP

    @udtf(returnType="k int, finish double")
    class Bounded:
        def eval(self, prep: list, compute: float, slots: int):
            start, ready, done = [], 0.0, 0.0
            for k, p in enumerate(prep):
                ready = max(ready, start[k - slots] if k >= slots else 0.0) + p
                start.append(max(ready, done))
                done = start[k] + compute
                yield k, float(done)

    return Bounded(F.array(*[F.lit(float(x)) for x in F4_PREP]), F.lit(float(F4_COMPUTE)), F.lit(2))


_NORM = "SELECT vec_id, round(sqrt(list_inner_product(embedding::DOUBLE[], embedding::DOUBLE[])), 5) AS x FROM embeddings"


@query(_NORM)
def udf_scalar_norm(spark, d):
    """A pandas function of a column: what :func:`arr_norm` does without Python."""
    return read(spark, d, "embeddings", "vec_id", "embedding").select("vec_id", F.round(R.pandas_norm("embedding"), 5).alias("x"))


@query("SELECT c_nationkey AS nation, round(sum(c_acctbal), 2) AS customers, (SELECT round(sum(s_acctbal), 2) FROM supplier WHERE s_nationkey = c_nationkey) AS suppliers FROM customer GROUP BY c_nationkey")
def udf_cogroup_totals(spark, d):
    """Cogrouped: the balances of a nation's customers beside those of its suppliers; both sides are summed by cells before they meet."""
    cell = F.pmod(F.xxhash64("id"), F.lit(8))
    summed = lambda df: df.groupBy("nation", cell.alias("cell")).agg(F.sum("x").alias("x"))
    c = read(spark, d, "customer", "c_custkey", "c_nationkey", "c_acctbal").toDF("id", "nation", "x")
    s = read(spark, d, "supplier", "s_suppkey", "s_nationkey", "s_acctbal").toDF("id", "nation", "x")
    told = R.cogrouped_totals(summed(c), summed(s), "nation")
    return told.where("customers is not null").select("nation", F.round("customers", 2).alias("customers"), F.round("suppliers", 2).alias("suppliers"))


@query("SELECT n_regionkey AS region, round(quantile_cont(c_acctbal, 0.5), 4) AS median FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_regionkey")
def udaf_pandas_median(spark, d):
    """A pandas aggregate: exact medians of bounded groups of distinct values."""
    n = read(spark, d, "nation", "n_nationkey", "n_regionkey")
    c = read(spark, d, "customer", "c_nationkey", "c_acctbal").join(n, F.col("c_nationkey") == F.col("n_nationkey"))
    counted = c.groupBy("n_regionkey", "c_acctbal").agg(F.count("*").alias("times"))
    return counted.groupBy(F.col("n_regionkey").alias("region")).agg(F.round(R.pandas_median("c_acctbal", "times"), 4).alias("median"))


@query(f"SELECT p_partkey, round(-ln({u_sql(7, 'p_partkey')}) / p_size, 6) AS race FROM part")
def sql_function_race(spark, d):
    """The race key as a function of SQL, in a query over a view."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gs_race(u DOUBLE, p DOUBLE) RETURNS DOUBLE RETURN -ln(u) / p")
    read(spark, d, "part", "p_partkey", "p_size").select("p_partkey", "p_size", uniform(7, F.col("p_partkey")).alias("u")).createOrReplaceTempView("gs_parts")
    return spark.sql("SELECT p_partkey, round(gs_race(u, CAST(p_size AS DOUBLE)), 6) AS race FROM gs_parts")


def _link_sql() -> str:
    score = "list_inner_product(x.embedding::DOUBLE[], y.embedding::DOUBLE[])"
    pos = "SELECT DISTINCT least(src, dst) AS src, greatest(src, dst) AS dst FROM a"
    neg = f"SELECT src, (src + 1 + floor({u_sql(7, chr(39) + 'neg' + chr(39), 'src', 'dst')} * (SELECT count(*) - 1 FROM n))::BIGINT) % (SELECT count(*) FROM n) AS dst FROM ({pos})"
    both = f"SELECT 1 AS y, src, dst FROM ({pos}) UNION ALL SELECT 0, src, dst FROM ({neg}) WHERE (src, dst) NOT IN (SELECT (src, dst) FROM a) AND (dst, src) NOT IN (SELECT (src, dst) FROM a)"
    return sql([*graph_sql("emb_knn"), f"pr AS MATERIALIZED (SELECT l.y, round({score}, 6) AS score FROM ({both}) l JOIN embeddings x ON x.vec_id = src JOIN embeddings y ON y.vec_id = dst)"], "SELECT round(avg(CASE WHEN p.score > q.score THEN 1.0 WHEN p.score = q.score THEN 0.5 ELSE 0.0 END), 6)::DOUBLE AS auc FROM pr p JOIN pr q ON p.y = 1 AND q.y = 0")


@query(_link_sql())
def linkpred_auc(spark, d):
    """Link prediction: linked pairs, each once whatever its direction, against hashed pairs without a link, scored by dot products."""
    g = load_graph(spark, d, "emb_knn")
    n = g.nodes.count()
    pos = g.edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).distinct()
    other = (F.col("src") + 1 + F.floor(uniform(7, "neg", F.col("src"), F.col("dst")) * (n - 1))) % n
    neg = pos.select("src", other.alias("dst"))
    e = g.edges.select("src", "dst")
    neg = neg.join(e, ["src", "dst"], "left_anti").join(e.select(F.col("dst").alias("src"), F.col("src").alias("dst")), ["src", "dst"], "left_anti")
    v = read(spark, d, "embeddings", "vec_id", "embedding")
    both = pos.select(F.lit(1).alias("y"), "src", "dst").union(neg.select(F.lit(0), "src", "dst"))
    scored = both.join(v.select(F.col("vec_id").alias("src"), F.col("embedding").alias("a")), "src").join(v.select(F.col("vec_id").alias("dst"), F.col("embedding").alias("b")), "dst")
    return M.roc_auc(scored.select("y", r6(dot(F.col("a"), F.col("b"))).alias("score"))).select(r6("auc").alias("auc"))
