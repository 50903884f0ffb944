"""Queries of the surrounding operators: sources, joins, aggregates, windows, sets, scalars, streams, functions."""

from __future__ import annotations

import math

from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.ml.stat import Summarizer
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import udfs
from ..functions import vectors as V
from ..operators import cluster, graph, index, relational, scan
from ..session import cut, fresh_path
from ..sources import files
from ..sources import workloads as W
from ..sources.graph_source import GraphSource
from ..sources.tables import table
from ..streaming import features as S
from . import oracle as O
from .method_queries import EMB, SPEC, emb_sigs
from .registry import query

R6 = "round({}, 6) + 0.0"

# --- scans, sources, sinks ---


@query("scan_parquet", "SELECT p_partkey, p_brand FROM part WHERE p_size > 40")
def scan_parquet(spark, sf_dir):
    return table(spark, sf_dir, "part").filter("p_size > 40").select("p_partkey", "p_brand")


_EDGES = O.with_(O.PART_PAIRS) + " SELECT src, dst FROM pe WHERE support >= 2"


def _edges_as(fmt):
    return lambda spark, sf_dir: files.roundtrip(W.part_edges(spark, sf_dir, 2).select("src", "dst"), fmt)


for _fmt in ("csv", "json", "orc", "parquet"):
    query(f"edges_{_fmt}_roundtrip", _EDGES)(_edges_as(_fmt))


@query("graph_source", "SELECT a.conv_id * 100000 + a.turn AS src, b.conv_id * 100000 + b.turn AS dst FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
def graph_source(spark, sf_dir):
    spark.dataSource.register(GraphSource)
    return spark.read.format("lookalike_graph").option("sf_dir", sf_dir).load()


@query("edges_conversation", "SELECT a.conv_id * 100000 + a.turn AS src, b.conv_id * 100000 + b.turn AS dst FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
def edges_conversation(spark, sf_dir):
    return W.conv_graph(spark, sf_dir).edges


@query("sql_view", "SELECT label, count(*) AS n FROM embeddings GROUP BY label")
def sql_view(spark, sf_dir):
    W.emb_nodes(spark, sf_dir).withColumnRenamed("verdict", "label").createOrReplaceTempView("lookalike_nodes")
    return spark.sql("SELECT label, count(*) AS n FROM lookalike_nodes GROUP BY label")


@query("partitioned_roundtrip", "SELECT label AS verdict, count(*) AS n FROM embeddings WHERE label <> 3 GROUP BY label")
def partitioned_roundtrip(spark, sf_dir):
    sigs = W.emb_nodes(spark, sf_dir).withColumnRenamed("x", "sig")
    return scan.load_by_verdict(spark, scan.store_by_verdict(sigs)).filter("verdict <> 3").groupBy("verdict").agg(F.count("*").alias("n"))


@query("bucketed_join", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1")
def bucketed_join(spark, sf_dir):
    a = files.bucketed(table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority"), "lookalike_orders", "o_orderkey")
    b = files.bucketed(table(spark, sf_dir, "lineitem").select("l_orderkey"), "lookalike_lines", "l_orderkey")
    return a.join(b.hint("merge"), a.o_orderkey == b.l_orderkey).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


# --- projections and filters ---


@query("features_part", O.with_(O.part_fixture(1)) + " SELECT id AS node_id, (i - 1)::INT AS dim, round(x[i], 6) + 0.0 AS value FROM x0, range(1, 28) t(i)")
def features_part(spark, sf_dir):
    return V.long_form(graph.assert_dim(W.part_nodes(spark, sf_dir), 27), "node_id", "x")


@query("features_customer", O.with_(O.CUST_FIXTURE) + " SELECT id AS node_id, (i - 1)::INT AS dim, round(round(x[i], 9), 4) + 0.0 AS value FROM x0, range(1, 18) t(i)")
def features_customer(spark, sf_dir):
    x = W.cust_nodes(spark, sf_dir).select("node_id", F.posexplode("x").alias("dim", "value"))
    return x.select("node_id", F.col("dim").cast("int").alias("dim"), V.r6(F.round("value", 9), 4).alias("value"))


@query("feature_values", O.with_(O.CUST_BASE, O.CUST_VALUES) + " SELECT id AS node_id, feature, value FROM fv")
def feature_values(spark, sf_dir):
    return W.cust_values(spark, sf_dir)


@query("filter_verdict", "SELECT vec_id AS node_id, label AS verdict FROM embeddings WHERE label IS DISTINCT FROM 4")
def filter_verdict(spark, sf_dir):
    return W.emb_nodes(spark, sf_dir).filter(~F.col("verdict").eqNullSafe(F.lit(4))).select("node_id", "verdict")


@query("split_assign", "SELECT p_partkey AS node_id, CASE WHEN p_partkey % 10 < 6 THEN 'train' WHEN p_partkey % 10 < 8 THEN 'valid' ELSE 'test' END AS split FROM part")
def split_assign(spark, sf_dir):
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("node_id"), W.split_of(F.col("p_partkey")).alias("split"))


@query("predicates", """SELECT c_custkey, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal BETWEEN 0 AND 5000 THEN 'low' ELSE 'high' END AS band FROM customer
 WHERE c_mktsegment IN (SELECT DISTINCT c_mktsegment FROM customer WHERE c_mktsegment LIKE '%U%') AND c_name IS NOT NULL""")
def predicates(spark, sf_dir):
    c = table(spark, sf_dir, "customer").filter(F.col("c_mktsegment").like("%U%") & F.col("c_name").isNotNull())
    return c.select("c_custkey", F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal").between(0, 5000), "low").otherwise("high").alias("band"))


# --- joins ---


@query("join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def join_broadcast(spark, sf_dir):
    c, n, r = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey).groupBy("r_name").agg(F.count("*").alias("n"))


_LO = "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY 1"


def _join_with(hint):
    def run(spark, sf_dir):
        o, l = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")  # noqa: E741
        return o.join(l.hint(hint), o.o_orderkey == l.l_orderkey).groupBy("o_orderstatus").agg(F.count("*").alias("n"))

    return run


query("join_merge", _LO)(_join_with("merge"))
query("join_shuffle_hash", _LO)(_join_with("shuffle_hash"))


@query("join_salted", _LO)
def join_salted(spark, sf_dir):
    o = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), "o_orderstatus")
    l = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber")  # noqa: E741
    return relational.salted_join(l, o, "k", 4, "l_linenumber").groupBy("o_orderstatus").agg(F.count("*").alias("n"))


@query("join_theta", "SELECT a.label AS la, b.label AS lb, count(*) AS n FROM embeddings a JOIN embeddings b ON a.label < b.label GROUP BY ALL")
def join_theta(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("label")
    return e.alias("a").join(e.alias("b"), F.col("a.label") < F.col("b.label")).groupBy(F.col("a.label").alias("la"), F.col("b.label").alias("lb")).agg(F.count("*").alias("n"))


@query("join_semi", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 400000)")
def join_semi(spark, sf_dir):
    c, o = table(spark, sf_dir, "customer"), table(spark, sf_dir, "orders").filter("o_totalprice > 400000")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


@query("join_anti", "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 45)")
def join_anti(spark, sf_dir):
    p, l = table(spark, sf_dir, "part"), table(spark, sf_dir, "lineitem").filter("l_quantity > 45")  # noqa: E741
    return p.join(l, p.p_partkey == l.l_partkey, "left_anti").select("p_partkey")


@query("join_outer", O.with_(O.PART_PAIRS) + ", d AS (SELECT n, count(*) AS c FROM (SELECT src AS n FROM pe WHERE support >= 2 UNION ALL SELECT dst FROM pe WHERE support >= 2) GROUP BY n) SELECT p_partkey AS node_id, coalesce(c, 0) AS degree FROM part LEFT JOIN d ON n = p_partkey")
def join_outer(spark, sf_dir):
    d = graph.degree(W.part_edges(spark, sf_dir, 2))
    return table(spark, sf_dir, "part").select(F.col("p_partkey").alias("node_id")).join(d, "node_id", "left").select("node_id", F.coalesce("degree", F.lit(0)).alias("degree"))


@query("join_full_outer", "SELECT coalesce(a.vec_id, b.doc_id) AS id, coalesce(a.label, -1) AS label, coalesce(b.quality, -1) AS quality FROM embeddings a FULL JOIN labels b ON a.vec_id = b.doc_id")
def join_full_outer(spark, sf_dir):
    a, b = table(spark, sf_dir, "embeddings"), table(spark, sf_dir, "labels")
    return a.join(b, a.vec_id == b.doc_id, "full").select(F.coalesce("vec_id", "doc_id").alias("id"), F.coalesce("label", F.lit(-1)).alias("label"), F.coalesce("quality", F.lit(-1)).alias("quality"))


@query("join_range", "SELECT a.p_partkey AS a, b.p_partkey AS b FROM part a JOIN part b ON a.p_brand < b.p_brand AND abs(a.p_retailprice - b.p_retailprice) <= 0.05")
def join_range(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    a = p.select(F.col("p_partkey").alias("a"), F.col("p_brand").alias("brand_a"), F.col("p_retailprice").alias("price_a"))
    b = p.select(F.col("p_partkey").alias("b"), F.col("p_brand").alias("brand_b"), F.col("p_retailprice").alias("price_b"))
    return relational.band_join(a, b, "price_a", "price_b", 0.05).filter("brand_a < brand_b").select("a", "b")


_SPANS = "SELECT event_id AS span_id, user_id AS span_user, ts AS s, ts + INTERVAL 10 MINUTE AS e FROM events WHERE event_type = (SELECT min(event_type) FROM events)"


@query("join_interval", f"SELECT span_id, event_id FROM events JOIN ({_SPANS}) ON ts >= s AND ts <= e AND user_id <> span_user")
def join_interval(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    first = e.agg(F.min("event_type").alias("t"))
    spans = e.join(F.broadcast(first), e.event_type == first.t).select(F.col("event_id").alias("span_id"), F.col("user_id").alias("span_user"), F.col("ts").alias("s"), (F.col("ts") + F.expr("interval 10 minutes")).alias("e"))
    return relational.interval_join(e, spans, "ts", "s", "e", 600, F.col("user_id") != F.col("span_user")).select("span_id", "event_id")


@query("join_asof", "WITH a AS (SELECT * FROM events WHERE event_id % 2 = 0), b AS (SELECT * FROM events WHERE event_id % 2 = 1) SELECT event_id, (SELECT event_type FROM b WHERE b.user_id = a.user_id AND b.ts <= a.ts ORDER BY b.ts DESC, b.event_id DESC LIMIT 1) AS verdict FROM a")
def join_asof(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    left = e.filter("event_id % 2 = 0").select("event_id", "user_id", "ts")
    right = e.filter("event_id % 2 = 1").select("event_id", "user_id", "ts", F.col("event_type").alias("verdict"))
    return relational.asof_join(left, right, "user_id", "ts", "verdict", "event_id").select("event_id", "verdict")


@query("lateral_explode", "SELECT vec_id, (i - 1)::INT AS dim, round(embedding[i]::DOUBLE, 6) + 0.0 AS value FROM embeddings, range(1, 65) t(i)")
def lateral_explode(spark, sf_dir):
    return V.long_form(table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e")), "vec_id", "e")


@query("lateral_top_orders", "SELECT c_custkey, o_orderkey FROM (SELECT o_custkey AS c_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def lateral_top_orders(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return o.withColumn("r", F.row_number().over(w)).filter("r <= 2").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey")


# --- aggregates ---


@query("vector_mean_by_label", "SELECT label, (i - 1)::INT AS dim, round(avg(embedding[i]::DOUBLE), 6) + 0.0 AS value FROM embeddings, range(1, 65) t(i) GROUP BY label, i")
def vector_mean_by_label(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings")
    m = e.groupBy("label").agg(vector_to_array(Summarizer.mean(array_to_vector(F.col("embedding").cast("array<double>")))).alias("m"))
    return V.long_form(m, "label", "m")


@query("agg_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"))


@query("agg_approx_distinct")
def agg_approx_distinct(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


_CG = "SELECT r_name, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY {}"


def _cube(kind):
    def run(spark, sf_dir):
        b = W.cust_base(spark, sf_dir).select("r_name", "c_mktsegment")
        if kind == "sets":
            g = b.groupingSets([[F.col("r_name")], [F.col("c_mktsegment")]], "r_name", "c_mktsegment")
        else:
            g = getattr(b, kind)("r_name", "c_mktsegment")
        return g.agg(F.count("*").alias("n"))

    return run


query("agg_cube", _CG.format("CUBE (r_name, c_mktsegment)"))(_cube("cube"))
query("agg_rollup", _CG.format("ROLLUP (r_name, c_mktsegment)"))(_cube("rollup"))
query("agg_grouping_sets", _CG.format("GROUPING SETS ((r_name), (c_mktsegment))"))(_cube("sets"))


@query("agg_argmax", "SELECT p_brand, arg_max(p_partkey, {'price': p_retailprice, 'k': p_partkey}) AS top_part FROM part GROUP BY p_brand")
def agg_argmax(spark, sf_dir):
    return table(spark, sf_dir, "part").groupBy("p_brand").agg(F.max_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("top_part"))


@query("agg_quantiles", "SELECT l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 6) + 0.0 AS median, round(quantile_cont(l_extendedprice, 0.9), 6) + 0.0 AS p90 FROM lineitem GROUP BY 1")
def agg_quantiles(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(V.r6(F.percentile("l_extendedprice", 0.5)).alias("median"), V.r6(F.percentile("l_extendedprice", 0.9)).alias("p90"))


@query("agg_histogram", "SELECT floor(sim * 20)::INT AS bin, count(*) AS n FROM (" + O.with_(EMB, O.local(1)) + " SELECT round(sim, 6) AS sim FROM lt) GROUP BY 1")
def agg_histogram(spark, sf_dir):
    twins = scan.exact_scan_all(emb_sigs(spark, sf_dir), 1)
    return twins.groupBy(F.floor(F.col("sim") * 20).cast("int").alias("bin")).agg(F.count("*").alias("n"))


@query("agg_pivot", "SELECT n_regionkey, count(*) FILTER (c_acctbal < 0) AS debt, count(*) FILTER (c_acctbal >= 0) AS credit FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def agg_pivot(spark, sf_dir):
    c, n = table(spark, sf_dir, "customer"), table(spark, sf_dir, "nation")
    side = F.when(F.col("c_acctbal") < 0, "debt").otherwise("credit")
    p = c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).withColumn("side", side).groupBy("n_regionkey").pivot("side", ["debt", "credit"]).agg(F.count("c_custkey"))
    return p.na.fill(0, ["debt", "credit"])


@query("bucket_arrays", O.with_(EMB, O.local(10)) + " SELECT v, string_agg(u || ':' || rank, ',' ORDER BY rank) AS bucket FROM lt GROUP BY v")
def bucket_arrays(spark, sf_dir):
    twins = scan.exact_scan_all(emb_sigs(spark, sf_dir), 10)
    packed = twins.groupBy("v").agg(F.array_sort(F.collect_list(F.struct("rank", "u"))).alias("b"))
    return packed.select("v", F.array_join(F.transform("b", lambda x: F.concat_ws(":", x["u"], x["rank"])), ",").alias("bucket"))


# --- windows ---


@query("window_topk", "SELECT o_custkey, o_orderkey, r::INT AS r, dr::INT AS dr FROM (SELECT o_custkey, o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS dr FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)) WHERE r <= 3")
def window_topk(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    o = table(spark, sf_dir, "orders")
    return o.select("o_custkey", "o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr")).filter("r <= 3")


@query("window_lag", "SELECT event_id, coalesce(epoch_us(ts) - epoch_us(lag(ts) OVER w), -1) AS gap_us, lead(event_type) OVER w AS next_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def window_lag(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return table(spark, sf_dir, "events").select("event_id", F.coalesce(us - F.lag(us).over(w), F.lit(-1)).alias("gap_us"), F.lead("event_type").over(w).alias("next_type"))


@query("window_ntile", "SELECT c_custkey, ntile(4) OVER w AS quarter, round(percent_rank() OVER w, 6) + 0.0 AS pr FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey)")
def window_ntile(spark, sf_dir):
    w = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey")
    return table(spark, sf_dir, "customer").select("c_custkey", F.ntile(4).over(w).cast("long").alias("quarter"), V.r6(F.percent_rank().over(w)).alias("pr"))


@query("window_range_frame", "SELECT p_partkey, count(*) OVER (PARTITION BY p_brand ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND CURRENT ROW) AS near FROM part")
def window_range_frame(spark, sf_dir):
    w = Window.partitionBy("p_brand").orderBy("p_size").rangeBetween(-5, 0)
    return table(spark, sf_dir, "part").select("p_partkey", F.count("*").over(w).alias("near"))


# --- sorts and sets ---


@query("topk_pairs", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_pairs(spark, sf_dir):
    return table(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("sort_full", "SELECT o_orderkey, o_custkey FROM orders")
def sort_full(spark, sf_dir):
    return table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").repartitionByRange("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")


_SETS = "SELECT l_suppkey AS k FROM lineitem WHERE l_quantity > 49 {} SELECT l_suppkey FROM lineitem WHERE l_quantity < 2"


def _sides(spark, sf_dir):
    l = table(spark, sf_dir, "lineitem")  # noqa: E741
    return l.filter("l_quantity > 49").select(F.col("l_suppkey").alias("k")), l.filter("l_quantity < 2").select(F.col("l_suppkey").alias("k"))


def _set(op):
    def run(spark, sf_dir):
        a, b = _sides(spark, sf_dir)
        return op(a, b)

    return run


query("set_union", _SETS.format("UNION"))(_set(lambda a, b: a.union(b).distinct()))
query("set_union_all", _SETS.format("UNION ALL"))(_set(lambda a, b: a.union(b)))
query("set_intersect", _SETS.format("INTERSECT"))(_set(lambda a, b: a.intersect(b)))
query("set_except", _SETS.format("EXCEPT"))(_set(lambda a, b: a.subtract(b)))
query("set_except_all", _SETS.format("EXCEPT ALL"))(_set(lambda a, b: a.exceptAll(b)))
query("set_intersect_all", _SETS.format("INTERSECT ALL"))(_set(lambda a, b: a.intersectAll(b)))

# --- scalars ---


@query("array_math", "SELECT vec_id, round(list_dot_product(e, e), 6) + 0.0 AS dot, round(sqrt(list_dot_product(e, e)), 6) + 0.0 AS norm, round(list_sum(list_transform(e, lambda v: v * 2)), 6) + 0.0 AS twice FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings)")
def array_math(spark, sf_dir):
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    total = F.aggregate(V.scale("e", F.lit(2.0)), F.lit(0.0), lambda s, v: s + v)
    return e.select("vec_id", V.r6(V.dot("e", "e")).alias("dot"), V.r6(V.norm("e")).alias("norm"), V.r6(total).alias("twice"))


@query("math_fns", "SELECT p_partkey, round(acos(p_size / 50.0), 6) + 0.0 AS angle, round(sqrt(p_retailprice), 6) + 0.0 AS root, greatest(p_size, 25) AS hi, least(p_size, 25) AS lo FROM part")
def math_fns(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    return p.select("p_partkey", V.r6(F.acos(F.col("p_size") / 50.0)).alias("angle"), V.r6(F.sqrt("p_retailprice")).alias("root"), F.greatest("p_size", F.lit(25)).alias("hi"), F.least("p_size", F.lit(25)).alias("lo"))


@query("string_fns", "SELECT doc_id, length(text) AS n, upper(left(coalesce(source, ''), 3)) AS s3, md5(text) AS h, len(string_split(text, ' '))::INT AS words FROM documents")
def string_fns(spark, sf_dir):
    d = table(spark, sf_dir, "documents")
    return d.select("doc_id", F.char_length("text").cast("long").alias("n"), F.upper(F.left(F.coalesce("source", F.lit("")), F.lit(3))).alias("s3"), F.md5("text").alias("h"), F.size(F.split("text", " ")).alias("words"))


@query("date_fns", "SELECT o_orderkey, year(o_orderdate)::INT AS y, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS m, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INT AS days FROM orders")
def date_fns(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("m"), F.datediff(F.col("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"))


@query("json_props", "SELECT event_id, (props ->> '$.k')::INT AS k FROM events")
def json_props(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


@query("json_typed", "SELECT event_id, (props ->> '$.k')::INT AS k FROM events")
def json_typed(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.from_json("props", "k INT")["k"].alias("k"))


@query("json_variant", "SELECT event_id, (props ->> '$.k')::INT AS k FROM events")
def json_variant(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "int").alias("k"))


@query("map_values", O.with_(O.CUST_BASE, O.CUST_VALUES) + " SELECT id AS node_id, max(CASE WHEN feature = 'region' THEN value END) AS region, count(*)::INT AS n FROM fv GROUP BY id")
def map_values(spark, sf_dir):
    v = W.cust_values(spark, sf_dir).groupBy("node_id").agg(F.map_from_entries(F.collect_list(F.struct("feature", "value"))).alias("m"))
    return v.select("node_id", F.col("m")["region"].alias("region"), F.size("m").alias("n"))


@query("page_lang", "SELECT page_id, regexp_extract(html, '<html lang=\"([a-z]+)\"', 1) AS lang FROM pages")
def page_lang(spark, sf_dir):
    return W.page_langs(spark, sf_dir)


@query("page_links", "SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS target FROM pages")
def page_links(spark, sf_dir):
    return W.page_links(spark, sf_dir)


@query("edges_page", """WITH l AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS t FROM pages)
SELECT a.page_id AS src, b.page_id AS dst, count(*) AS support FROM l a JOIN l b ON a.t = b.t AND a.page_id < b.page_id GROUP BY ALL""")
def edges_page(spark, sf_dir):
    """Every shared target counts, however many pages link to it."""
    return graph.co_occurrence(W.page_links(spark, sf_dir), "target", "page_id", block=1024)


@query("edges_document", "SELECT a.doc_id AS src, b.doc_id AS dst FROM documents a JOIN documents b ON a.source = b.source AND a.lang = b.lang AND a.doc_id < b.doc_id")
def edges_document(spark, sf_dir):
    return graph.shared_key(table(spark, sf_dir, "documents"), "doc_id", ["source", "lang"])


@query("edges_customer", O.with_(O.CUST_FIXTURE) + " SELECT src, dst FROM ed WHERE src < dst")
def edges_customer(spark, sf_dir):
    return W.cust_edges(spark, sf_dir)


@query("edges_embedding", O.with_(O.emb_nodes(), O.emb_edges(0.2)) + " SELECT src, dst FROM ed WHERE src < dst")
def edges_embedding(spark, sf_dir):
    return W.emb_graph(spark, sf_dir).edges


_TERMS = r"SELECT doc_id, unnest(regexp_extract_all(lower(text), '[a-zà-ÿ]+')) AS w FROM documents"


@query("tfidf_terms", f"WITH t AS ({_TERMS}), tf AS (SELECT doc_id, w, count(*) AS n FROM t GROUP BY ALL), df AS (SELECT w, count(*) AS d FROM tf GROUP BY w) SELECT doc_id, w, round(n * ln((1.0 + (SELECT count(*) FROM documents)) / (1 + d)), 6) + 0.0 AS tfidf FROM tf JOIN df USING (w)")
def tfidf_terms(spark, sf_dir):
    """The weight of every term of every document, rare terms too."""
    return _tfidf(spark, sf_dir).drop("d")


def _tfidf(spark, sf_dir):
    """``doc_id, w, d, tfidf``: every term of every document, and how many documents have it."""
    d = table(spark, sf_dir, "documents")
    texts = d.select("doc_id", "text").repartition("doc_id")  # the text is shuffled once, and its terms are counted where it lies
    words = texts.select("doc_id", F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-zà-ÿ]+"), 0)).alias("w"))
    tf = words.groupBy("doc_id", "w").agg(F.count("*").alias("n"))
    df = tf.groupBy("w").agg(F.count("*").alias("d"))
    n = d.agg(F.count("*").alias("docs"))
    return tf.join(df, "w").crossJoin(F.broadcast(n)).select("doc_id", "w", "d", V.r6(F.col("n") * F.log((1.0 + F.col("docs")) / (1 + F.col("d")))).alias("tfidf"))


@query("hashed_tfidf")
def hashed_tfidf(spark, sf_dir):
    from pyspark.ml.feature import IDF, HashingTF

    d = table(spark, sf_dir, "documents").select("doc_id", F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+").alias("words"))
    tf = HashingTF(inputCol="words", outputCol="tf", numFeatures=256).transform(d)
    return IDF(inputCol="tf", outputCol="v").fit(tf).transform(tf).select("doc_id", vector_to_array("v").alias("x"))


_WORDS = r"[^ \t\n\x0B\f\r]+"


@query("keyword_presence", f"SELECT DISTINCT doc_id, unnest(regexp_extract_all(lower(text), '{_WORDS}')) AS word, 1 AS present FROM documents")
def keyword_presence(spark, sf_dir):
    """The binary presence vector of each document over the whole vocabulary, as its non-zero entries."""
    d = table(spark, sf_dir, "documents")
    words = F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(_WORDS), 0))
    per_row = d.select("doc_id", F.explode(words).alias("word"))
    return per_row.distinct().select("doc_id", "word", F.lit(1).alias("present"))


@query("near_copy_classes", "SELECT doc_id, min(doc_id) OVER (PARTITION BY text) AS class_id FROM documents WHERE text IS NOT NULL")
def near_copy_classes(spark, sf_dir):
    """Which document stands for each text in ``near_copy_edges``: the copy with the smallest id."""
    d = table(spark, sf_dir, "documents").filter("text is not null").select("doc_id", F.sha2("text", 256).alias("h"))
    return d.join(d.groupBy("h").agg(F.min("doc_id").alias("class_id")), "h").select("doc_id", "class_id")


@query("near_copy_edges")
def near_copy_edges(spark, sf_dir):
    """Documents whose whole word sets have a Jaccard distance below 0.2, exactly; copies of a text stand for one, which ``near_copy_classes`` names."""
    d = table(spark, sf_dir, "documents").filter("text is not null").groupBy("text").agg(F.min("doc_id").alias("doc_id"))
    words = d.select("doc_id", F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "").alias("w"))
    return graph.alike_sets(words, "doc_id", "w", (4, 5))


@query("user_features", "SELECT user_id AS node_id, event_type, count(*) AS n FROM events GROUP BY ALL")
def user_features(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("node_id"), "event_type").agg(F.count("*").alias("n"))


@query("user_labels", "SELECT user_id AS node_id, event_type AS label FROM (SELECT user_id, event_type, row_number() OVER (PARTITION BY user_id ORDER BY n DESC, event_type) AS r FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL)) WHERE r = 1")
def user_labels(spark, sf_dir):
    types = W.sorted_values(table(spark, sf_dir, "events"), "event_type")
    return W.user_nodes(spark, sf_dir).select("node_id", F.element_at(F.array(*[F.lit(t) for t in types]), F.col("label") + 1).alias("label"))


# --- streams ---

_FMT = "strftime({}, '%Y-%m-%d %H:%M:%S')"


def _text(df, *cols):
    for c in cols:
        df = df.withColumn(c, F.date_format(c, "yyyy-MM-dd HH:mm:ss"))
    return df


@query("stream_tumbling", f"SELECT {_FMT.format(chr(39) + '1970-01-01' + chr(39) + '::TIMESTAMP + INTERVAL 1 HOUR * h')} AS start, event_type, count(*) AS n, round(avg(value), 6) + 0.0 AS mean FROM (SELECT *, floor(epoch_us(ts) / 3600000000)::BIGINT AS h FROM events) GROUP BY h, event_type")
def stream_tumbling(spark, sf_dir):
    return _text(S.drain(S.tumbling(S.read_events(spark, sf_dir)), "complete"), "start").withColumn("mean", V.r6("mean"))


@query("stream_sliding", f"SELECT {_FMT.format(chr(39) + '1970-01-01' + chr(39) + '::TIMESTAMP + INTERVAL 1 HOUR * (h - o)')} AS start, event_type, count(*) AS n FROM (SELECT *, floor(epoch_us(ts) / 3600000000)::BIGINT AS h FROM events), (SELECT unnest([0, 1]) AS o) GROUP BY h - o, event_type")
def stream_sliding(spark, sf_dir):
    return _text(S.drain(S.sliding(S.read_events(spark, sf_dir)), "complete"), "start")


@query(
    "stream_session",
    f"""WITH a AS (SELECT user_id, ts, event_id, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER w) < 21600000000 THEN 0 ELSE 1 END AS f FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
b AS (SELECT user_id, ts, sum(f) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS g FROM a)
SELECT {_FMT.format("min(ts)")} AS start, {_FMT.format("max(ts) + INTERVAL 6 HOUR")} AS "end", user_id, count(*) AS n FROM b GROUP BY user_id, g""",
)
def stream_session(spark, sf_dir):
    return _text(S.drain(S.sessions(S.read_events(spark, sf_dir)), "complete"), "start", "end")


@query("stream_dedupe", "SELECT DISTINCT event_id, user_id FROM events")
def stream_dedupe(spark, sf_dir):
    return S.drain(S.deduped(S.read_events(spark, sf_dir))).select("event_id", "user_id")


@query("stream_alert")
def stream_alert(spark, sf_dir):
    return S.drain(S.verdict_changes(S.read_events(spark, sf_dir)))


@query("stream_join", "SELECT a.event_id AS a_id, b.event_id AS b_id, a.event_type FROM events a JOIN events b ON a.event_type = b.event_type AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE AND a.user_id < b.user_id")
def stream_join(spark, sf_dir):
    return S.drain(S.twin_feed(S.read_events(spark, sf_dir)))


@query("stream_static_join", "SELECT event_type, c_mktsegment, count(*) AS n FROM events JOIN customer ON c_custkey = user_id GROUP BY ALL")
def stream_static_join(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return S.drain(S.read_events(spark, sf_dir).join(c, "user_id").groupBy("event_type", "c_mktsegment").agg(F.count("*").alias("n")), "complete")


@query("stream_assign", O.with_(EMB, O.layers(3, 10, 3, 64)) + " SELECT id AS node_id, layer, c AS cluster FROM home")
def stream_assign(spark, sf_dir):
    """Signatures arrive as a stream and find their homes under layers fitted before."""
    sigs = emb_sigs(spark, sf_dir).select("node_id", "verdict", "sig")
    path = fresh_path(spark, "arrivals")
    sigs.write.parquet(path)
    layers = cluster.build_layers(sigs, SPEC)
    arrivals = spark.readStream.schema(sigs.schema).option("maxFilesPerTrigger", 2).parquet(path)
    return S.upkeep(arrivals, layers, fresh_path(spark, "upkeep-index")).select("node_id", "layer", "cluster")


# --- functions for SQL ---


@query("udf_sim", "SELECT a.vec_id AS a, b.vec_id AS b, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) + 0.0 AS sim FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1")
def udf_sim(spark, sf_dir):
    udfs.register(spark)
    W.emb_nodes(spark, sf_dir).createOrReplaceTempView("lookalike_vectors")
    return spark.sql("SELECT a.node_id AS a, b.node_id AS b, round(twin_sim(a.x, b.x), 6) + 0.0D AS sim FROM lookalike_vectors a JOIN lookalike_vectors b ON b.node_id = a.node_id + 1")


@query("udf_boundary_weight", O.with_(O.cap_table(8)) + f", c AS (SELECT p_partkey, p_size / 50.0 AS cos FROM part) SELECT p_partkey, round({O.weight_of('cos')}, 6) + 0.0 AS weight FROM c, tab")
def udf_boundary_weight(spark, sf_dir):
    udfs.register(spark)
    table(spark, sf_dir, "part").createOrReplaceTempView("lookalike_part")
    return spark.sql(f"SELECT p_partkey, round(twin_weight(CAST(p_size / 50.0D AS DOUBLE), {math.pi / 3}D, 8D), 6) + 0.0D AS weight FROM lookalike_part")


@query("udaf_vec_avg", "SELECT label, (i - 1)::INT AS dim, round(avg(embedding[i]::DOUBLE), 6) + 0.0 AS value FROM embeddings, range(1, 65) t(i) GROUP BY label, i")
def udaf_vec_avg(spark, sf_dir):
    udfs.register(spark)
    W.emb_nodes(spark, sf_dir).createOrReplaceTempView("lookalike_vectors")
    return V.long_form(spark.sql("SELECT verdict AS label, vec_avg(x) AS m FROM lookalike_vectors GROUP BY verdict"), "label", "m")


@query("udtf_explode", "SELECT vec_id AS node_id, (i - 1)::INT AS dim, round(embedding[i]::DOUBLE, 6) + 0.0 AS value FROM embeddings, range(1, 65) t(i)")
def udtf_explode(spark, sf_dir):
    udfs.register(spark)
    W.emb_nodes(spark, sf_dir).createOrReplaceTempView("lookalike_vectors")
    return spark.sql("SELECT node_id, t.dim, round(t.value, 6) + 0.0D AS value FROM lookalike_vectors, LATERAL explode_vector(x) t")


@query("udtf_topk", O.with_(EMB, O.local(5)) + " SELECT v, u, rank, round(sim, 6) + 0.0 AS sim FROM lt")
def udtf_topk(spark, sf_dir):
    udfs.register(spark)
    cut(emb_sigs(spark, sf_dir), "sigs").createOrReplaceTempView("lookalike_sigs")
    scored = "SELECT a.node_id AS v, b.node_id AS u, round(aggregate(zip_with(a.sig, b.sig, (x, y) -> x * y), 0.0D, (s, t) -> s + t), 9) AS sim FROM lookalike_sigs a JOIN lookalike_sigs b ON a.verdict <> b.verdict"
    return spark.sql(f"SELECT v, u, rank, round(sim, 6) + 0.0D AS sim FROM top_twins(TABLE({scored}) PARTITION BY (v), 5)")


@query("block_scan", O.with_(EMB, O.local(10)) + " SELECT v, u, rank, round(sim, 6) + 0.0 AS sim FROM lt")
def block_scan(spark, sf_dir):
    """The blocked kernel with blocks so small that every node's list is merged from many."""
    from ..operators.kernels import blocked_topk

    sigs = cut(emb_sigs(spark, sf_dir), "sigs").select(F.lit(0).alias("cell"), "node_id", "verdict", "sig")
    return scan.merge_topk(blocked_topk(sigs, sigs, 10, block=100), 10)


@query("index_drift")
def index_drift(spark, sf_dir):
    """Mean home weight of fitted nodes against arrivals (here the same nodes)."""
    ix = index.build(emb_sigs(spark, sf_dir), SPEC)
    return S.drift(ix.nodes, ix.nodes)
