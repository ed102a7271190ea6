"""Queries on the operators around the methods: scans, joins, windows, aggregates, text, time, arrays, maps."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import vectors
from ..metrics import consensus
from ..metrics.combined import SIGN
from ..sources import networks as net
from ..streaming import events as stream
from . import sql
from .measures import _INFO, flow2, part1, part2, table
from .network import query, rounded

T = net.table

query("scan_filter_pushdown", "SELECT c_custkey, c_nationkey FROM customer WHERE c_nationkey < 5 AND c_acctbal > 0")(lambda s, d: T(s, d, "customer").filter("c_nationkey < 5 and c_acctbal > 0").select("c_custkey", "c_nationkey"))
query("filter_events_window", "SELECT event_id, user_id FROM events WHERE ts >= TIMESTAMP '2024-01-10' AND ts < TIMESTAMP '2024-01-11' AND event_type IN ('click', 'view')")(lambda s, d: T(s, d, "events").filter("ts >= timestamp_ntz'2024-01-10' and ts < timestamp_ntz'2024-01-11' and event_type in ('click', 'view')").select("event_id", "user_id"))
query("join_broadcast", "SELECT r_name, count(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")(lambda s, d: T(s, d, "customer").join(F.broadcast(T(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(T(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("customers")))
query("join_sort_merge", "SELECT o_custkey, count(*) AS lines FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")(lambda s, d: T(s, d, "orders").hint("merge").join(T(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey").agg(F.count("*").alias("lines")))
query("join_shuffle_hash", "SELECT p_brand, count(*) AS lines FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")(lambda s, d: T(s, d, "lineitem").join(T(s, d, "part").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count("*").alias("lines")))
query("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT user_id FROM events)")(lambda s, d: T(s, d, "customer").join(T(s, d, "events"), F.col("c_custkey") == F.col("user_id"), "left_semi").select("c_custkey"))
query("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT user_id FROM events)")(lambda s, d: T(s, d, "customer").join(T(s, d, "events"), F.col("c_custkey") == F.col("user_id"), "left_anti").select("c_custkey"))
query("join_full_outer", f"WITH {sql.NET2} SELECT coalesce(a.src, b.dst) AS src, coalesce(a.dst, b.src) AS dst, a.src IS NOT NULL AS forth, b.src IS NOT NULL AS back FROM follow2 a FULL JOIN follow2 b ON a.src = b.dst AND a.dst = b.src")(lambda s, d: _both_ways(net.events_net(s, d).follow))


def _both_ways(f):
    b = f.select(F.col("dst").alias("s2"), F.col("src").alias("d2"))
    return f.join(b, (F.col("src") == F.col("s2")) & (F.col("dst") == F.col("d2")), "full").select(F.coalesce("src", "s2").alias("src"), F.coalesce("dst", "d2").alias("dst"), F.col("src").isNotNull().alias("forth"), F.col("s2").isNotNull().alias("back"))


@query("join_interval_follow", "WITH e AS (SELECT event_id, user_id, ts, CAST(regexp_extract(props, '([0-9]+)', 1) AS INTEGER) AS k FROM events) SELECT a.event_id AS later, b.event_id AS earlier FROM e a JOIN e b ON a.k = b.k AND a.user_id <> b.user_id AND b.ts < a.ts AND epoch_us(a.ts) - epoch_us(b.ts) <= 3600000000")
def join_interval_follow(spark, d):
    """Pairs of events of different users at the same k within an hour: an equi join on k and an hour bucket (the event's own
    and the one before), then the exact range."""
    e = stream.prepared(T(spark, d, "events")).select("event_id", "user_id", "k", F.unix_micros("ts").alias("at")).withColumn("hour", F.floor(F.col("at") / 3_600_000_000))
    a = e.select(F.col("event_id").alias("later"), F.col("user_id").alias("u"), "k", F.col("at").alias("t"), F.explode(F.array("hour", F.col("hour") - 1)).alias("hour"))
    b = e.select(F.col("event_id").alias("earlier"), "user_id", "k", "at", "hour")
    return a.join(b, ["k", "hour"]).filter((F.col("u") != F.col("user_id")) & (F.col("at") < F.col("t")) & (F.col("t") - F.col("at") <= 3_600_000_000)).select("later", "earlier")


@query("asof_prev_buyer", "SELECT l_partkey, o_orderkey, lag(o_orderkey) OVER (PARTITION BY l_partkey ORDER BY o_orderdate, o_orderkey) AS previous FROM (SELECT DISTINCT l_partkey, o_orderkey, o_orderdate FROM lineitem JOIN orders ON l_orderkey = o_orderkey)")
def asof_prev_buyer(spark, d):
    o = T(spark, d, "orders").select("o_orderkey", "o_orderdate")
    seen = T(spark, d, "lineitem").select("l_partkey", F.col("l_orderkey").alias("o_orderkey")).distinct().join(o, "o_orderkey")
    return seen.select("l_partkey", "o_orderkey", F.lag("o_orderkey").over(Window.partitionBy("l_partkey").orderBy("o_orderdate", "o_orderkey")).alias("previous"))


query("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(*) AS n FROM events GROUP BY 1")(lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.count("*").alias("n")))
query("agg_approx_distinct")(lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users")))
query("rollup_cluster_flow", f"WITH {sql.closeness(2, sql.UNIFORM)}, {sql.PART2} SELECT a.cluster AS c1, b.cluster AS c2, round(sum(s), 6) AS w FROM S JOIN part2 a ON a.user_id = src JOIN part2 b ON b.user_id = dst GROUP BY ROLLUP (a.cluster, b.cluster)")(lambda s, d: rounded(flow2(s, d).rollup("c1", "c2").agg(F.sum("w").alias("w")), "w"))
query("cube_report", "SELECT event_type, hour(ts) AS hour, count(*) AS n FROM events GROUP BY CUBE (event_type, hour(ts))")(lambda s, d: T(s, d, "events").withColumn("hour", F.hour("ts")).cube("event_type", "hour").agg(F.count("*").alias("n")))


@query("grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
def grouping_sets(spark, d):
    T(spark, d, "customer").createOrReplaceTempView("_customers")
    return spark.sql("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM _customers GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")


query("win_rank_share", "SELECT user_id, cluster, row_number() OVER (PARTITION BY cluster ORDER BY user_id) AS r, round(1.0 / count(*) OVER (PARTITION BY cluster), 6) AS share FROM (SELECT DISTINCT user_id, CAST(user_id % 10 AS INTEGER) AS cluster FROM events)")(lambda s, d: part2(s, d).select("user_id", "cluster", F.row_number().over(Window.partitionBy("cluster").orderBy("user_id")).alias("r"), F.round(1 / F.count("*").over(Window.partitionBy("cluster")), 6).alias("share")))
query("win_running", "SELECT o_custkey, o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 2) AS last3 FROM orders")(lambda s, d: T(s, d, "orders").select("o_custkey", "o_orderkey", F.round(F.sum("o_totalprice").over(Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(-2, 0)), 2).alias("last3")))
query("win_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type || ':' || CAST(CAST(floor(value / 10) AS BIGINT) AS VARCHAR) AS word, count(*) AS cnt FROM events GROUP BY 1, 2")(lambda s, d: _ntz(stream.tumbling(stream.prepared(T(s, d, "events")))))
query("win_sliding", "SELECT date_trunc('hour', ts) - to_hours(b) AS start, CAST(regexp_extract(props, '([0-9]+)', 1) AS INTEGER) AS k, count(*) AS cnt FROM events CROSS JOIN (VALUES (0), (1)) v(b) GROUP BY 1, 2")(lambda s, d: _ntz(stream.sliding(stream.prepared(T(s, d, "events")))))
query("win_session", "WITH g AS (SELECT user_id, ts, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts)) < 21600000000 THEN 0 ELSE 1 END AS new FROM events), n AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM g) SELECT min(ts) AS start, user_id, count(*) AS cnt FROM n GROUP BY user_id, g")(lambda s, d: _ntz(stream.sessions(stream.prepared(T(s, d, "events")))))


def _ntz(df):
    return df.withColumn("start", F.col("start").cast("timestamp_ntz"))


query("set_union_intersect", "SELECT user_id, 'both' AS side FROM (SELECT c_custkey AS user_id FROM customer INTERSECT SELECT user_id FROM events) UNION ALL SELECT user_id, 'one' FROM (SELECT c_custkey AS user_id FROM customer EXCEPT SELECT user_id FROM events)")(lambda s, d: _sets(T(s, d, "customer").select(F.col("c_custkey").alias("user_id")), T(s, d, "events").select("user_id")))


def _sets(a, b):
    return a.intersect(b).select("user_id", F.lit("both").alias("side")).union(a.subtract(b).select("user_id", F.lit("one").alias("side")))


query("tokens_doc", "SELECT doc_id, len(t) AS tokens, len(list_distinct(t)) AS kinds FROM (SELECT doc_id, regexp_extract_all(lower(text), '[\\p{L}]{3,}') AS t FROM documents)")(lambda s, d: T(s, d, "documents").select("doc_id", net.tokens(F.col("text")).alias("t")).select("doc_id", F.size("t").cast("long").alias("tokens"), F.size(F.array_distinct("t")).cast("long").alias("kinds")))
query("page_host", "SELECT regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host, count(*) AS pages FROM pages GROUP BY 1")(lambda s, d: T(s, d, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/:]+)", 1).alias("host")).agg(F.count("*").alias("pages")))
query("json_props", "SELECT CAST(regexp_extract(props, '([0-9]+)', 1) AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")(lambda s, d: T(s, d, "events").groupBy(F.from_json("props", "k int")["k"].alias("k")).agg(F.count("*").alias("n")))
query("date_buckets", "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n FROM orders GROUP BY 1")(lambda s, d: T(s, d, "orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count("*").alias("n")))
query("vec_dot", "SELECT a.vec_id, round(list_dot_product(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS dot FROM embeddings a JOIN embeddings b ON b.vec_id = 0")(lambda s, d: _dots(T(s, d, "embeddings")))


def _dots(e):
    one = e.filter("vec_id = 0").select(F.col("embedding").alias("b"))
    return e.crossJoin(F.broadcast(one)).select("vec_id", F.round(vectors.dot("embedding", "b"), 6).alias("dot"))


_SIGNED = ", ".join(f"('{m}', {float(SIGN[m])}, {m})" for m in ("mi", "nmi", "vi"))


@query("map_signs", f"{_INFO}, v AS (SELECT mi, mi / sqrt(h1 * h2) AS nmi, h1 + h2 - 2 * mi AS vi FROM i) SELECT t.measure, t.sign, round(t.sign * t.value, 6) AS signed FROM v, LATERAL (VALUES {_SIGNED}) t(measure, sign, value)")
def map_signs(spark, d):
    """The consensus measures of the reference partitions as a map, and each with its sign from another map."""
    values = consensus.information(table(spark, d)).select(F.create_map(*[x for m in ("mi", "nmi", "vi") for x in (F.lit(m), F.col(m))]).alias("m"))
    signs = F.map_from_entries(F.array(*[F.struct(F.lit(m), F.lit(float(x))) for m, x in SIGN.items()]))
    got = values.select(F.explode("m").alias("measure", "value")).withColumn("sign", F.element_at(signs, F.col("measure")))
    return got.select("measure", "sign", F.round(F.col("sign") * F.col("value"), 6).alias("signed"))


query("safe_math", "SELECT c_custkey, CASE WHEN c_acctbal > 0 THEN round(log2(c_acctbal), 6) END AS bits, round(c_acctbal / nullif(c_nationkey, 0), 6) AS ratio FROM customer")(lambda s, d: T(s, d, "customer").select("c_custkey", F.when(F.col("c_acctbal") > 0, F.round(F.log2("c_acctbal"), 6)).alias("bits"), F.round(F.try_divide("c_acctbal", "c_nationkey"), 6).alias("ratio")))


@query("sql_surface", f"WITH {sql.NET2} SELECT kind, count(*) AS posts FROM posts2 JOIN attr2 USING (post_id) GROUP BY 1")
def sql_surface(spark, d):
    net.aligned_tables(spark, d).views()
    return spark.sql("SELECT kind, count(*) AS posts FROM posts_1 JOIN attributes_1 USING (post_id) GROUP BY 1")


query("reference_partition", "SELECT cluster, count(*) AS users FROM (SELECT c_nationkey % 10 AS cluster FROM customer) GROUP BY 1")(lambda s, d: part1(s, d).groupBy("cluster").agg(F.count("*").alias("users")))
