"""Relational operators around the methods, each once on the given tables, with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def _read(s: SparkSession, d: str, name: str) -> DataFrame:
    return s.read.parquet(f"{d}/{name}.parquet")


def in_sql(text: str, *tables: str):
    """A query whose text both engines read alike; tables stand in braces."""
    return (lambda s, d: s.sql(text, **{t: _read(s, d, t) for t in tables})), text.format(**{t: t for t in tables})


def _asof(s: SparkSession, d: str) -> DataFrame:
    """The last purchase of a user at or before each error, by one sort over the union of both sides."""
    e = _read(s, d, "events").where("event_type IN ('purchase', 'error')")
    order = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "error", "event_id")
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(order.rowsBetween(Window.unboundedPreceding, 0))
    return e.withColumn("purchase_id", last).where("event_type = 'error'").select("event_id", "purchase_id")


def _band(s: SparkSession, d: str) -> DataFrame:
    """Orders within three days after an order of the same customer: a range join by buckets of the range."""
    o = _read(s, d, "orders").select("o_custkey", "o_orderkey", F.datediff("o_orderdate", F.lit("1990-01-01")).alias("day"))
    left = o.select("o_custkey", F.col("o_orderkey").alias("first_key"), F.col("day").alias("first_day"), F.explode(F.array(F.floor(F.col("day") / 3), F.floor(F.col("day") / 3) + 1)).alias("slot"))
    right = o.select("o_custkey", "o_orderkey", "day", F.floor(F.col("day") / 3).alias("slot"))
    near = left.join(right, ["o_custkey", "slot"]).where("o_orderkey <> first_key AND day >= first_day AND day <= first_day + 3")
    return near.select("first_key", "o_orderkey")


def _pivot(s: SparkSession, d: str) -> DataFrame:
    return _read(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).na.fill(0)


def _topk(s: SparkSession, d: str) -> DataFrame:
    order = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return _read(s, d, "customer").withColumn("r", F.row_number().over(order)).where("r <= 3").select("c_nationkey", "c_custkey", "r")


def _salted(s: SparkSession, d: str) -> DataFrame:
    """Counts by a skewed key in two steps: a salted partial count, then the sum of the few partial rows."""
    e = _read(s, d, "events").withColumn("salt", F.pmod("event_id", F.lit(16)))
    return e.groupBy("event_type", "salt").agg(F.count("*").alias("n")).groupBy("event_type").agg(F.sum("n").alias("n"))


def _broadcast(s: SparkSession, d: str) -> DataFrame:
    """Nations have 25 rows by the schema's nature, so they may be broadcast."""
    return _read(s, d, "customer").join(F.broadcast(_read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))


def _approx(s: SparkSession, d: str) -> DataFrame:
    return _read(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"), F.percentile_approx("value", 0.5).alias("median"))


_COUNT = "CAST(count(*) AS BIGINT) AS n"
QUERIES = {
    "op_asof": (_asof, "SELECT e.event_id, (SELECT p.event_id FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts ORDER BY p.ts DESC, p.event_id DESC LIMIT 1) AS purchase_id FROM events e WHERE e.event_type = 'error'"),
    "op_band": (_band, "SELECT a.o_orderkey AS first_key, b.o_orderkey FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey <> b.o_orderkey AND CAST(b.o_orderdate AS DATE) BETWEEN CAST(a.o_orderdate AS DATE) AND CAST(a.o_orderdate AS DATE) + 3"),
    "op_pivot": (_pivot, "SELECT o_orderpriority, " + ", ".join(f"count(*) FILTER (o_orderstatus = '{x}') AS \"{x}\"" for x in "FOP") + " FROM orders GROUP BY 1"),
    "op_topk": (_topk, "SELECT c_nationkey, c_custkey, r FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3"),
    "op_salted": (_salted, "SELECT event_type, CAST(count(*) AS BIGINT) AS n FROM events GROUP BY 1"),
    "op_join_broadcast": (_broadcast, f"SELECT n_name, {_COUNT} FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"),
    "op_approx": (_approx, None),
    "op_project": in_sql("SELECT c_custkey + 1 AS next_key, upper(c_mktsegment) AS segment, CAST(c_nationkey AS BIGINT) AS nation_key FROM {customer}", "customer"),
    "op_filter": in_sql("SELECT o_orderkey FROM {orders} WHERE o_orderstatus IN ('F', 'P') AND o_totalprice BETWEEN 1000 AND 90000 AND o_orderpriority LIKE '%-%'", "orders"),
    "op_null_safe": in_sql("SELECT c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') AS segment, CASE WHEN c_acctbal < 0 THEN 'debt' ELSE 'fine' END AS state FROM {customer}", "customer"),
    "op_join_inner": in_sql(f"SELECT c_nationkey, {_COUNT} FROM {{orders}} JOIN {{customer}} ON o_custkey = c_custkey GROUP BY c_nationkey", "orders", "customer"),
    "op_join_left": in_sql("SELECT o_orderkey, CAST(count(l_orderkey) AS BIGINT) AS n FROM {orders} LEFT JOIN {lineitem} ON o_orderkey = l_orderkey GROUP BY o_orderkey", "orders", "lineitem"),
    "op_join_full": in_sql("SELECT s_nationkey, c_nationkey FROM (SELECT DISTINCT s_nationkey FROM {supplier}) s FULL JOIN (SELECT DISTINCT c_nationkey FROM {customer}) c ON s_nationkey = c_nationkey", "supplier", "customer"),
    "op_semi": in_sql("SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderstatus = 'P')", "customer", "orders"),
    "op_anti": in_sql("SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderstatus = 'P')", "customer", "orders"),
    "op_theta": in_sql("SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM {nation} a JOIN {nation} b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey", "nation"),
    "op_cross": in_sql("SELECT r_regionkey, k FROM {region} CROSS JOIN (VALUES (0), (1), (2)) t(k)", "region"),
    "op_agg": in_sql("SELECT l_returnflag, l_linestatus, CAST(count(*) AS BIGINT) AS n, CAST(count(*) FILTER (WHERE l_quantity > 25) AS BIGINT) AS many, min(l_shipdate) AS first_ship, max(l_linenumber) AS top FROM {lineitem} GROUP BY l_returnflag, l_linestatus", "lineitem"),
    "op_distinct": in_sql("SELECT o_orderstatus, CAST(count(DISTINCT o_custkey) AS BIGINT) AS customers, CAST(count(DISTINCT o_orderpriority) AS BIGINT) AS priorities FROM {orders} GROUP BY o_orderstatus", "orders"),
    "op_cube": in_sql(f"SELECT o_orderstatus, o_orderpriority, {_COUNT} FROM {{orders}} GROUP BY CUBE (o_orderstatus, o_orderpriority)", "orders"),
    "op_rollup": in_sql(f"SELECT n_regionkey, n_nationkey, {_COUNT} FROM {{nation}} JOIN {{customer}} ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_regionkey, n_nationkey)", "nation", "customer"),
    "op_gsets": in_sql(f"SELECT source, lang, {_COUNT} FROM {{documents}} GROUP BY GROUPING SETS ((source), (lang), ())", "documents"),
    "op_unpivot": (lambda s, d: _read(s, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "name", "value"), "SELECT p_partkey, 'size' AS name, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part"),
    "op_percentile": in_sql("SELECT c_mktsegment, round(percentile_cont(0.5) WITHIN GROUP (ORDER BY c_acctbal), 6) AS median FROM {customer} GROUP BY c_mktsegment", "customer"),
    "op_collect": (lambda s, d: _read(s, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names")), "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names FROM nation GROUP BY 1"),
    "op_maxby": in_sql("SELECT o_custkey, max_by(o_orderkey, o_orderkey) AS last_key, min_by(o_orderstatus, o_orderkey) AS first_status FROM {orders} GROUP BY o_custkey", "orders"),
    "op_boolagg": in_sql("SELECT o_custkey, bool_and(o_totalprice > 10000) AS all_large, bool_or(o_orderstatus = 'P') AS any_open FROM {orders} GROUP BY o_custkey", "orders"),
    "op_rank": in_sql("SELECT s_suppkey, CAST(rank() OVER w AS BIGINT) AS r, CAST(dense_rank() OVER w AS BIGINT) AS dr, CAST(ntile(4) OVER w AS BIGINT) AS q FROM {supplier} WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_suppkey)", "supplier"),
    "op_lag": in_sql("SELECT event_id, lag(event_id) OVER w AS before_id, lead(event_id, 2) OVER w AS after_id FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)", "events"),
    "op_frames": in_sql("SELECT conv_id, turn, CAST(sum(length(text)) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS near, CAST(sum(length(text)) OVER (PARTITION BY conv_id ORDER BY turn) AS BIGINT) AS upto FROM {conversations}", "conversations"),
    "op_union": in_sql("SELECT c_nationkey AS k FROM {customer} UNION ALL SELECT s_nationkey FROM {supplier}", "customer", "supplier"),
    "op_intersect": in_sql("SELECT c_nationkey AS k FROM {customer} INTERSECT SELECT s_nationkey FROM {supplier}", "customer", "supplier"),
    "op_except": in_sql("SELECT n_nationkey AS k FROM {nation} EXCEPT SELECT s_nationkey FROM {supplier}", "nation", "supplier"),
    "op_subquery": in_sql("SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT avg(o_totalprice) FROM {orders})", "orders"),
    # A chain of line numbers, each with the items up to it; a step joins the counts, so it stays as small as they are.
    "op_recursive": in_sql(
        "WITH RECURSIVE c AS (SELECT CAST(l_linenumber AS INT) AS k, CAST(count(*) AS BIGINT) AS items FROM {lineitem} GROUP BY 1), "
        "r(n, upto) AS (SELECT k, items FROM c WHERE k = 1 UNION ALL SELECT c.k, r.upto + c.items FROM r JOIN c ON c.k = r.n + 1) SELECT n, upto FROM r",
        "lineitem",
    ),
    "op_dedup": in_sql("SELECT text, min(doc_id) AS doc_id FROM {documents} GROUP BY text", "documents"),
    "op_sort": in_sql("SELECT o_orderkey FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20", "orders"),
    "op_tumble": (
        lambda s, d: _read(s, d, "events").groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("day"), "event_type", "n"),
        "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL",
    ),
    "op_slide": (
        lambda s, d: _read(s, d, "events").groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("day"), "n"),
        "SELECT day, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS day FROM events) GROUP BY 1",
    ),
    "op_lastnn": (
        lambda s, d: _read(s, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "signup", F.col("value")), ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("last_value")),
        "SELECT event_id, last_value(CASE WHEN event_type = 'signup' THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS last_value FROM events",
    ),
    "op_lateral": in_sql("SELECT o_orderkey, x FROM {orders}, LATERAL (SELECT o_custkey + 1 AS x) l", "orders"),
    "op_stratified": (
        lambda s, d: _read(s, d, "documents").where((F.col("doc_id") * 7919) % 1009 < F.when(F.col("lang") == "en", 50).otherwise(200)).select("doc_id", "lang"),
        "SELECT doc_id, lang FROM documents WHERE (doc_id * 7919) % 1009 < CASE WHEN lang = 'en' THEN 50 ELSE 200 END",
    ),
    "op_session": (
        lambda s, d: _read(s, d, "events").groupBy(F.session_window("ts", "1 hour").alias("w"), "user_id").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest")),
        "WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 HOUR OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events), s AS (SELECT user_id, sum(new) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM g), c AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY ALL) SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1",
    ),
}
