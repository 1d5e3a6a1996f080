"""The relational operators around the searches, a query for each group with its SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def _t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def as_of_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """Adds the last ``value`` of the right rows at or before the time of each left row; one shuffle by key."""
    both = left.withColumn("__v", F.lit(None).cast(right.schema[value].dataType)).withColumn("__side", F.lit(1)).unionByName(right.select(key, time, F.col(value).alias("__v")).withColumn("__side", F.lit(0)), allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(time, "__side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(value + "_asof", F.last("__v", ignorenulls=True).over(w)).filter("__side = 1").drop("__v", "__side")


def range_bucket_join(left: DataFrame, right: DataFrame, x: str, lo: str, hi: str, width: float) -> DataFrame:
    """Rows with lo <= x <= hi by an equi-join on buckets of the axis."""
    slot = lambda c: F.floor(F.col(c) / F.lit(width))
    r = right.withColumn("__slot", F.explode(F.sequence(slot(lo), slot(hi))))
    return left.withColumn("__slot", slot(x)).join(r, "__slot").filter((F.col(x) >= F.col(lo)) & (F.col(x) <= F.col(hi))).drop("__slot")


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """Equi-join with the rows of a hot key of the left side spread over ``salts`` tasks."""
    x = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    y = right.withColumn("__salt", F.explode(F.array(*[F.lit(i).cast("long") for i in range(salts)])))
    return x.join(y, [key, "__salt"]).drop("__salt")


def _scan(s: SparkSession, sf: str) -> DataFrame:
    return _t(s, sf, "lineitem").filter((F.col("l_quantity") < 5) & (F.col("l_discount") >= 0.05)).select("l_orderkey", "l_partkey", (F.col("l_partkey") % 10).alias("bucket"))


def _joins(s: SparkSession, sf: str) -> DataFrame:
    n, r = _t(s, sf, "nation"), _t(s, sf, "region")
    c = _t(s, sf, "customer").select("c_custkey", "c_nationkey")
    o = _t(s, sf, "orders").select("o_orderkey", "o_custkey")
    geo = F.broadcast(n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey).select("n_nationkey", "r_name"))
    return c.join(geo, c.c_nationkey == geo.n_nationkey).join(o, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("r_name").agg(F.countDistinct("c_custkey").alias("customers"), F.count("o_orderkey").alias("orders"))


def _semi_anti(s: SparkSession, sf: str) -> DataFrame:
    c, o = _t(s, sf, "customer").select("c_custkey", "c_nationkey"), _t(s, sf, "orders").select(F.col("o_custkey").alias("c_custkey"))
    has = c.join(o, "c_custkey", "left_semi").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("with_orders"))
    none = c.join(o, "c_custkey", "left_anti").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("without_orders"))
    return has.join(none, "c_nationkey", "full").select("c_nationkey", F.coalesce("with_orders", F.lit(0)).alias("with_orders"), F.coalesce("without_orders", F.lit(0)).alias("without_orders"))


def _as_of(s: SparkSession, sf: str) -> DataFrame:
    e = _t(s, sf, "events").select("event_id", "user_id", "ts", "event_type")
    clicks = e.filter("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("click"))
    return as_of_join(e.filter("event_type = 'purchase'").select("event_id", "user_id", "ts"), clicks, "user_id", "ts", "click").select("event_id", F.coalesce("click_asof", F.lit(-1)).alias("click_asof"))


def _band(s: SparkSession, sf: str) -> DataFrame:
    a = _t(s, sf, "supplier").select("s_suppkey", F.col("s_acctbal").cast("double").alias("x"))
    b = _t(s, sf, "supplier").select(F.col("s_suppkey").alias("t_suppkey"), (F.col("s_acctbal").cast("double") - 50).alias("lo"), (F.col("s_acctbal").cast("double") + 50).alias("hi"))
    return range_bucket_join(a, b, "x", "lo", "hi", 100.0).filter("s_suppkey <> t_suppkey").groupBy("s_suppkey").agg(F.count(F.lit(1)).alias("near"))


def _salted(s: SparkSession, sf: str) -> DataFrame:
    o = _t(s, sf, "orders").select("o_orderkey", F.col("o_custkey").alias("k"))
    return salted_join(o, _t(s, sf, "customer").select(F.col("c_custkey").alias("k"), "c_mktsegment"), "k").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("orders"))


def _lateral(s: SparkSession, sf: str) -> DataFrame:
    _t(s, sf, "customer").select("c_custkey", "c_nationkey").createOrReplaceTempView("lat_customer")
    _t(s, sf, "orders").select("o_orderkey", "o_custkey", "o_totalprice").createOrReplaceTempView("lat_orders")
    return s.sql("SELECT c_custkey, t.o_orderkey FROM lat_customer, LATERAL (SELECT o_orderkey FROM lat_orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1) t")


def _cube(s: SparkSession, sf: str) -> DataFrame:
    p = _t(s, sf, "part")
    return p.cube("p_type", "p_brand").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("g"))


def _pivot(s: SparkSession, sf: str) -> DataFrame:
    e = _t(s, sf, "events")
    return e.groupBy("user_id").agg(*[F.count_if(F.col("event_type") == v).alias(v) for v in ("click", "purchase", "view")])


def _rank(s: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return _t(s, sf, "customer").select("c_nationkey", "c_custkey", "c_acctbal").withColumn("nth", F.row_number().over(w)).filter("nth <= 3").select("c_nationkey", "c_custkey", "nth")


def _frames(s: SparkSession, sf: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = _t(s, sf, "events").select("user_id", "event_id", "ts")
    at = F.unix_seconds(F.col("ts").cast("timestamp"))
    gap = at - F.lag(at).over(w)
    back = F.count(F.lit(1)).over(w.rowsBetween(-4, 0))
    session = e.withColumn("new", F.coalesce(gap > 86_400, F.lit(True)).cast("long")).withColumn("recent", back)
    return session.withColumn("session", F.sum("new").over(w)).select("user_id", "event_id", "session", "recent")


def _sets(s: SparkSession, sf: str) -> DataFrame:
    c, p = _t(s, sf, "customer").select(F.col("c_nationkey").alias("k")), _t(s, sf, "supplier").select(F.col("s_nationkey").alias("k"))
    tag = lambda d, n: d.select(F.lit(n).alias("op"), "k")
    return tag(c.union(p).distinct(), "union").unionByName(tag(c.intersect(p), "intersect")).unionByName(tag(c.exceptAll(p).distinct(), "except_all"))


def _json(s: SparkSession, sf: str) -> DataFrame:
    e = _t(s, sf, "events").select("event_id", "props")
    return e.select("event_id", F.length("props").cast("long").alias("size"), F.from_json("props", "map<string,string>").alias("m")).select("event_id", "size", F.array_join(F.array_sort(F.map_keys("m")), ",").alias("keys"))


def _strings(s: SparkSession, sf: str) -> DataFrame:
    host = F.parse_url("url", F.lit("HOST"))
    words = F.size(F.filter(F.split(F.regexp_replace("html", "<[^>]*>", " "), r"\s+"), lambda x: x != "")).cast("long")
    return _t(s, sf, "pages").select("page_id", host.alias("host"), words.alias("words"))


def _dates(s: SparkSession, sf: str) -> DataFrame:
    o = _t(s, sf, "orders")
    return o.groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("orders"), F.countDistinct("o_custkey").alias("customers"))


def _arrays(s: SparkSession, sf: str) -> DataFrame:
    v = _t(s, sf, "embeddings")
    return v.select("vec_id", F.size(F.filter("embedding", lambda x: x >= 0)).cast("long").alias("positive"), F.element_at("embedding", 1).cast("double").alias("first"))


def _windows(s: SparkSession, sf: str) -> DataFrame:
    return _t(s, sf, "events").groupBy(F.window("ts", "1 day").start.cast("date").alias("day"), "event_type").agg(F.count(F.lit(1)).alias("n"))


def _sampled(s: SparkSession, sf: str) -> DataFrame:
    """A sampling operator: a tenth of the customers by a digest of the key, the same at every run."""
    c = _t(s, sf, "customer")
    digest = F.conv(F.substring(F.md5(F.col("c_custkey").cast("string")), 1, 8), 16, 10).cast("long")
    return c.filter(digest % 10 == 0).select("c_custkey")


QUERIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "scan_filter_project": (_scan, "SELECT l_orderkey, l_partkey, l_partkey % 10 AS bucket FROM lineitem WHERE l_quantity < 5 AND l_discount >= 0.05"),
    "joins_broadcast_outer": (_joins, "SELECT r_name, count(DISTINCT c_custkey) AS customers, count(o_orderkey) AS orders FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey LEFT JOIN orders ON c_custkey = o_custkey GROUP BY r_name"),
    "joins_semi_anti": (_semi_anti, "SELECT c_nationkey, count(*) FILTER (WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)) AS with_orders, count(*) FILTER (WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)) AS without_orders FROM customer GROUP BY c_nationkey"),
    "joins_as_of": (_as_of, "SELECT p.event_id, coalesce((SELECT arg_max(e.event_id, (e.ts, e.event_id)) FROM events e WHERE e.event_type = 'click' AND e.user_id = p.user_id AND e.ts <= p.ts), -1) AS click_asof FROM events p WHERE p.event_type = 'purchase'"),
    "joins_range": (_band, "SELECT x.s_suppkey, count(*) AS near FROM supplier x JOIN supplier y ON x.s_suppkey <> y.s_suppkey AND CAST(x.s_acctbal AS DOUBLE) BETWEEN CAST(y.s_acctbal AS DOUBLE) - 50 AND CAST(y.s_acctbal AS DOUBLE) + 50 GROUP BY x.s_suppkey"),
    "joins_salted": (_salted, "SELECT c_mktsegment, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment"),
    "joins_lateral": (_lateral, "SELECT o_custkey AS c_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders JOIN customer ON o_custkey = c_custkey) WHERE r = 1"),
    "agg_cube": (_cube, "SELECT p_type, p_brand, count(*) AS n, CAST(grouping(p_type, p_brand) AS BIGINT) AS g FROM part GROUP BY CUBE (p_type, p_brand)"),
    "agg_pivot": (_pivot, "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{v}') AS {v}" for v in ("click", "purchase", "view")) + " FROM events GROUP BY user_id"),
    "window_rank": (_rank, "SELECT c_nationkey, c_custkey, CAST(nth AS INTEGER) AS nth FROM (SELECT c_nationkey, c_custkey, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS nth FROM customer) WHERE nth <= 3"),
    "window_frames": (_frames, "WITH g AS (SELECT user_id, event_id, ts, CASE WHEN epoch(date_trunc('second', ts)) - epoch(date_trunc('second', lag(ts) OVER w)) <= 86400 THEN 0 ELSE 1 END AS new, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS recent FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) SELECT user_id, event_id, CAST(sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS session, recent FROM g"),
    "set_ops": (_sets, "SELECT 'union' AS op, k FROM (SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier) UNION ALL SELECT 'intersect', k FROM (SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier) UNION ALL SELECT DISTINCT 'except_all', k FROM (SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier)"),
    "json_props": (_json, "SELECT event_id, CAST(length(props) AS BIGINT) AS size, array_to_string(list_sort(json_keys(props)), ',') AS keys FROM events"),
    "strings_urls": (_strings, r"SELECT page_id, regexp_extract(url, '://([^/?#:]+)', 1) AS host, CAST(len(list_filter(regexp_split_to_array(regexp_replace(html, '<[^>]*>', ' ', 'g'), '\s+'), lambda x: x <> '')) AS BIGINT) AS words FROM pages"),
    "dates_months": (_dates, "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS orders, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY 1"),
    "arrays_vectors": (_arrays, "SELECT vec_id, CAST(len(list_filter(embedding, lambda x: x >= 0)) AS BIGINT) AS positive, CAST(embedding[1] AS DOUBLE) AS first FROM embeddings"),
    "time_windows": (_windows, "SELECT CAST(ts AS DATE) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
    "sample_by_digest": (_sampled, "SELECT c_custkey FROM customer WHERE CAST('0x' || substr(md5(CAST(c_custkey AS VARCHAR)), 1, 8) AS BIGINT) % 10 = 0"),
}
