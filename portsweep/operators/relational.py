"""The relational operations around the protocols, each as a query over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.graphs import table


def interval_join(points: DataFrame, ranges: DataFrame, x: str, lo: str, hi: str, width: int) -> DataFrame:
    """Pairs with lo <= x <= hi as an equi-join over buckets of `width`; exact for ranges of any length."""
    p = points.withColumn("__bucket", F.floor(F.col(x) / width))
    r = ranges.withColumn("__bucket", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor(F.col(hi) / width))))
    return p.join(r, "__bucket").where(F.col(x).between(F.col(lo), F.col(hi))).drop("__bucket")


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """left with the last `value` of right at or before ts for the same key: one union and one window, no pairs."""
    both = left.select(key, ts, *[c for c in left.columns if c not in (key, ts)], F.lit(None).cast(right.schema[value].dataType).alias("__v"), F.lit(1).alias("__left"))
    blank = [F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (key, ts)]
    both = both.union(right.select(key, ts, *blank, F.col(value).alias("__v"), F.lit(0)))
    by = W.partitionBy(key).orderBy(ts, "__left").rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn(value, F.last("__v", ignorenulls=True).over(by)).where("__left = 1").drop("__v", "__left")


def top_k(df: DataFrame, k: int, *order: F.Column) -> DataFrame:
    return df.orderBy(*order).limit(k)


def revenue_rollup(s: SparkSession, d: str) -> DataFrame:
    """The same sums as the bottom-up protocol, by rollup."""
    o, c, n, r = (table(s, d, t) for t in ("orders", "customer", "nation", "region"))
    j = o.join(c, o.o_custkey == c.c_custkey).join(n, c.c_nationkey == n.n_nationkey).join(r, n.n_regionkey == r.r_regionkey)
    return j.rollup("r_name", "n_name").agg(F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))


def pricing_cube(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("quantity"), F.countDistinct("l_suppkey").alias("suppliers"))


def last_event_before_error(s: SparkSession, d: str) -> DataFrame:
    e = table(s, d, "events")
    errors = e.where("event_type = 'error'").select("user_id", "ts", "event_id")
    others = e.where("event_type <> 'error'").select("user_id", "ts", F.col("event_id").alias("before_id"))
    return asof_join(errors, others, "user_id", "ts", "before_id").select("event_id", "before_id")


def parts_in_price_bands(s: SparkSession, d: str) -> DataFrame:
    parts = table(s, d, "part").select("p_partkey", F.floor("p_retailprice").cast("bigint").alias("price"))
    bands = table(s, d, "nation").select("n_nationkey", (900 + F.col("n_nationkey") * 40).cast("bigint").alias("lo"), (1000 + F.col("n_nationkey") * 45).cast("bigint").alias("hi"))
    return interval_join(parts, bands, "price", "lo", "hi", 50).groupBy("n_nationkey").agg(F.count("*").alias("parts"))


def customers_without_orders(s: SparkSession, d: str) -> DataFrame:
    c, o = table(s, d, "customer"), table(s, d, "orders")
    return c.join(o, c.c_custkey == o.o_custkey, "left_anti").select("c_custkey")


def supplier_sets(s: SparkSession, d: str) -> DataFrame:
    """Suppliers of region 1 that supplied (intersect) and that supplied nothing returned (except)."""
    sup, n, li = table(s, d, "supplier"), table(s, d, "nation"), table(s, d, "lineitem")
    mine = sup.join(n.where("n_regionkey = 1"), sup.s_nationkey == n.n_nationkey).select("s_suppkey")
    used, returned = li.select("l_suppkey"), li.where("l_returnflag = 'R' and l_quantity > 49").select("l_suppkey")
    return mine.intersect(used).select(F.lit("used").alias("what"), "s_suppkey").union(mine.exceptAll(returned.distinct()).select(F.lit("clean"), "s_suppkey"))


def user_sessions(s: SparkSession, d: str) -> DataFrame:
    by = W.partitionBy("user_id").orderBy("ts", "event_id")
    e = table(s, d, "events").select("user_id", "event_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("ts"))
    new = F.coalesce((F.col("ts") - F.lag("ts").over(by) > 6 * 3600 * 1_000_000).cast("bigint"), F.lit(1))
    return e.withColumn("new", new).groupBy("user_id").agg(F.sum("new").alias("sessions"), F.count("*").alias("events"))


def event_keys(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "events").groupBy("event_type", F.get_json_object("props", "$.k").alias("k")).agg(F.count("*").alias("n"))


def events_per_day(s: SparkSession, d: str) -> DataFrame:
    day = F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd")
    return table(s, d, "events").groupBy(day.alias("day")).agg(F.count("*").alias("n"), F.countDistinct("user_id").alias("users"))


def top_customers(s: SparkSession, d: str) -> DataFrame:
    o = table(s, d, "orders").groupBy("o_custkey").agg(F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).alias("cents"))
    return top_k(o, 10, F.desc("cents"), F.col("o_custkey"))


def nation_quartiles(s: SparkSession, d: str) -> DataFrame:
    c = table(s, d, "customer").groupBy("c_nationkey").agg(F.count("*").alias("n"))
    by = W.orderBy(F.desc("n"), "c_nationkey")  # 25 rows
    return c.select(F.col("c_nationkey").cast("bigint").alias("c_nationkey"), "n", F.ntile(4).over(by).cast("bigint").alias("quartile"), F.dense_rank().over(W.orderBy(F.desc("n"))).cast("bigint").alias("place"))


def page_hosts(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("host")).agg(F.count("*").alias("pages"))


def approximate_users(s: SparkSession, d: str) -> DataFrame:
    """Whether the sketched number of users lies within a tenth of the exact one (its standard error is 0.02)."""
    e = table(s, d, "events").agg(F.countDistinct("user_id").alias("users"), F.approx_count_distinct("user_id", 0.02).alias("near"))
    return e.select("users", (10 * F.abs(F.col("near") - F.col("users")) <= F.col("users")).alias("close"))


def grouped_sales(s: SparkSession, d: str) -> DataFrame:
    li = table(s, d, "lineitem")
    li.createOrReplaceTempView("portsweep_lineitem")
    return s.sql("SELECT l_returnflag, l_linestatus, count(*) n FROM portsweep_lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")


def price_percentiles(s: SparkSession, d: str) -> DataFrame:
    """Exact percentiles of whole prices for each brand."""
    p = table(s, d, "part").select("p_brand", F.floor("p_retailprice").cast("bigint").alias("price"))
    return p.groupBy("p_brand").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY price)").cast("bigint").alias("median"), F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY price)").cast("bigint").alias("p90"))


def supplier_volume(s: SparkSession, d: str) -> DataFrame:
    """A shuffled hash join, by hint, for two sides of which the smaller one's parts fit in memory."""
    li, sup = table(s, d, "lineitem").select("l_suppkey"), table(s, d, "supplier").select("s_suppkey", "s_nationkey")
    return li.join(sup.hint("shuffle_hash"), li.l_suppkey == sup.s_suppkey).groupBy("s_nationkey").agg(F.count("*").alias("items"))


_ALL = {
    approximate_users: "SELECT count(DISTINCT user_id) users, true \"close\" FROM events",
    grouped_sales: "SELECT l_returnflag, l_linestatus, count(*) n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    price_percentiles: "SELECT p_brand, quantile_disc(price, 0.5) median, quantile_disc(price, 0.9) p90 FROM (SELECT p_brand, CAST(floor(p_retailprice) AS BIGINT) price FROM part) GROUP BY p_brand",
    supplier_volume: "SELECT s_nationkey, count(*) items FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_nationkey",
    revenue_rollup: "SELECT r_name, n_name, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) cents FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
    pricing_cube: "SELECT l_returnflag, l_linestatus, count(*) n, CAST(sum(CAST(floor(l_quantity) AS BIGINT)) AS BIGINT) quantity, count(DISTINCT l_suppkey) suppliers FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)",
    last_event_before_error: "SELECT e.event_id, o.event_id before_id FROM (SELECT * FROM events WHERE event_type = 'error') e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type <> 'error') o ON e.user_id = o.user_id AND e.ts >= o.ts",
    parts_in_price_bands: "SELECT n_nationkey, count(*) parts FROM part JOIN nation ON CAST(floor(p_retailprice) AS BIGINT) BETWEEN 900 + n_nationkey * 40 AND 1000 + n_nationkey * 45 GROUP BY n_nationkey",
    customers_without_orders: "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
    supplier_sets: "WITH mine AS (SELECT s_suppkey FROM supplier JOIN nation ON s_nationkey = n_nationkey WHERE n_regionkey = 1) SELECT 'used' what, s_suppkey FROM (SELECT s_suppkey FROM mine INTERSECT SELECT l_suppkey FROM lineitem) UNION ALL SELECT 'clean', s_suppkey FROM (SELECT s_suppkey FROM mine EXCEPT SELECT l_suppkey FROM lineitem WHERE l_returnflag = 'R' AND l_quantity > 49)",
    user_sessions: "SELECT user_id, CAST(sum(n) AS BIGINT) sessions, count(*) events FROM (SELECT user_id, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) <= 21600000000 THEN 0 ELSE 1 END n FROM events) GROUP BY user_id",
    event_keys: "SELECT event_type, json_extract_string(props, '$.k') k, count(*) n FROM events GROUP BY ALL",
    events_per_day: "SELECT strftime(ts, '%Y-%m-%d') \"day\", count(*) n, count(DISTINCT user_id) users FROM events GROUP BY ALL",
    top_customers: "SELECT o_custkey, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) AS BIGINT) cents FROM orders GROUP BY o_custkey ORDER BY cents DESC, o_custkey LIMIT 10",
    nation_quartiles: "SELECT CAST(c_nationkey AS BIGINT) c_nationkey, n, ntile(4) OVER (ORDER BY n DESC, c_nationkey) quartile, dense_rank() OVER (ORDER BY n DESC) place FROM (SELECT c_nationkey, count(*) n FROM customer GROUP BY c_nationkey)",
    page_hosts: "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) host, count(*) pages FROM pages GROUP BY ALL",
}


def queries() -> dict:
    return {f.__name__: f for f in _ALL}


def oracle_sql() -> dict[str, str]:
    return {f.__name__: q for f, q in _ALL.items()}
