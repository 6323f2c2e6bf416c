"""Operators that surround the methods: joins by time and range, roll-ups, windows, sets, pivots."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from annspark.sources.tables import table


def asof_join(left: DataFrame, right: DataFrame, key: str, ts: str, value: str, name: str) -> DataFrame:
    """Each left row with the latest ``value`` of the right side at or before its time, null where there is none.

    Both sides go through one shuffle by the key, in time order; right rows come
    before left rows of the same time.
    """
    marked = left.withColumns({"_v": F.lit(None).cast(dict(right.dtypes)[value]), "_side": F.lit(1)})
    other = right.select(key, ts, F.col(value).alias("_v"), F.lit(0).alias("_side"))
    by = W.partitionBy(key).orderBy(ts, "_side").rowsBetween(W.unboundedPreceding, 0)
    both = marked.unionByName(other, allowMissingColumns=True)
    return both.withColumn(name, F.last("_v", ignorenulls=True).over(by)).where("_side = 1").drop("_v", "_side")


def range_join(left: DataFrame, right: DataFrame, key: str, left_ts: str, right_ts: str, seconds: int) -> DataFrame:
    """Pairs of the same key with the right time in (left, left + seconds]: time buckets meet by equality, then the check."""
    bucket = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / seconds)
    a = left.withColumn("_b", F.explode(F.array(bucket(left_ts), bucket(left_ts) + 1)))
    b = right.withColumn("_b", bucket(right_ts))
    near = (F.col(right_ts) > F.col(left_ts)) & (F.unix_micros(F.col(right_ts).cast("timestamp")) <= F.unix_micros(F.col(left_ts).cast("timestamp")) + seconds * 1_000_000)
    return a.join(b, [key, "_b"]).where(near).drop("_b")


def salted_sum(df: DataFrame, key: str, value: str, salts: int = 16) -> DataFrame:
    """Sums by key in two steps, so that one hot key is many groups first."""
    first = df.groupBy(key, F.pmod(F.xxhash64(*df.columns), F.lit(salts)).alias("_salt")).agg(F.sum(value).alias("_s"), F.count("*").alias("_n"))
    return first.groupBy(key).agg(F.sum("_s").alias(f"sum_{value}"), F.sum("_n").alias("n"))


def r2(c: Column | str) -> Column:
    return F.round(c, 2) + 0.0


def scan_filter(spark, d):
    line = table(spark, d, "lineitem")
    return line.where("l_shipdate >= TIMESTAMP '1998-01-01' AND l_quantity < 5").select("l_orderkey", "l_linenumber", "l_quantity")


def agg_rollup(spark, d):
    out = table(spark, d, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), r2(F.sum("l_quantity")).alias("quantity"), F.grouping_id().alias("level"))
    return out


def cube_orders(spark, d):
    return table(spark, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.countDistinct("o_custkey").alias("customers"))


def window_rank(spark, d):
    by = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, d, "orders").withColumn("place", F.row_number().over(by)).where("place <= 3").select("o_custkey", "o_orderkey", "place")


def asof_events(spark, d):
    e = table(spark, d, "events")
    views = e.where("event_type = 'view'").select("event_id", "user_id", "ts")
    bought = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase_id"))
    return asof_join(views, bought, "user_id", "ts", "purchase_id", "last_purchase").select("event_id", "last_purchase")


def range_events(spark, d):
    e = table(spark, d, "events")
    a = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("purchase_ts"))
    return range_join(a, b, "user_id", "click_ts", "purchase_ts", 7200).select("click_id", "purchase_id")


def semi_anti(spark, d):
    orders = table(spark, d, "orders")
    cust = table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    big = orders.where("o_totalprice > 400000").select(F.col("o_custkey").alias("c_custkey"))
    low = orders.where("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("c_custkey"))
    return cust.join(big, "c_custkey", "left_semi").join(low, "c_custkey", "left_anti")


def set_operations(spark, d):
    line = table(spark, d, "lineitem")
    of = lambda flag: line.where(F.col("l_returnflag") == flag).select("l_orderkey")
    return of("R").intersect(of("A")).exceptAll(of("N").distinct()).union(of("R").subtract(of("A")))


def pivot_orders(spark, d):
    out = table(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1)))
    return out.select("o_orderpriority", *[F.coalesce(c, F.lit(0)).alias(f"n_{c.lower()}") for c in ("F", "O", "P")])


def json_props(spark, d):
    k = F.from_json("props", "k INT")["k"]
    return table(spark, d, "events").groupBy("event_type").agg(F.sum(k).alias("sum_k"), F.max(k).alias("max_k"))


def salted_events(spark, d):
    return salted_sum(table(spark, d, "events").select("event_type", F.round(F.col("value") * 100).cast("long").alias("cents")), "event_type", "cents")


def hourly_windows(spark, d):
    out = table(spark, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "6 hours").alias("w"), "event_type").agg(F.count("*").alias("n"))
    return out.select(F.unix_seconds("w.start").alias("start_s"), "event_type", "n")


QUERIES = {
    "scan_filter": (scan_filter, "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1998-01-01' AND l_quantity < 5"),
    "agg_rollup": (agg_rollup, "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, grouping_id(l_returnflag, l_linestatus) AS level FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)"),
    "cube_orders": (cube_orders, "SELECT o_orderstatus, o_orderpriority, count(*) AS n, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)"),
    "window_rank": (window_rank, "SELECT o_custkey, o_orderkey, CAST(place AS INTEGER) AS place FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS place FROM orders) WHERE place <= 3"),
    "asof_join": (asof_events, "SELECT v.event_id, p.event_id AS last_purchase FROM (SELECT * FROM events WHERE event_type = 'view') v ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON v.user_id = p.user_id AND v.ts >= p.ts"),
    "range_join": (range_events, "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 2 HOUR"),
    "semi_anti_join": (semi_anti, "SELECT c_custkey, c_mktsegment FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 400000) AND c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')"),
    "set_operations": (set_operations, "(SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R' INTERSECT SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'A' EXCEPT SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'N') UNION ALL (SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'R' EXCEPT SELECT l_orderkey FROM lineitem WHERE l_returnflag = 'A')"),
    "pivot_orders": (pivot_orders, "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS n_f, count(*) FILTER (o_orderstatus = 'O') AS n_o, count(*) FILTER (o_orderstatus = 'P') AS n_p FROM orders GROUP BY o_orderpriority"),
    "json_props": (json_props, "SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS sum_k, CAST(max(CAST(json_extract(props, '$.k') AS INTEGER)) AS INTEGER) AS max_k FROM events GROUP BY event_type"),
    "salted_sum": (salted_events, "SELECT event_type, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS sum_cents, count(*) AS n FROM events GROUP BY event_type"),
    "tumbling_windows": (hourly_windows, "SELECT CAST(epoch(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01')) AS BIGINT) AS start_s, event_type, count(*) AS n FROM events GROUP BY ALL"),
}
