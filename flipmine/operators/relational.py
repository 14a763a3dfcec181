"""Joins, windows and groupings around basket data, each a plan over given tables with its SQL counterpart."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

Load = Callable[..., DataFrame]


def _micros(ts: Column) -> Column:
    return F.unix_micros(ts.cast("timestamp"))


def contains(items: str, itemset: tuple[int, ...]) -> Column:
    """Whether the list ``items`` has all of ``itemset``."""
    return F.size(F.array_except(F.array(*(F.lit(i) for i in itemset)), items)) == 0


def support_shares(counts: DataFrame) -> DataFrame:
    """Item counts (item, n) with share of the total, rank, relative rank and quarter; a universe is small, so one window is enough."""
    by_n = Window.orderBy("n")
    return counts.select(
        "item", "n", F.round(F.col("n") / F.sum("n").over(Window.partitionBy()), 9).alias("share"), F.rank().over(Window.orderBy(F.desc("n"))).alias("rank"),
        F.round(F.percent_rank().over(by_n), 9).alias("relative"), F.ntile(4).over(Window.orderBy("n", "item")).alias("quarter"),
    )


def asof(left: DataFrame, right: DataFrame, key: str, at: str, value: str, out: str) -> DataFrame:
    """Each row of ``left`` with the ``value`` of the latest row of ``right`` not after it; one window over the union, no range join.

    Both have ``key`` and ``at``; of rows of equal time the right ones come first, of equal ones the greatest value wins.
    """
    a = left.withColumn("side", F.lit(1)).withColumn(out, F.lit(None).cast(right.schema[value].dataType))
    b = right.select(key, at, F.lit(0).alias("side"), F.col(value).alias(out))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(at, "side", F.col(out).asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn(out, F.last(out, ignorenulls=True).over(w)).where("side = 1").drop("side")


def sessions(events: DataFrame, gap_seconds: int = 1800) -> DataFrame:
    """Events of a user whose neighbours are ``gap_seconds`` apart or closer: (user_id, begin, n)."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    new = F.coalesce(_micros(F.col("ts")) - _micros(F.lag("ts").over(w)) > gap_seconds * 1_000_000, F.lit(True))
    numbered = events.withColumn("session", F.sum(new.cast("int")).over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy("user_id", "session").agg(F.min("ts").alias("begin"), F.count(F.lit(1)).alias("n")).drop("session")


def salted_pair_counts(long: DataFrame, salts: int = 16) -> DataFrame:
    """(a, b, n): pairs of items that share a tuple, where one tuple may be very long.

    The left side of a tuple's self-join is dealt to ``salts`` parts and the right side copied to each.
    """
    left = long.select("tid", F.col("item").alias("a"), F.pmod(F.xxhash64("item"), F.lit(salts)).cast("int").alias("salt"))
    right = long.select("tid", F.col("item").alias("b"), F.explode(F.sequence(F.lit(0), F.lit(salts - 1))).alias("salt"))
    return left.join(right, ["tid", "salt"]).where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


def _asof_enrich(load: Load) -> DataFrame:
    events = load("events", "event_id", "user_id", "ts").select("event_id", F.col("user_id").alias("key"), F.col("ts").cast("timestamp").alias("at"))
    orders = load("orders", "o_orderkey", "o_custkey", "o_orderdate").select(F.col("o_custkey").alias("key"), F.col("o_orderdate").cast("timestamp").alias("at"), "o_orderkey")
    return asof(events, orders, "key", "at", "o_orderkey", "last_order").select("event_id", "last_order")


def _clicks_session(load: Load) -> DataFrame:
    return sessions(load("events", "event_id", "user_id", "ts"))


def _clicks_recent(load: Load) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy(_micros(F.col("ts"))).rangeBetween(-86_400_000_000, 0)
    return load("events", "event_id", "user_id", "ts").select("event_id", F.count(F.lit(1)).over(w).alias("recent"))


def _running_support(load: Load) -> DataFrame:
    rows = load("lineitem", "l_orderkey", "l_suppkey").distinct()
    w = Window.partitionBy("l_suppkey").orderBy("l_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return rows.select("l_orderkey", "l_suppkey", F.count(F.lit(1)).over(w).alias("so_far"))


def _items_per_user(load: Load) -> DataFrame:
    rows = load("events", "user_id", "event_type", "props")
    return rows.groupBy("user_id").agg(F.count_distinct(F.get_json_object("props", "$.k")).alias("items"), F.count_distinct("event_type").alias("types"), F.count(F.lit(1)).alias("events"))


def _json_items(load: Load) -> DataFrame:
    rows = load("events", "props").select(F.from_json("props", "k int").k.alias("k"))
    return rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"))


def _set_ops_all(load: Load) -> DataFrame:
    a, b = load("orders", "o_custkey").select(F.col("o_custkey").alias("c")), load("customer", "c_custkey").select(F.col("c_custkey").alias("c"))
    parts = (("intersect_all", a.intersectAll(b)), ("except_all", a.exceptAll(b)), ("none", b.exceptAll(a)))
    out = None
    for name, df in parts:
        one = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("part"), "n")
        out = one if out is None else out.unionByName(one)
    return out


def _level_delta(load: Load) -> DataFrame:
    """Brands' order counts by year and the change from the year before."""
    lines = load("lineitem", "l_orderkey", "l_partkey", "l_shipdate").join(load("part", "p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    by = lines.groupBy("p_brand", F.year("l_shipdate").alias("year")).agg(F.count_distinct("l_orderkey").alias("n"))
    return by.withColumn("change", F.col("n") - F.lag("n").over(Window.partitionBy("p_brand").orderBy("year")))


def _sliced_items(load: Load) -> DataFrame:
    """Suppliers in a slice of time; the filter and the two columns reach the scan."""
    rows = load("lineitem", "l_orderkey", "l_suppkey", "l_shipdate").where("l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01'")
    return rows.groupBy("l_suppkey").agg(F.count_distinct("l_orderkey").alias("n"))


def _range_join(load: Load) -> DataFrame:
    """Orders by price band; bands are few, and the equality on the bucket keeps the join from comparing all with all."""
    orders = load("orders", "o_orderkey", "o_totalprice").withColumn("bucket", F.floor(F.col("o_totalprice") / 100_000).cast("long"))
    bands = orders.sparkSession.range(20).select(F.col("id").alias("band"), (F.col("id") * 50_000).alias("low"), ((F.col("id") + 1) * 50_000).alias("high"), F.floor(F.col("id") / 2).alias("bucket"))
    return orders.join(F.broadcast(bands), "bucket").where("o_totalprice >= low AND o_totalprice < high").groupBy("band").agg(F.count(F.lit(1)).alias("n"))


def _rollup_segments(load: Load) -> DataFrame:
    rows = load("orders", "o_custkey", "o_orderpriority").join(load("customer", "c_custkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
    out = rows.rollup("c_mktsegment", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("gid"))
    return out.select(F.coalesce("c_mktsegment", F.lit("all")).alias("segment"), F.coalesce("o_orderpriority", F.lit("all")).alias("priority"), "n", F.col("gid").cast("long").alias("gid"))


def _salted_pairs(load: Load) -> DataFrame:
    rows = load("lineitem", "l_orderkey", "l_suppkey").select(F.col("l_orderkey").alias("tid"), F.col("l_suppkey").cast("int").alias("item")).distinct()
    return salted_pair_counts(rows)


#: Name to (plan, oracle).
TABLE_QUERIES: dict[str, tuple[Callable[[Load], DataFrame], str]] = {
    "asof_enrich": (_asof_enrich, """WITH b AS (SELECT event_id, user_id AS k, ts AS tm, 1 AS side, NULL::BIGINT AS o FROM events UNION ALL SELECT NULL, o_custkey, o_orderdate::TIMESTAMP, 0, o_orderkey FROM orders)
SELECT event_id, last_order FROM (SELECT event_id, side, last_value(o IGNORE NULLS) OVER (PARTITION BY k ORDER BY tm, side, o NULLS FIRST ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_order FROM b) WHERE side = 1"""),
    "clicks_session": (_clicks_session, """WITH g AS (SELECT *, coalesce(epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) > 1800000000, TRUE)::INT AS fresh FROM events),
s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS session FROM g) SELECT user_id, min(ts) AS "begin", count(*) AS n FROM s GROUP BY user_id, session"""),
    "clicks_recent": (_clicks_recent, "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS recent FROM events"),
    "running_support": (_running_support, "SELECT l_orderkey, l_suppkey, count(*) OVER (PARTITION BY l_suppkey ORDER BY l_orderkey ROWS UNBOUNDED PRECEDING) AS so_far FROM (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem)"),
    "items_per_user": (_items_per_user, "SELECT user_id, count(DISTINCT json_extract_string(props, '$.k')) AS items, count(DISTINCT event_type) AS types, count(*) AS events FROM events GROUP BY user_id"),
    "json_items": (_json_items, "SELECT json_extract_string(props, '$.k')::INTEGER AS k, count(*) AS n FROM events GROUP BY 1"),
    "set_ops_all": (_set_ops_all, "SELECT 'intersect_all' AS part, count(*) AS n FROM (SELECT o_custkey FROM orders INTERSECT ALL SELECT c_custkey FROM customer) UNION ALL SELECT 'except_all', count(*) FROM (SELECT o_custkey FROM orders EXCEPT ALL SELECT c_custkey FROM customer) UNION ALL SELECT 'none', count(*) FROM (SELECT c_custkey FROM customer EXCEPT ALL SELECT o_custkey FROM orders)"),
    "level_delta": (_level_delta, "SELECT p_brand, year::INTEGER AS year, n, n - lag(n) OVER (PARTITION BY p_brand ORDER BY year) AS change FROM (SELECT p_brand, year(l_shipdate) AS year, count(DISTINCT l_orderkey) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL)"),
    "sliced_items": (_sliced_items, "SELECT l_suppkey, count(DISTINCT l_orderkey) AS n FROM lineitem WHERE l_shipdate >= TIMESTAMP '1996-01-01' AND l_shipdate < TIMESTAMP '1997-01-01' GROUP BY 1"),
    "range_join": (_range_join, "SELECT floor(o_totalprice / 50000)::BIGINT AS band, count(*) AS n FROM orders WHERE o_totalprice < 1000000 GROUP BY 1"),
    "rollup_segments": (_rollup_segments, "SELECT coalesce(c_mktsegment, 'all') AS segment, coalesce(o_orderpriority, 'all') AS priority, count(*) AS n, grouping_id(c_mktsegment, o_orderpriority)::BIGINT AS gid FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ROLLUP (c_mktsegment, o_orderpriority)"),
    "salted_pairs": (_salted_pairs, "WITH x AS (SELECT DISTINCT l_orderkey AS tid, l_suppkey::INTEGER AS item FROM lineitem) SELECT u.item AS a, v.item AS b, count(*) AS n FROM x u JOIN x v ON u.tid = v.tid AND u.item < v.item GROUP BY ALL"),
}
