"""Scans, filters, joins, aggregates, windows and set operations on the tables.

Each entry is ``name: (frame, SQL)``; the SQL is an independent statement of it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from peertrust import graph
from peertrust.functions.rng import RNG_SEED, TWO32, u32, u32_sql
from peertrust.queries import sqltext as s
from peertrust.sources.tables import interactions, load, numbered, peer_edges

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def _counts(spark, d):
    out = None
    for t in TABLES:
        row = load(spark, d, t).agg(F.count(F.lit(1)).alias("n")).select(F.lit(t).alias("name"), "n")
        out = row if out is None else out.union(row)
    return out


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """An inner join whose hot keys are spread: rows of the left side draw a salt, the
    right side is repeated for each."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "_salt"]).drop("_salt")


def interval_join(a: DataFrame, b: DataFrame, time: str, other: str, seconds: int) -> DataFrame:
    """Pairs of rows at most ``seconds`` apart: an equality join on time buckets, each
    right row standing in its own and both neighbouring ones."""
    bucket = F.floor(F.unix_micros(time) / F.lit(seconds * 1_000_000))
    right = b.withColumn("_b", F.explode(F.array(*[F.floor(F.unix_micros(other) / F.lit(seconds * 1_000_000)) + F.lit(i) for i in (-1, 0, 1)])))
    near = F.abs(F.unix_micros(time) - F.unix_micros(other)) <= seconds * 1_000_000
    return a.withColumn("_b", bucket).join(right, "_b").filter(near).drop("_b")


def asof_join(left: DataFrame, right: DataFrame, key: str, time: str, value: str) -> DataFrame:
    """For each left row the last right ``value`` of its key at or before its time:
    one shuffle and one sort of the union, no pairs."""
    a = left.withColumn("_v", F.lit(None).cast(dict(right.dtypes)[value])).withColumn("_right", F.lit(0))
    b = right.select(*[F.col(c) if c in (key, time) else F.lit(None).cast(dict(left.dtypes)[c]).alias(c) for c in left.columns], F.col(value).alias("_v"), F.lit(1).alias("_right"))
    w = Window.partitionBy(key).orderBy(time, F.desc("_right")).rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(f"last_{value}", F.last("_v", ignorenulls=True).over(w)).filter("_right = 0").drop("_v", "_right")


def _chain(spark, d):
    c, n, r = (load(spark, d, t) for t in ("customer", "nation", "region"))
    return c.join(F.broadcast(n), c.c_nationkey == n.n_nationkey).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))


def _sorted(spark, d):
    """A total sort by ranges, with the place that each row has in it."""
    keys = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
    rows = load(spark, d, "lineitem").select(*keys, F.struct((-F.col("l_extendedprice")).alias("a"), *keys).alias("order"))
    return numbered(rows, "order").select(*keys, "place")


def _sorted_within(spark, d):
    """Rows of a supplier meet in one partition and are sorted there, without a total
    order: how often a row is not before its successor of the same supplier."""
    rows = load(spark, d, "lineitem").repartition("l_suppkey").sortWithinPartitions("l_suppkey", F.desc("l_extendedprice"))

    def falls(batches):
        before = None
        for batch in batches:
            if batch.num_rows:
                supplier, price = (batch.column(i).to_numpy() for i in (0, 1))
                last = (supplier[:1], price[:1] + 1) if before is None else before
                fall = (np.append(last[0], supplier[:-1]) == supplier) & (price <= np.append(last[1], price[:-1]))
                if before is None:
                    fall[0] = False
                before = supplier[-1:], price[-1:]
                yield pa.RecordBatch.from_arrays([pa.array(supplier), pa.array(fall.astype(np.int64))], schema=schema)

    schema = pa.schema([("l_suppkey", pa.int64()), ("fall", pa.int64())])
    return rows.select("l_suppkey", "l_extendedprice").mapInArrow(falls, "l_suppkey long, fall long").groupBy("l_suppkey").agg(F.sum("fall").alias("falls"))


def _orders_w():
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


def _asof(spark, d):
    """For each error the amount of the agent's last transfer of another kind."""
    x = interactions(spark, d)
    left = x.filter("kind = 'error'").select("id", "p", "ts")
    right = x.filter("kind <> 'error'").select("p", "ts", "up")
    return asof_join(left, right, "p", "ts", "up").select("id", "last_up")


def _near(spark, d):
    e = load(spark, d, "events").filter("event_type = 'purchase'")
    a, b = e.select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").cast("timestamp").alias("ta")), e.select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").cast("timestamp").alias("tb"))
    return interval_join(a, b, "ta", "tb", 600).filter("ua < ub").select("a", "b")


def _half(spark, d, kinds):
    """Edges of the graph of some kinds of transfers."""
    return graph.net_edges(interactions(spark, d).filter(F.col("kind").isin(*kinds))).select("src", "dst")


_ONE, _OTHER = ("click", "view", "error"), ("purchase", "error", "signup")
_W = "(PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)"
_CHAIN = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
_MUTUAL = s.final(s.TRANSFERS, """
g AS (SELECT src, dst, sum(w) AS w FROM (SELECT q AS src, p AS dst, up AS w FROM tr UNION ALL SELECT p, q, down FROM tr) GROUP BY 1, 2 HAVING sum(w) > 0)""", select="SELECT a.src, a.dst FROM g a JOIN g b ON a.src = b.dst AND a.dst = b.src WHERE a.src < a.dst")


def _sets(op):
    tables = []
    for name, kinds in (("x", _ONE), ("y", _OTHER)):
        tables.append(f"""
{name}_n AS (SELECT least(p, q) AS a, greatest(p, q) AS b, sum(CASE WHEN p < q THEN up - down ELSE down - up END) AS net FROM tr WHERE kind IN {kinds} GROUP BY 1, 2),
{name}_e AS (SELECT CASE WHEN net > 0 THEN b ELSE a END AS src, CASE WHEN net > 0 THEN a ELSE b END AS dst FROM {name}_n WHERE net <> 0)""")
    return s.final(s.TRANSFERS, *tables, select=f"SELECT src, dst FROM x_e {op} SELECT src, dst FROM y_e")


OPERATORS = {
    "op_scan_counts": (_counts, " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES)),
    "op_filter_pushed": (
        lambda spark, d: load(spark, d, "events").filter(F.col("event_type").isin("purchase", "error") & F.col("value").between(10, 100)).select("event_id", "value"),
        "SELECT event_id, value FROM events WHERE event_type IN ('purchase', 'error') AND value BETWEEN 10 AND 100",
    ),
    "op_filter_like_regex": (
        lambda spark, d: load(spark, d, "part").filter(F.col("p_type").like("%A%") & F.col("p_name").rlike("[aeiou]{1}")).select("p_partkey", "p_name"),
        "SELECT p_partkey, p_name FROM part WHERE p_type LIKE '%A%' AND regexp_matches(p_name, '[aeiou]{1}')",
    ),
    "op_nested_projection": (
        lambda spark, d: interactions(spark, d).select("id", F.struct("up", "down").alias("tx")).select("id", "tx.up", "tx.down").filter("tx.up > 0"),
        s.final(s.TRANSFERS, select="SELECT id, up, down FROM tr WHERE up > 0"),
    ),
    "op_case_signed": (
        lambda spark, d: load(spark, d, "events").select("event_id", F.when(F.col("event_type").isin("error", "signup"), -F.col("value")).otherwise(F.col("value")).alias("signed")),
        "SELECT event_id, CASE WHEN event_type IN ('error', 'signup') THEN -value ELSE value END AS signed FROM events",
    ),
    "op_join_sort_merge": (
        lambda spark, d: load(spark, d, "lineitem").join(load(spark, d, "orders").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.sum(F.col("l_quantity").cast("long")).alias("q")),
        "SELECT o_custkey, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_custkey",
    ),
    "op_join_broadcast": (lambda spark, d: _chain(spark, d).select("c_custkey", "n_name", "r_name"), f"SELECT c_custkey, n_name, r_name FROM {_CHAIN}"),
    "op_join_shuffle_hash": (
        lambda spark, d: load(spark, d, "lineitem").join(load(spark, d, "part").hint("shuffle_hash"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.count(F.lit(1)).alias("n")),
        "SELECT p_brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand",
    ),
    "op_join_left": (
        lambda spark, d: load(spark, d, "customer").join(load(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n")),
        "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey",
    ),
    "op_join_full": (
        lambda spark, d: load(spark, d, "customer").filter("c_mktsegment = 'BUILDING'").join(load(spark, d, "supplier").filter("s_acctbal > 0"), F.col("c_custkey") == F.col("s_suppkey"), "full").select("c_custkey", "s_suppkey"),
        "SELECT c_custkey, s_suppkey FROM (SELECT * FROM customer WHERE c_mktsegment = 'BUILDING') FULL JOIN (SELECT * FROM supplier WHERE s_acctbal > 0) ON c_custkey = s_suppkey",
    ),
    "op_join_semi": (lambda spark, d: load(spark, d, "customer").join(load(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)"),
    "op_join_anti": (lambda spark, d: load(spark, d, "customer").join(load(spark, d, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)"),
    "op_join_cross": (lambda spark, d: load(spark, d, "nation").select("n_name").crossJoin(load(spark, d, "region").select("r_name")), "SELECT n_name, r_name FROM nation, region"),
    "op_join_theta": (
        lambda spark, d: load(spark, d, "region").alias("a").join(load(spark, d, "nation").alias("b"), F.col("a.r_regionkey") > F.col("b.n_regionkey")).select("r_name", "n_name"),
        "SELECT r_name, n_name FROM region, nation WHERE r_regionkey > n_regionkey",
    ),
    "op_join_interval": (_near, "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id < y.user_id AND abs(epoch_us(x.ts) - epoch_us(y.ts)) <= 600000000 WHERE x.event_type = 'purchase' AND y.event_type = 'purchase'"),
    "op_join_asof": (_asof, s.final(s.TRANSFERS, select="SELECT l.id, r.up AS last_up FROM (SELECT * FROM tr WHERE kind = 'error') l ASOF LEFT JOIN (SELECT * FROM tr WHERE kind <> 'error') r ON l.p = r.p AND l.ts >= r.ts")),
    "op_join_self_mutual": (lambda spark, d: (lambda g: g.alias("a").join(g.alias("b"), (F.col("a.src") == F.col("b.dst")) & (F.col("a.dst") == F.col("b.src"))).select("a.src", "a.dst").filter("src < dst"))(graph.gross_edges(interactions(spark, d))), _MUTUAL),
    "op_join_salted": (
        lambda spark, d: salted_join(load(spark, d, "lineitem").select(F.col("l_suppkey").alias("k"), "l_orderkey", "l_linenumber", "l_partkey"), load(spark, d, "supplier").select(F.col("s_suppkey").alias("k"), "s_name"), "k").groupBy("s_name").agg(F.count(F.lit(1)).alias("n")),
        "SELECT s_name, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY s_name",
    ),
    "op_agg_hash": (lambda spark, d: load(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum(F.col("l_quantity").cast("long")).alias("q"), F.count(F.lit(1)).alias("n")), "SELECT l_returnflag, l_linestatus, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q, count(*) AS n FROM lineitem GROUP BY 1, 2"),
    "op_agg_sort": (lambda spark, d: load(spark, d, "part").groupBy("p_brand").agg(F.max("p_name").alias("last_name")), "SELECT p_brand, max(p_name) AS last_name FROM part GROUP BY p_brand"),
    "op_agg_global": (lambda spark, d: load(spark, d, "events").agg(F.count(F.lit(1)).alias("n"), F.max("user_id").alias("top")), "SELECT count(*) AS n, max(user_id) AS top FROM events"),
    "op_agg_distinct": (lambda spark, d: load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")), "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1"),
    "op_agg_rollup": (lambda spark, d: _chain(spark, d).rollup("r_name", "n_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("g")), f"SELECT r_name, n_name, c_mktsegment, count(*) AS n, CAST(grouping_id(r_name, n_name, c_mktsegment) AS BIGINT) AS g FROM {_CHAIN} GROUP BY ROLLUP (r_name, n_name, c_mktsegment)"),
    "op_agg_cube": (lambda spark, d: load(spark, d, "events").withColumn("day", F.to_date("ts")).cube("event_type", "day").agg(F.count(F.lit(1)).alias("n")), "SELECT event_type, day, count(*) AS n FROM (SELECT event_type, CAST(ts AS DATE) AS day FROM events) GROUP BY CUBE (event_type, day)"),
    "op_agg_having": (lambda spark, d: load(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).filter("n > 12"), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12"),
    "op_agg_conditional": (lambda spark, d: load(spark, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "click").alias("clicks"), F.sum(F.when(F.col("value") > 100, 1).otherwise(0)).alias("large")), "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks, CAST(sum(CASE WHEN value > 100 THEN 1 ELSE 0 END) AS BIGINT) AS large FROM events GROUP BY 1"),
    "op_agg_last_state": (lambda spark, d: load(spark, d, "events").groupBy("user_id").agg(F.max_by("event_type", F.struct("ts", "event_id")).alias("last"), F.min_by("event_type", F.struct("ts", "event_id")).alias("first")), "SELECT user_id, arg_max(event_type, (ts, event_id)) AS last, arg_min(event_type, (ts, event_id)) AS first FROM events GROUP BY 1"),
    "op_agg_percentile": (lambda spark, d: load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.percentile("l_quantity", F.lit(0.5)).alias("median")), "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS median FROM lineitem GROUP BY 1"),
    "op_agg_statistics": (lambda spark, d: load(spark, d, "lineitem").agg(*[F.round(x, 6).alias(n) for n, x in (("sd", F.stddev("l_quantity")), ("var", F.var_pop("l_quantity")), ("cor", F.corr("l_quantity", "l_extendedprice")), ("slope", F.regr_slope("l_extendedprice", "l_quantity")))]), "SELECT round(stddev(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS var, round(corr(l_quantity, l_extendedprice), 6) AS cor, round(regr_slope(l_extendedprice, l_quantity), 6) AS slope FROM lineitem"),
    "op_agg_pivot": (lambda spark, d: load(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0), "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O, count(*) FILTER (WHERE o_orderstatus = 'P') AS P FROM orders GROUP BY 1"),
    "op_window_ranks": (lambda spark, d: load(spark, d, "orders").select("o_orderkey", F.row_number().over(_orders_w()).alias("rn"), F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderstatus")).alias("rk"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderstatus")).alias("dr")), f"SELECT o_orderkey, CAST(row_number() OVER {_W} AS INTEGER) AS rn, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderstatus) AS INTEGER) AS dr FROM orders"),
    "op_window_shares": (lambda spark, d: load(spark, d, "supplier").select("s_suppkey", *[F.round(x.over(Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")), 8).alias(n) for n, x in (("pr", F.percent_rank()), ("cd", F.cume_dist()))], F.ntile(3).over(Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")).alias("nt")), "SELECT s_suppkey, round(percent_rank() OVER w, 8) AS pr, round(cume_dist() OVER w, 8) AS cd, CAST(ntile(3) OVER w AS INTEGER) AS nt FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)"),
    "op_window_lag_lead": (lambda spark, d: load(spark, d, "orders").select("o_orderkey", F.lag("o_orderkey").over(_orders_w()).alias("before"), F.lead("o_orderkey", 2).over(_orders_w()).alias("after")), f"SELECT o_orderkey, lag(o_orderkey) OVER {_W} AS before, lead(o_orderkey, 2) OVER {_W} AS after FROM orders"),
    "op_window_values": (lambda spark, d: load(spark, d, "orders").select("o_orderkey", *[x.over(_orders_w().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias(n) for n, x in (("f", F.first("o_orderkey")), ("l", F.last("o_orderkey")), ("second", F.nth_value("o_orderkey", 2)))]), f"SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS second FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"),
    "op_window_running": (lambda spark, d: interactions(spark, d).select("id", F.sum("up").over(Window.partitionBy("p").orderBy("ts", "id").rowsBetween(Window.unboundedPreceding, 0)).alias("total")), s.final(s.TRANSFERS, select="SELECT id, CAST(sum(up) OVER (PARTITION BY p ORDER BY ts, id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS total FROM tr")),
    "op_window_time_range": (lambda spark, d: interactions(spark, d).select("id", F.sum("up").over(Window.partitionBy("p").orderBy(F.unix_micros("ts")).rangeBetween(-86_400_000_000, 0)).alias("day_sum")), s.final(s.TRANSFERS, select="SELECT id, CAST(sum(up) OVER (PARTITION BY p ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS BIGINT) AS day_sum FROM tr")),
    "op_window_sliding": (lambda spark, d: load(spark, d, "orders").select("o_orderkey", F.sum("o_orderkey").over(_orders_w().rowsBetween(-2, 2)).alias("five")), "SELECT o_orderkey, CAST(sum(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING) AS BIGINT) AS five FROM orders"),
    "op_sort_total": (_sorted, "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, row_number() OVER (ORDER BY l_extendedprice DESC, l_orderkey, l_linenumber, l_partkey, l_suppkey) - 1 AS place FROM lineitem"),
    "op_sort_within": (_sorted_within, "SELECT l_suppkey, count(*) - 1 AS falls FROM lineitem GROUP BY l_suppkey"),
    "op_top_k": (lambda spark, d: load(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25"),
    "op_limit_offset": (lambda spark, d: load(spark, d, "orders").orderBy("o_orderdate", "o_orderkey").offset(10).limit(15).select("o_orderkey"), "SELECT o_orderkey FROM orders ORDER BY o_orderdate, o_orderkey LIMIT 15 OFFSET 10"),
    "op_top_k_per_group": (lambda spark, d: load(spark, d, "orders").withColumn("r", F.row_number().over(Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).filter("r <= 3").select("o_custkey", "o_orderkey", "r"), "SELECT o_custkey, o_orderkey, CAST(row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS INTEGER) AS r FROM orders QUALIFY r <= 3"),
    "op_union_by_name": (lambda spark, d: _half(spark, d, _ONE).unionByName(_half(spark, d, _OTHER).select("dst", "src")), _sets("UNION ALL")),
    "op_intersect": (lambda spark, d: _half(spark, d, _ONE).intersect(_half(spark, d, _OTHER)), _sets("INTERSECT")),
    "op_except": (lambda spark, d: _half(spark, d, _ONE).subtract(_half(spark, d, _OTHER)), _sets("EXCEPT")),
    "op_except_all": (lambda spark, d: load(spark, d, "customer").select("c_nationkey").exceptAll(load(spark, d, "supplier").select(F.col("s_nationkey").alias("c_nationkey"))), "SELECT c_nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier"),
    "op_intersect_all": (lambda spark, d: load(spark, d, "customer").select("c_nationkey").intersectAll(load(spark, d, "supplier").select(F.col("s_nationkey").alias("c_nationkey"))), "SELECT c_nationkey FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier"),
    "op_distinct": (lambda spark, d: load(spark, d, "events").select("user_id", "event_type").distinct(), "SELECT DISTINCT user_id, event_type FROM events"),
    "op_exists_subquery": (
        lambda spark, d: load(spark, d, "customer").join(load(spark, d, "orders").filter("o_orderstatus = 'P'").select("o_custkey").distinct(), F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey"),
        "SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o_orderstatus = 'P')",
    ),
    "op_hash_sample": (lambda spark, d: load(spark, d, "orders").filter(u32(RNG_SEED, "smp", F.col("o_orderkey")) < int(0.1 * TWO32)).select("o_orderkey"), f"SELECT o_orderkey FROM orders WHERE {u32_sql(RNG_SEED, 'smp', 'o_orderkey')} < {int(0.1 * TWO32)}"),
    "op_time_tumbling": (lambda spark, d: load(spark, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.to_date("w.start").alias("day"), "event_type", "n"), "SELECT CAST(ts AS DATE) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
    "op_time_session": (
        lambda spark, d: load(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.unix_micros("session_window.start").alias("start_us"), "n"),
        "SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sess FROM (SELECT *, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) < 21600000000 THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, sess",
    ),
    "op_conversation_roles": (
        lambda spark, d: load(spark, d, "conversations").withColumn("next", F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn"))).filter("next IS NOT NULL").groupBy("role", "next").agg(F.count(F.lit(1)).alias("n")),
        "SELECT role, next, count(*) AS n FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS next FROM conversations) WHERE next IS NOT NULL GROUP BY 1, 2",
    ),
}

QUERIES = {k: f for k, (f, _) in OPERATORS.items()}
ORACLE_SQL = {k: q for k, (_, q) in OPERATORS.items()}
