"""Strings, hashes, dates, numbers, arrays, maps, JSON: function surface in use."""

from __future__ import annotations

from pyspark.sql import functions as F

from peertrust.functions.rng import RNG_SEED, register, u32_sql
from peertrust.schemas import PROPS
from peertrust.sources.tables import load


def _named(spark, d):
    register(spark)
    load(spark, d, "orders").createOrReplaceTempView("peertrust_orders")
    return spark.sql(f"SELECT o_orderkey, u32(concat_ws('|', '{RNG_SEED}', 'f', o_orderkey)) AS draw FROM peertrust_orders")


OPERATORS = {
    "op_strings": (
        lambda spark, d: load(spark, d, "customer").select("c_custkey", F.lower("c_name").alias("low"), F.lpad(F.col("c_custkey").cast("string"), 8, "0").alias("padded"), F.substring("c_name", 1, 4).alias("head"), F.concat_ws("-", "c_mktsegment", "c_nationkey").alias("joined"), F.translate("c_mktsegment", "AEIOU", "aeiou").alias("vowels"), F.length(F.trim("c_name")).alias("n")),
        "SELECT c_custkey, lower(c_name) AS low, lpad(CAST(c_custkey AS VARCHAR), 8, '0') AS padded, substr(c_name, 1, 4) AS head, concat_ws('-', c_mktsegment, c_nationkey) AS joined, translate(c_mktsegment, 'AEIOU', 'aeiou') AS vowels, CAST(length(trim(c_name)) AS INTEGER) AS n FROM customer",
    ),
    "op_hashes": (lambda spark, d: load(spark, d, "events").select("event_id", F.md5("props").alias("m"), F.sha2("props", 256).alias("s")), "SELECT event_id, md5(props) AS m, sha256(props) AS s FROM events"),
    "op_named_draws": (_named, f"SELECT o_orderkey, {u32_sql(RNG_SEED, 'f', 'o_orderkey')} AS draw FROM orders"),
    "op_dates": (
        lambda spark, d: load(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_diff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"), F.to_date(F.date_trunc("month", "o_orderdate")).alias("month"), F.add_months(F.to_date("o_orderdate"), 3).alias("later")),
        "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(datediff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS days, CAST(date_trunc('month', o_orderdate) AS DATE) AS month, CAST(CAST(o_orderdate AS DATE) + INTERVAL 3 MONTH AS DATE) AS later FROM orders",
    ),
    "op_intervals": (lambda spark, d: load(spark, d, "events").select("event_id", F.unix_micros((F.col("ts") + F.expr("INTERVAL 90 MINUTES")).cast("timestamp")).alias("later_us")), "SELECT event_id, epoch_us(ts + INTERVAL 90 MINUTE) AS later_us FROM events"),
    "op_math": (
        lambda spark, d: load(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", F.round(F.sqrt("l_quantity"), 8).alias("root"), F.round(F.ln(F.col("l_extendedprice") + 1), 8).alias("lg"), F.signum(F.col("l_discount") - 0.05).alias("sg"), F.greatest("l_partkey", "l_suppkey").alias("top"), F.pmod(-F.col("l_partkey"), F.lit(7)).alias("rest")),
        "SELECT l_orderkey, l_partkey, l_suppkey, round(sqrt(l_quantity), 8) AS root, round(ln(l_extendedprice + 1), 8) AS lg, CAST(sign(l_discount - 0.05::DOUBLE) AS DOUBLE) AS sg, greatest(l_partkey, l_suppkey) AS top, ((-l_partkey) % 7 + 7) % 7 AS rest FROM lineitem",
    ),
    "op_decimals": (lambda spark, d: load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("total")), "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM lineitem GROUP BY 1"),
    "op_arrays": (
        lambda spark, d: load(spark, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.element_at("embedding", 3).cast("double").alias("third"), F.size(F.slice("embedding", 5, 4)).alias("part")),
        "SELECT vec_id, CAST(len(embedding) AS INTEGER) AS n, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INTEGER) AS positive, CAST(embedding[3] AS DOUBLE) AS third, CAST(len(embedding[5:8]) AS INTEGER) AS part FROM embeddings",
    ),
    "op_json": (lambda spark, d: load(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("a"), F.from_json("props", PROPS)["k"].alias("b")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS a, CAST(json_extract_string(props, '$.k') AS BIGINT) AS b FROM events"),
    "op_maps": (
        lambda spark, d: load(spark, d, "orders").select("o_orderkey", F.explode(F.map_filter(F.create_map(F.lit("status"), "o_orderstatus", F.lit("priority"), "o_orderpriority"), lambda k, v: F.length(v) > 1)).alias("k", "v")),
        "SELECT o_orderkey, k, v FROM (SELECT o_orderkey, 'status' AS k, o_orderstatus AS v FROM orders UNION ALL SELECT o_orderkey, 'priority', o_orderpriority FROM orders) WHERE length(v) > 1",
    ),
    "op_containment": (
        lambda spark, d: load(spark, d, "documents").join(F.broadcast(load(spark, d, "benchmark").select("item_id", F.col("text").alias("passage"))), F.col("text").contains(F.col("passage"))).select("doc_id", "item_id"),
        "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    ),
}

QUERIES = {k: f for k, (f, _) in OPERATORS.items()}
ORACLE_SQL = {k: q for k, (_, q) in OPERATORS.items()}
