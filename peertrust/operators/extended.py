"""Sources and sinks, Python functions, table functions, lateral joins and streams."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from peertrust import metrics
from peertrust.functions import extended as fx
from peertrust.functions.rng import RNG_SEED, register, u32_sql
from peertrust.queries import sqltext as s
from peertrust.sources import files
from peertrust.sources.tables import load, peer_edges, scratch
from peertrust.streaming import operators as st
from peertrust.streaming.trust import ledger_files, pair_nets_by_batch, stream_events, transfers_of


def _by_day(spark, d):
    path = scratch(spark, "by-day")
    files.write_by_day(load(spark, d, "events"), "ts", path)
    days = load(spark, d, "events").agg(F.min(F.to_date("ts")).alias("a")).first()[0]
    return files.read_days(spark, path, str(days), str(days)).select("event_id", "day")


def _bucketed(spark, d):
    # a name of its own: folders of earlier sessions may still be in the warehouse
    table = files.save_bucketed(peer_edges(spark, d), f"peertrust_edges_{uuid.uuid4().hex[:12]}")
    return table.groupBy("src").agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("n"))


def _approx(spark, d):
    return load(spark, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.02).alias("users"))


def _reviews(spark, d):
    return load(spark, d, "documents").join(load(spark, d, "labels"), "doc_id").select("lang", F.col("doc_id").alias("node"), (F.col("quality") == 1).alias("is_honest"), F.col("n_chars").cast("double").alias("score"))


def _roc_table(spark, d):
    _reviews(spark, d).createOrReplaceTempView("peertrust_reviews")
    spark.udtf.register("roc_points", fx.RocPoints)
    return spark.sql("SELECT node, cut, round(fpr, 8) AS fpr, round(tpr, 8) AS tpr FROM roc_points(TABLE(peertrust_reviews) PARTITION BY lang)")


def _walk_table(spark, d):
    fx.register_walk(spark, peer_edges(spark, d), "peertrust_walk")
    return spark.sql("SELECT r.id AS walk_id, w.step, w.node FROM range(60) r, LATERAL peertrust_walk(CAST(0 AS BIGINT), r.id, CAST(0.3 AS DOUBLE)) w")


def _front_end(spark, d):
    register(spark)
    peer_edges(spark, d).createOrReplaceTempView("peertrust_edges")
    return spark.sql("WITH law AS (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS p FROM peertrust_edges) SELECT dst AS node, round(sum(p), 8) AS inflow FROM law GROUP BY dst")


def _lateral(spark, d):
    peer_edges(spark, d).createOrReplaceTempView("peertrust_edges")
    return spark.sql("SELECT n.src, b.dst, b.w FROM (SELECT DISTINCT src FROM peertrust_edges) n, LATERAL (SELECT dst, w FROM peertrust_edges e WHERE e.src = n.src ORDER BY w DESC, dst LIMIT 3) b")


def _near_sources(spark, d):
    """Pairs of sources by how many different lines of 12 words or more they share.  A
    line meets its sources as one set, so a hot line is one row; the sets are counted
    before they are taken apart, and there are few sources."""
    lines = load(spark, d, "documents").select("source", F.explode(F.split("text", "\n")).alias("line")).filter(F.size(F.split("line", " ")) >= 12)
    sets = lines.groupBy(F.xxhash64("line").alias("h"), F.md5("line").alias("m")).agg(F.array_sort(F.collect_set("source")).alias("s")).filter(F.size("s") > 1)
    counted = sets.groupBy("s").agg(F.count(F.lit(1)).alias("n"))
    pairs = counted.select("n", "s", F.posexplode("s").alias("i", "a")).select("n", "a", F.explode(F.slice("s", F.col("i") + 2, F.size("s"))).alias("b"))
    return pairs.groupBy("a", "b").agg(F.sum("n").alias("n"))


_PARTS = 6


def _flips(spark, d):
    """Pairs whose net turned its sign, from the state of a stream fed in six parts."""
    path = scratch(spark, "ledger-parts")
    ledger_files(load(spark, d, "events"), path, "volume", _PARTS)
    n = load(spark, d, "events").select("user_id").distinct().count()
    return pair_nets_by_batch(transfers_of(stream_events(spark, path, "*.parquet"), n)).select("a", "b", "net", "flipped")


def _jdbc(spark, d):
    """Where no database driver is on the class path, the reader's own error."""
    try:
        return files.scan_jdbc(spark, "jdbc:sqlite:/nowhere.db", "blocks", "sequence_number", 0, 100, 4).limit(0).select(F.lit("read").alias("outcome"))
    except Exception as e:
        return spark.createDataFrame([("no driver" if "river" in str(e) else "failed",)], "outcome string")


_DAY = "SELECT CAST(ts AS DATE) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2"
_SAME = "SELECT n_nationkey, n_name, n_regionkey FROM nation"

OPERATORS = {
    **{f"op_round_trip_{k}": (lambda spark, d, k=k: files.write_read(load(spark, d, "nation"), k), _SAME) for k in files.FORMATS},
    "op_partitioned_by_day": (_by_day, "SELECT event_id, CAST(ts AS DATE) AS day FROM events WHERE CAST(ts AS DATE) = (SELECT min(CAST(ts AS DATE)) FROM events)"),
    "op_bucketed_edges": (_bucketed, s.final(s.PEER, select="SELECT src, CAST(sum(w) AS BIGINT) AS w, count(*) AS n FROM edges GROUP BY src")),
    "op_agg_approx_distinct": (_approx, None),
    "op_agg_grouping_sets": (
        lambda spark, d: load(spark, d, "lineitem").groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")),
        "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    ),
    "op_unpivot": (
        lambda spark, d: load(spark, d, "part").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "what", "value"),
        "SELECT p_partkey, 'size' AS what, CAST(p_size AS DOUBLE) AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part",
    ),
    "op_time_sliding": (
        lambda spark, d: load(spark, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 day", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.unix_micros("w.start").alias("start_us"), "n"),
        "SELECT start_us, count(*) AS n FROM (SELECT (epoch_us(ts) // 21600000000 - i.range) * 21600000000 AS start_us FROM events, range(4) i) GROUP BY 1",
    ),
    "op_pandas_scalar": (lambda spark, d: load(spark, d, "orders").select("o_orderkey", fx.u32_udf(F.concat_ws("|", F.lit(RNG_SEED), F.lit("pd"), "o_orderkey")).alias("draw")), f"SELECT o_orderkey, {u32_sql(RNG_SEED, 'pd', 'o_orderkey')} AS draw FROM orders"),
    "op_pandas_aggregate": (
        lambda spark, d: _reviews(spark, d).groupBy("lang").agg(F.round(fx.auroc_udaf("score", "is_honest"), 8).alias("auroc")),
        "SELECT lang, round(sum(CASE WHEN a.s > b.s THEN 1.0 WHEN a.s = b.s THEN 0.5 ELSE 0 END) / count(*), 8)::DOUBLE AS auroc FROM (SELECT lang, n_chars AS s FROM documents JOIN labels USING (doc_id) WHERE quality = 1) a JOIN (SELECT lang, n_chars AS s FROM documents JOIN labels USING (doc_id) WHERE quality <> 1) b USING (lang) GROUP BY lang",
    ),
    "op_pandas_kendall": (lambda spark, d: load(spark, d, "part").groupBy("p_brand").agg(F.round(fx.kendall_udaf("p_size", "p_retailprice"), 8).alias("tau")), "SELECT p_brand, round(sum(x * y) / sqrt(sum(x * x) * sum(y * y)), 8) AS tau FROM (SELECT a.p_brand, sign(a.p_size - b.p_size)::DOUBLE AS x, sign(a.p_retailprice - b.p_retailprice)::DOUBLE AS y FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey) GROUP BY p_brand"),
    "op_auroc_by_group": (lambda spark, d: metrics.auroc(_reviews(spark, d), ["lang"]).withColumn("auroc", F.round("auroc", 8)), "SELECT lang, round(sum(CASE WHEN a.s > b.s THEN 1.0 WHEN a.s = b.s THEN 0.5 ELSE 0 END) / count(*), 8)::DOUBLE AS auroc FROM (SELECT lang, n_chars AS s FROM documents JOIN labels USING (doc_id) WHERE quality = 1) a JOIN (SELECT lang, n_chars AS s FROM documents JOIN labels USING (doc_id) WHERE quality <> 1) b USING (lang) GROUP BY lang"),
    "op_table_function_roc": (
        _roc_table,
        "SELECT node, row_number() OVER w AS cut, round(sum(CASE WHEN h THEN 0 ELSE 1 END) OVER w / nullif(count(*) FILTER (WHERE NOT h) OVER (PARTITION BY lang), 0), 8) AS fpr, round(sum(CASE WHEN h THEN 1 ELSE 0 END) OVER w / nullif(count(*) FILTER (WHERE h) OVER (PARTITION BY lang), 0), 8) AS tpr FROM (SELECT lang, doc_id AS node, quality = 1 AS h, n_chars AS s FROM documents JOIN labels USING (doc_id)) WINDOW w AS (PARTITION BY lang ORDER BY s DESC, node)",
    ),
    "op_table_function_walk": (_walk_table, s.final(s.PEER, s.cdf(), s.starts([0], 60), s.walk(0.3), select="SELECT walk_id, step, node FROM walk")),
    "op_sql_front_end": (_front_end, s.final(s.PEER, select="SELECT dst AS node, round(sum(p), 8) AS inflow FROM (SELECT dst, w / sum(w) OVER (PARTITION BY src) AS p FROM edges) GROUP BY dst")),
    "op_lateral_best_partners": (_lateral, s.final(s.PEER, select="SELECT src, dst, w FROM edges QUALIFY row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) <= 3")),
    "op_near_sources": (
        _near_sources,
        "WITH l AS (SELECT DISTINCT source, line FROM (SELECT source, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE len(string_split(line, ' ')) >= 12) SELECT x.source AS a, y.source AS b, count(*) AS n FROM l x JOIN l y ON x.line = y.line AND x.source < y.source GROUP BY 1, 2",
    ),
    "op_stream_complete": (lambda spark, d: st.drain(stream_events(spark, d).groupBy(F.to_date("ts").alias("day"), "event_type").agg(F.count(F.lit(1)).alias("n")), "complete"), _DAY),
    "op_stream_update": (lambda spark, d: st.drain(stream_events(spark, d).groupBy(F.to_date("ts").alias("day"), "event_type").agg(F.count(F.lit(1)).alias("n")), "update", keys=["day", "event_type"]), _DAY),
    "op_stream_state": (_flips, s.final(s.TRANSFERS, f"""
evb AS (SELECT event_id AS id, (row_number() OVER (ORDER BY ts, event_id) - 1) // (SELECT CAST(ceil(count(*) / {_PARTS}) AS BIGINT) FROM events) AS part FROM events)""", select="""SELECT a, b, net, coalesce(lag(net) OVER w, 0) * net < 0 AS flipped FROM (
  SELECT a, b, part, CAST(sum(g) OVER (PARTITION BY a, b ORDER BY part) AS BIGINT) AS net FROM (
    SELECT least(p, q) AS a, greatest(p, q) AS b, part, sum(CASE WHEN p < q THEN up - down ELSE down - up END) AS g FROM tr JOIN evb USING (id) GROUP BY 1, 2, 3)) WINDOW w AS (PARTITION BY a, b ORDER BY part)""")),
    # a day comes out once the watermark, an hour behind the last event, has passed its end
    "op_stream_watermark": (lambda spark, d: st.drain(st.daily_counts(stream_events(spark, d))), f"SELECT * FROM ({_DAY}) WHERE day + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)"),
    "op_scan_jdbc": (_jdbc, "SELECT 'no driver' AS outcome"),
    "op_stream_dedup": (lambda spark, d: st.drain(st.without_duplicates(stream_events(spark, d)).select("event_id", "user_id")), "SELECT event_id, user_id FROM events"),
    "op_stream_static_join": (lambda spark, d: st.drain(st.with_static(stream_events(spark, d), load(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").select("event_id", "c_mktsegment")), "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey"),
    "op_stream_stream_join": (
        lambda spark, d: st.drain(st.halves(stream_events(spark, d))),
        "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts >= x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTE WHERE x.event_type = 'click' AND y.event_type = 'purchase'",
    ),
}

QUERIES = {k: f for k, (f, _) in OPERATORS.items()}
ORACLE_SQL = {k: q for k, (_, q) in OPERATORS.items() if q}
