"""Queries on the mechanisms that came before, and on batches of a ledger."""

from __future__ import annotations

from pyspark.sql import functions as F

from peertrust import baselines, graph, metrics
from peertrust.functions.rng import RNG_SEED, u32_sql
from peertrust.sources import tables as t
from peertrust.streaming import trust

from . import sqltext as s

def _random_auroc(spark, d):
    """A hash-random ranking of the customers, those in debt being the others: near 1/2."""
    own = t.load(spark, d, "customer").select(F.col("c_custkey").alias("node"), (F.col("c_acctbal") >= 0).alias("is_honest"))
    return metrics.auroc(metrics.labelled(baselines.random_rank(own), own)).withColumn("auroc", F.round("auroc", 8))


QUERIES = {
    "baseline_tit_for_tat": lambda spark, d: baselines.tit_for_tat(t.interactions(spark, d)),
    "baseline_net_contribution": lambda spark, d: baselines.net_contribution(t.interactions(spark, d)),
    "baseline_reported_contribution": lambda spark, d: baselines.reported_contribution(t.interactions(spark, d)),
    "baseline_drop_interested": lambda spark, d: baselines.drop_interested(t.peer_edges(spark, d), 0),
    "baseline_review_average": lambda spark, d: baselines.review_average(t.load(spark, d, "documents"), t.load(spark, d, "labels")),
    "baseline_random_rank": lambda spark, d: baselines.random_rank(graph.nodes(t.peer_edges(spark, d))),
    "baseline_random_auroc": _random_auroc,
    "baseline_pair_game": lambda spark, d: baselines.pair_game(t.interactions(spark, d)),
    "batches_by_time": lambda spark, d: trust.batches(t.interactions(spark, d), "time").groupBy("batch").agg(F.count(F.lit(1)).alias("n"), F.sum("up").alias("up")),
    "batches_by_volume": lambda spark, d: trust.batches(t.interactions(spark, d), "volume", 1_000).groupBy("batch").agg(F.count(F.lit(1)).alias("n"), F.sum("up").alias("up")),
}

_SIDES = """
sides AS (SELECT p AS peer, q AS partner, up AS given, down AS taken, ts, id FROM tr UNION ALL SELECT q, p, down, up, ts, id FROM tr)"""
_DAILY = """
daily AS (SELECT *, row_number() OVER (PARTITION BY day, peer ORDER BY got DESC, partner) AS r FROM (SELECT CAST(ts AS DATE) AS day, peer, partner, CAST(sum(taken) AS BIGINT) AS got FROM sides GROUP BY 1, 2, 3))"""
_DRAW = u32_sql(RNG_SEED, "unchoke", "day", "peer", "partner")

ORACLE_SQL = {
    "baseline_tit_for_tat": s.final(s.TRANSFERS, _SIDES, _DAILY, select=f"""SELECT day, peer, partner, 'earned' AS slot FROM daily WHERE r < 4 AND got > 0
UNION ALL SELECT day, peer, partner, 'free' FROM (SELECT *, row_number() OVER (PARTITION BY day, peer ORDER BY {_DRAW}, partner) AS f FROM daily WHERE r >= 4 OR got <= 0) WHERE f = 1"""),
    "baseline_net_contribution": s.final(s.TRANSFERS, _SIDES, select="SELECT peer AS node, CAST(sum(given) - sum(taken) AS BIGINT) AS score, sum(given) < sum(taken) AS free_rider FROM sides GROUP BY peer"),
    "baseline_reported_contribution": s.final(s.TRANSFERS, _SIDES, select="SELECT peer AS node, CAST(sum(given) * CASE WHEN peer % 5 = 0 THEN 10 ELSE 1 END - sum(taken) AS BIGINT) AS score FROM sides GROUP BY peer"),
    "baseline_drop_interested": s.final(s.PEER, select="SELECT src, dst, w FROM edges WHERE src NOT IN (SELECT src FROM edges WHERE dst = 0) AND dst NOT IN (SELECT src FROM edges WHERE dst = 0)"),
    "baseline_review_average": "SELECT source, count(quality) AS reviews, avg(quality) AS score FROM documents JOIN labels USING (doc_id) GROUP BY source",
    "baseline_random_rank": s.final(s.PEER, s.nodes(), select=f"SELECT node, CAST({u32_sql(RNG_SEED, 'rank', 'node')} AS DOUBLE) AS score FROM nodes"),
    "baseline_random_auroc": f"""SELECT round((sum(r) FILTER (WHERE h) - count(*) FILTER (WHERE h) * (count(*) FILTER (WHERE h) + 1) / 2) / (count(*) FILTER (WHERE h) * count(*) FILTER (WHERE NOT h)), 8)::DOUBLE AS auroc
FROM (SELECT h, rank() OVER (ORDER BY x) + (count(*) OVER (PARTITION BY x) - 1) / 2 AS r FROM (SELECT c_acctbal >= 0 AS h, {u32_sql(RNG_SEED, 'rank', 'c_custkey')} AS x FROM customer))""",
    "baseline_pair_game": s.final(s.TRANSFERS, """
rounds AS (SELECT up > 0 AS coop, coalesce(lag(up > 0) OVER (PARTITION BY least(p, q), greatest(p, q) ORDER BY ts, id), true) AS before FROM tr)""", select="""
SELECT policy, count(*) AS rounds, CAST(sum(CASE WHEN mine AND coop THEN 3 WHEN mine THEN 0 WHEN coop THEN 5 ELSE 1 END) AS BIGINT) AS payoff FROM (
  SELECT 'cooperate' AS policy, true AS mine, coop FROM rounds UNION ALL SELECT 'defect', false, coop FROM rounds UNION ALL SELECT 'reciprocate', before, coop FROM rounds) GROUP BY policy"""),
    "batches_by_time": s.final(s.TRANSFERS, select="SELECT CAST(datediff('day', (SELECT min(CAST(ts AS DATE)) FROM tr), CAST(ts AS DATE)) AS BIGINT) AS batch, count(*) AS n, CAST(sum(up) AS BIGINT) AS up FROM tr GROUP BY 1"),
    "batches_by_volume": s.final(s.TRANSFERS, select="SELECT CAST((r - 1) // 1000 AS BIGINT) AS batch, count(*) AS n, CAST(sum(up) AS BIGINT) AS up FROM (SELECT *, row_number() OVER (ORDER BY ts, id) AS r FROM tr) GROUP BY 1"),
}
