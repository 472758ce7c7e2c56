"""Queries on the ledger and on the graph made of it."""

from __future__ import annotations

from pyspark.sql import functions as F

from peertrust import graph, ledger
from peertrust.sources import tables as t

from . import sqltext as s

_CHAIN = """
chain AS (SELECT agent, row_number() OVER (PARTITION BY agent ORDER BY ts, id) AS seq, id, hash FROM (
  SELECT p AS agent, id, ts, sha256(concat_ws('|', id, p, q, up, down)) AS hash FROM tr UNION ALL
  SELECT q, id, ts, sha256(concat_ws('|', id, p, q, up, down)) FROM tr))"""
_LINKED = """
linked AS (SELECT *, coalesce(lag(hash) OVER (PARTITION BY agent ORDER BY seq), repeat('0', 64)) AS previous_hash, lead(id) OVER (PARTITION BY agent ORDER BY seq) AS next_id FROM chain)"""
_HALF = "(SELECT median(id) FROM tr)"


def _blocks(spark, d):
    b = ledger.build_blocks(t.interactions(spark, d))
    return b.select("id", "type", "tx.up", "tx.down", "tx.total_up", "tx.total_down", "public_key", "sequence_number", "link_public_key", "link_sequence_number", "previous_hash", "block_hash")


def _linked(spark, d):
    return ledger.link_blocks(ledger.agent_chains(t.interactions(spark, d)))


def _tampered(spark, d):
    # every 97th block of the chains has another content now
    bad = _linked(spark, d).withColumn("hash", F.when(F.col("id") % 97 == 0, F.sha2(F.concat(F.lit("x"), "hash"), 256)).otherwise(F.col("hash")))
    return ledger.audit_chain(bad)


def _doubled(spark, d):
    linked = _linked(spark, d)
    again = linked.filter("id % 101 = 0").withColumn("hash", F.sha2(F.concat(F.lit("y"), "hash"), 256))
    return linked.unionByName(again)


def _banned(spark, d):
    flagged = ledger.find_double_spends(_doubled(spark, d)).filter("seq % 7 = 0").select(F.col("agent").alias("node"))
    return graph.ban_agents(t.peer_edges(spark, d), flagged)


def _snapshots(spark, d):
    x = t.interactions(spark, d)
    half = x.agg(F.percentile("id", F.lit(0.5)).alias("half"))
    old = x.join(F.broadcast(half), how="cross").filter("id <= half").drop("half")
    return graph.net_edges(old), graph.net_edges(x)


QUERIES = {
    "ledger_blocks": _blocks,
    "ledger_chains": lambda spark, d: ledger.agent_chains(t.interactions(spark, d)),
    "ledger_links": lambda spark, d: _linked(spark, d).select("agent", "seq", "id", "previous_hash", "next_id"),
    "ledger_audit": lambda spark, d: ledger.audit_chain(_linked(spark, d)),
    "ledger_audit_tampered": _tampered,
    "ledger_double_spends": lambda spark, d: ledger.find_double_spends(_doubled(spark, d)),
    "ledger_ban": _banned,
    "ledger_interactions": lambda spark, d: t.interactions(spark, d).select("id", "p", "q", "up", "down", "kind"),
    "ledger_model_check": lambda spark, d: ledger.check_model(t.interactions(spark, d)),
    "graph_nodes": lambda spark, d: graph.nodes(t.peer_edges(spark, d)),
    "graph_net_edges": t.peer_edges,
    "graph_gross_edges": lambda spark, d: graph.gross_edges(t.interactions(spark, d)),
    "graph_net_edges_from_totals": lambda spark, d: graph.net_edges_from_totals(ledger.build_blocks(t.interactions(spark, d))),
    "graph_unweighted": lambda spark, d: graph.unweighted(t.peer_edges(spark, d)),
    "graph_diff": lambda spark, d: graph.diff_edges(*_snapshots(spark, d)),
    "graph_flip_history": lambda spark, d: graph.net_flip_history(t.interactions(spark, d)),
    "graph_profile": lambda spark, d: graph.graph_profile(t.peer_edges(spark, d)),
    "graph_relay_discounted": lambda spark, d: graph.net_edges(t.interactions(spark, d), ("view",), 0.25),
    "graph_trade_edges": t.trade_edges,
    "graph_trade_profile": lambda spark, d: graph.graph_profile(t.trade_edges(spark, d)),
    "graph_links": t.link_pairs,
    "graph_random_edges": lambda spark, d: t.random_edges(spark, d, 100),
    "graph_knn_edges": t.knn_edges,
}

_PROFILE = """
deg AS (SELECT node, sum(o) AS o, sum(i) AS i, sum(o * w) AS strength FROM (SELECT src AS node, 1 AS o, 0 AS i, w FROM edges UNION ALL SELECT dst, 0, 1, w FROM edges) GROUP BY node)"""
_PROFILE_SELECT = """SELECT count(*) AS n_nodes, CAST(sum(o) AS BIGINT) AS n_edges, CAST(sum(strength) AS BIGINT) AS weight, CAST(count(*) FILTER (WHERE o = 0) AS BIGINT) AS n_dangling,
  CAST(count(*) FILTER (WHERE i = 0) AS BIGINT) AS n_unreferenced, CAST(max(o) AS BIGINT) AS max_out, CAST(max(i) AS BIGINT) AS max_in FROM deg"""
TRADE = """
tr AS (SELECT o_custkey * 2 AS p, l_suppkey * 2 + 1 AS q, CASE WHEN l_returnflag = 'R' THEN 0 ELSE CAST(round(l_quantity * 100) AS BIGINT) END AS up,
  CASE WHEN l_returnflag = 'R' THEN CAST(round(l_quantity * 100) AS BIGINT) ELSE 0 END AS down FROM lineitem JOIN orders ON l_orderkey = o_orderkey)"""
_OLD = """
tr0 AS (SELECT * FROM tr WHERE id <= (SELECT quantile_cont(id, 0.5) FROM tr)),
pn0 AS (SELECT least(p, q) AS a, greatest(p, q) AS b, sum(CASE WHEN p < q THEN up - down ELSE down - up END) AS net FROM tr0 GROUP BY 1, 2),
old AS (SELECT CASE WHEN net > 0 THEN b ELSE a END AS src, CASE WHEN net > 0 THEN a ELSE b END AS dst, CAST(abs(net) AS BIGINT) AS w FROM pn0 WHERE net <> 0)"""
_ALL_EDGES = "SELECT src, dst, w FROM edges"
_RELAY = """
tr AS (SELECT id, p, q, CASE WHEN kind = 'view' THEN CAST(floor(up * 0.25) AS BIGINT) ELSE up END AS up, CASE WHEN kind = 'view' THEN CAST(floor(down * 0.25) AS BIGINT) ELSE down END AS down FROM tr_all)"""
_DRAW = s.u32_sql
_TAMPER = """
bad AS (SELECT agent, seq, id, previous_hash, CASE WHEN id % 97 = 0 THEN sha256('x' || hash) ELSE hash END AS hash FROM linked),
seen AS (SELECT *, seq - coalesce(lag(seq) OVER w, 0) <> 1 AS gap, previous_hash <> coalesce(lag(hash) OVER w, repeat('0', 64)) AS broken FROM bad WINDOW w AS (PARTITION BY agent ORDER BY seq, id))"""
_DOUBLE = """
dbl AS (SELECT agent, seq, hash FROM linked UNION ALL SELECT agent, seq, sha256('y' || hash) FROM linked WHERE id % 101 = 0),
spent AS (SELECT agent, seq, count(DISTINCT hash) AS n FROM dbl GROUP BY agent, seq HAVING count(DISTINCT hash) > 1)"""

KNN = """SELECT src, dst, w FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY w DESC, dst) AS r FROM (
  SELECT a.vec_id AS src, b.vec_id AS dst, CAST(round(list_dot_product(a.e, b.e) * 1000) AS BIGINT) AS w
  FROM (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) a, (SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings) b WHERE a.vec_id <> b.vec_id)) WHERE r <= 5 AND w > 0"""

ORACLE_SQL = {
    "ledger_blocks": s.final(s.TRANSFERS, _CHAIN, _LINKED, select="""
SELECT tr.id, tr.kind AS type, up, down,
  CAST(CASE WHEN p < q THEN sum(CASE WHEN p < q THEN up ELSE down END) OVER w ELSE sum(CASE WHEN p < q THEN down ELSE up END) OVER w END AS BIGINT) AS total_up,
  CAST(CASE WHEN p < q THEN sum(CASE WHEN p < q THEN down ELSE up END) OVER w ELSE sum(CASE WHEN p < q THEN up ELSE down END) OVER w END AS BIGINT) AS total_down,
  p AS public_key, a.seq AS sequence_number, q AS link_public_key, b.seq AS link_sequence_number, a.previous_hash, a.hash AS block_hash
FROM tr JOIN linked a ON a.agent = p AND a.id = tr.id JOIN linked b ON b.agent = q AND b.id = tr.id
WINDOW w AS (PARTITION BY least(p, q), greatest(p, q) ORDER BY ts, tr.id)"""),
    "ledger_chains": s.final(s.TRANSFERS, _CHAIN, select="SELECT agent, seq, id, hash FROM chain"),
    "ledger_links": s.final(s.TRANSFERS, _CHAIN, _LINKED, select="SELECT agent, seq, id, previous_hash, next_id FROM linked"),
    "ledger_audit": s.final(s.TRANSFERS, _CHAIN, _LINKED, select="SELECT agent, seq, id, true AS gap, true AS broken FROM linked WHERE false"),
    "ledger_audit_tampered": s.final(s.TRANSFERS, _CHAIN, _LINKED, _TAMPER, select="SELECT agent, seq, id, gap, broken FROM seen WHERE gap OR broken"),
    "ledger_double_spends": s.final(s.TRANSFERS, _CHAIN, _LINKED, _DOUBLE, select="SELECT agent, seq, n FROM spent"),
    "ledger_ban": s.final(s.PEER, _CHAIN, _LINKED, _DOUBLE, select="""SELECT src, dst, w FROM edges
WHERE src NOT IN (SELECT agent FROM spent WHERE seq % 7 = 0) AND dst NOT IN (SELECT agent FROM spent WHERE seq % 7 = 0)"""),
    "ledger_interactions": s.final(s.TRANSFERS, select="SELECT id, p, q, up, down, kind FROM tr"),
    "ledger_model_check": s.final(s.TRANSFERS, select="SELECT count(*) FILTER (WHERE p = q) AS selfish, count(*) FILTER (WHERE up < 0 OR down < 0) AS negative, 0::BIGINT AS disordered FROM tr"),
    "graph_nodes": s.final(s.PEER, s.nodes(), select="SELECT node FROM nodes"),
    "graph_net_edges": s.final(s.PEER, select=_ALL_EDGES),
    "graph_gross_edges": s.final(s.TRANSFERS, select="""SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT q AS src, p AS dst, up AS w FROM tr UNION ALL SELECT p, q, down FROM tr)
GROUP BY src, dst HAVING sum(w) > 0"""),
    "graph_net_edges_from_totals": s.final(s.PEER, select=_ALL_EDGES),
    "graph_unweighted": s.final(s.PEER, select="SELECT src, dst, 1::BIGINT AS w FROM edges"),
    "graph_diff": s.final(s.PEER, _OLD, select="""SELECT CASE WHEN o.w IS NULL THEN 'add' WHEN e.w IS NULL THEN 'remove' ELSE 'reweight' END AS op, src, dst, o.w AS w_old, e.w AS w_new
FROM old o FULL JOIN edges e USING (src, dst) WHERE o.w IS DISTINCT FROM e.w"""),
    "graph_flip_history": s.final(s.TRANSFERS, select="""SELECT a, b, id, net, coalesce(sign(lag(net) OVER (PARTITION BY a, b ORDER BY ts, id)), 0) * sign(net) < 0 AS flipped FROM (
  SELECT least(p, q) AS a, greatest(p, q) AS b, id, ts, CAST(sum(CASE WHEN p < q THEN up - down ELSE down - up END) OVER (PARTITION BY least(p, q), greatest(p, q) ORDER BY ts, id) AS BIGINT) AS net FROM tr)"""),
    "graph_profile": s.final(s.PEER, _PROFILE, select=_PROFILE_SELECT),
    "graph_relay_discounted": s.final(s.TRANSFERS.replace("tr AS", "tr_all AS"), _RELAY, s.PAIRS, s.EDGES, select=_ALL_EDGES),
    "graph_trade_edges": s.final(TRADE, s.PAIRS, s.EDGES, select=_ALL_EDGES),
    "graph_trade_profile": s.final(TRADE, s.PAIRS, s.EDGES, _PROFILE, select=_PROFILE_SELECT),
    "graph_links": """SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, target, count(*) AS n FROM (SELECT url, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS target FROM pages) GROUP BY 1, 2""",
    "graph_random_edges": s.final(f"""
drawn AS (SELECT c_custkey - 1 AS src, {_DRAW(42, 'rd', 'c_custkey - 1', 'i.range')} % 100 AS dst, {_DRAW(42, 'rw', 'c_custkey - 1', 'i.range')} % 10 + 1 AS w FROM customer, range(1, 3) i WHERE c_custkey BETWEEN 1 AND 100)""",
        select="SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM drawn WHERE src <> dst GROUP BY src, dst"),
    "graph_knn_edges": KNN,
}
