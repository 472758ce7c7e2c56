"""Queries on sybil regions and detection measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from peertrust import metrics, power, sybil
from peertrust.functions.rng import RNG_SEED, u32_sql
from peertrust.sources import tables as t

from . import sqltext as s

CELLS = ((0, 0.3), (50, 0.3), (50, 0.5))
R = 200
#: Reset probability and rounds of the scores that tell communities apart.
FAR, FAR_ROUNDS = 0.02, 300


def _cells(spark, d):
    edges, extra, labels, h = sybil.build(spark, d, 50)
    return t.cut(sybil.scenario_walks(edges, extra, list(CELLS), R)), labels, h


def _curve(spark, d, **options):
    w, labels, _ = _cells(spark, d)
    return metrics.roc(metrics.labelled(sybil.scenario_scores(w), labels, by=["attack", "alpha"]), ["attack", "alpha"], **options)


def _measures(drop):
    def run(spark, d):
        w, labels, h = _cells(spark, d)
        out = sybil.evaluate(w, labels, h, drop)
        return out.select("attack", "alpha", *[F.round(c, 8).alias(c) for c in ("auroc", "fp_mean", "fn_mean", "fp_at", "fn_at")])

    return run


def _one_cell(spark, d):
    w, labels, _ = _cells(spark, d)
    return w.filter((F.col("attack") == 50) & (F.col("alpha") == 0.3)), labels


def _attacked(spark, d):
    """The graph of one cell as a whole, its walks, and its attack edges."""
    edges, extra, _, _ = sybil.build(spark, d, 50)
    extra = extra.filter("i <= 50")
    both = t.cut(edges.union(extra.select("src", "dst", "w")).groupBy("src", "dst").agg(F.sum("w").alias("w")))
    w = t.cut(sybil.scenario_walks(edges, extra, [(50, 0.3)], R).select("walk_id", "step", "node"))
    return both, w, extra


def _suspects(spark, d):
    edges, w, extra = _attacked(spark, d)
    return t.cut(sybil.suspect_edges(w, sybil.settled(sybil.community(*_scored(edges)), edges, 0))), w, edges, extra


def _scored(edges):
    """Trust of far-reaching walks that go along edges and against them: it stays in the
    seed's own community for long."""
    return t.cut(power.power_iteration(sybil.both_ways(edges), 0, FAR, rounds=FAR_ROUNDS)), edges


def _review_rows(spark, d):
    docs, labels = t.load(spark, d, "documents"), t.load(spark, d, "labels")
    return docs.join(labels, "doc_id").select(F.col("doc_id").alias("node"), (F.col("quality") == 1).alias("is_honest"), F.col("n_chars").cast("double").alias("score"))


QUERIES = {
    "sybil_honest_region": lambda spark, d: sybil.honest_region(t.load(spark, d, "orders")),
    "sybil_region": lambda spark, d: sybil.sybil_region(t.load(spark, d, "customer")),
    "sybil_attack_edges": lambda spark, d: sybil.attack_edges(spark, 500, numbers=t.load(spark, d, "orders").select((F.col("o_orderkey") + 0).alias("i"))),
    "sybil_walk_scores": lambda spark, d: sybil.scenario_scores(_cells(spark, d)[0]).withColumn("score", F.round("score", 8)),
    "sybil_roc": lambda spark, d: _curve(spark, d).select("attack", "alpha", "cut", "node", F.round("fpr", 8).alias("fpr"), F.round("tpr", 8).alias("tpr")),
    "sybil_roc_blocks": lambda spark, d: _curve(spark, d, ties="block").select("attack", "alpha", "cut", F.round("fpr", 8).alias("fpr"), F.round("tpr", 8).alias("tpr")),
    "sybil_measures": _measures(False),
    "sybil_measures_visited": _measures(True),
    "sybil_auroc_trapezoid": lambda spark, d: metrics.auroc_trapezoid(_curve(spark, d), ["attack", "alpha"]).withColumn("auroc", F.round("auroc", 8)),
    "sybil_region_flow": lambda spark, d: metrics.region_flow(*_one_cell(spark, d)),
    "sybil_sweep": lambda spark, d: sybil.sweep(*_scored(_attacked(spark, d)[0])).withColumn("conductance", F.round("conductance", 8)),
    "sybil_suspect_edges": lambda spark, d: _suspects(spark, d)[0],
    "sybil_suspect_quality": lambda spark, d: sybil.detection_quality(*_suspects(spark, d)).withColumn("auroc", F.round("auroc", 8)),
    "sybil_cap_seed_share": lambda spark, d: sybil.cap_seed_share(t.peer_edges(spark, d), 0, 0.05),
    "detection_review_roc": lambda spark, d: metrics.roc(_review_rows(spark, d)).select("cut", "node", F.round("fpr", 8).alias("fpr"), F.round("tpr", 8).alias("tpr")),
    "detection_review_auroc": lambda spark, d: metrics.auroc(_review_rows(spark, d)).withColumn("auroc", F.round("auroc", 8)),
    "detection_review_cuts": lambda spark, d: metrics.cut_table(metrics.roc(_review_rows(spark, d))).select("cut", *[F.round(c, 8).alias(c) for c in ("sensitivity", "specificity", "youden")]),
    "detection_review_rates": lambda spark, d: metrics.error_rates(metrics.roc(_review_rows(spark, d)), 100).select(*[F.round(c, 8).alias(c) for c in ("fp_mean", "fn_mean", "fp_at", "fn_at")]),
}

_D = lambda tag, *p: u32_sql(RNG_SEED, tag, *p)
# sizes of the scale that the SQL runs at
_H, _E, _S = 500, 2000, 1000
_HONEST = f"""
honest AS (SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT {_D('hs', 'o_orderkey - 1')} % {_H} AS src, {_D('hd', 'o_orderkey - 1')} % {_H} AS dst, {_D('hw', 'o_orderkey - 1')} % 10 + 1 AS w
  FROM orders WHERE o_orderkey BETWEEN 1 AND {_E}) WHERE src <> dst GROUP BY 1, 2)"""
_SYBIL = f"""
syb AS (SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT c_custkey - 1 + {_H} AS src, {_D('sd', 'c_custkey - 1', 'j.range')} % {_S} + {_H} AS dst, {_D('sw', 'c_custkey - 1', 'j.range')} % 10 + 1 AS w
  FROM customer, range(1, 11) j WHERE c_custkey BETWEEN 1 AND {_S}) WHERE src <> dst GROUP BY 1, 2)"""
_ATTACK = f"""
pairs AS (SELECT i.range AS i, CASE WHEN i.range % 50 = 5 THEN 0 ELSE {_D('ah', 'i.range')} % {_H} END AS h, {_D('as', 'i.range')} % {_S} + {_H} AS s, {_D('aw', 'i.range')} % 10 + 1 AS w FROM range(1, 501) i),
attack AS (SELECT i, h AS src, s AS dst, w FROM pairs UNION ALL SELECT i, s, h, w FROM pairs)"""


def _cell(k, attack, alpha):
    return (
        f"""
e{k} AS (SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT src, dst, w FROM honest UNION ALL SELECT src, dst, w FROM syb UNION ALL SELECT src, dst, w FROM attack WHERE i <= {attack}) GROUP BY 1, 2)""",
        s.cdf(f"e{k}", f"cdf{k}"),
        s.walk(alpha, table=f"cdf{k}", name=f"walk{k}"),
    )


_BASE = (_HONEST, _SYBIL, _ATTACK, s.starts([0], R), *(x for k, (a, p) in enumerate(CELLS) for x in _cell(k, a, p)))
_SCORES = "\nsc AS (" + " UNION ALL ".join(f"SELECT {a}::BIGINT AS attack, {p}::DOUBLE AS alpha, node, count(*) / (SELECT count(*) FROM walk{k}) AS score FROM walk{k} GROUP BY node" for k, (a, p) in enumerate(CELLS)) + ")"
_LABELLED = f"""
cells AS (SELECT DISTINCT attack, alpha FROM sc),
lab AS (SELECT c.attack, c.alpha, r.range AS node, r.range < {_H} AS is_honest, coalesce(sc.score, 0) AS score FROM cells c CROSS JOIN range({_H + _S}) r LEFT JOIN sc ON sc.attack = c.attack AND sc.alpha = c.alpha AND sc.node = r.range)"""


def _roc(source="lab", by="attack, alpha"):
    part = f"PARTITION BY {by}" if by else ""
    lead = f"{by}, " if by else ""
    return f"""
roc AS (SELECT {lead}node, score, is_honest, row_number() OVER ({part} ORDER BY score DESC, node) AS cut,
  sum(CASE WHEN is_honest THEN 0 ELSE 1 END) OVER ({part} ORDER BY score DESC, node) / nullif(count(*) FILTER (WHERE NOT is_honest) OVER ({part}), 0) AS fpr,
  sum(CASE WHEN is_honest THEN 1 ELSE 0 END) OVER ({part} ORDER BY score DESC, node) / nullif(count(*) FILTER (WHERE is_honest) OVER ({part}), 0) AS tpr FROM {source})"""


_VISITED = "\nvis AS (SELECT * FROM lab WHERE score > 0)"


def _measure_sql(source):
    """The area as the share of won comparisons, counted pair by pair."""
    return f"""
wins AS (SELECT a.attack, a.alpha, sum(CASE WHEN a.score > b.score THEN 1.0 WHEN a.score = b.score THEN 0.5 ELSE 0 END) / count(*) AS auroc
  FROM {source} a JOIN {source} b ON a.attack = b.attack AND a.alpha = b.alpha AND a.is_honest AND NOT b.is_honest GROUP BY 1, 2)"""


_MEASURE_SELECT = f"""SELECT r.attack, r.alpha, round(any_value(w.auroc), 8)::DOUBLE AS auroc, round(avg(fpr), 8) AS fp_mean, round(avg(1 - tpr), 8) AS fn_mean,
round(max(fpr) FILTER (WHERE cut = {_H}), 8) AS fp_at, round(max(1 - tpr) FILTER (WHERE cut = {_H}), 8) AS fn_at FROM roc r LEFT JOIN wins w ON w.attack = r.attack AND w.alpha = r.alpha GROUP BY r.attack, r.alpha"""
_REVIEW = """
lab AS (SELECT doc_id AS node, quality = 1 AS is_honest, CAST(n_chars AS DOUBLE) AS score FROM documents JOIN labels USING (doc_id))"""
_FLOW = f"""
hops AS (SELECT *, node < {_H} AS h, lead(node) OVER (PARTITION BY walk_id ORDER BY step) AS next FROM walk1)"""

_SWEEP = f"""
u1 AS (SELECT src, dst, CAST(sum(w) AS BIGINT) AS w FROM (SELECT src, dst, w FROM e1 UNION ALL SELECT dst, src, w FROM e1) GROUP BY 1, 2),{s.nodes("e1", "nodes1", extra=0)},{s.power(FAR, FAR_ROUNDS, 0, edges="u1", node_table="nodes1", name="pw")},
deg AS (SELECT node, CAST(sum(w) AS BIGINT) AS d FROM (SELECT src AS node, w FROM e1 UNION ALL SELECT dst, w FROM e1) GROUP BY node),
ranked AS (SELECT row_number() OVER (ORDER BY round(x.score / d, 12) DESC, node) AS place, node, d FROM pw x JOIN deg USING (node) WHERE k = {FAR_ROUNDS} AND x.score > 0),
placed AS (SELECT e.w, a.place AS pa, b.place AS pb FROM e1 e LEFT JOIN ranked a ON a.node = e.src LEFT JOIN ranked b ON b.node = e.dst),
sums AS (SELECT r.place, r.node, CAST(sum(r.d) OVER (ORDER BY r.place) AS BIGINT) AS volume,
  (SELECT CAST(coalesce(sum(w), 0) AS BIGINT) FROM placed p WHERE (coalesce(p.pa, 1000000) <= r.place) <> (coalesce(p.pb, 1000000) <= r.place)) AS cut FROM ranked r),
swept AS (SELECT *, cut / nullif(least(volume, (SELECT CAST(sum(d) AS BIGINT) FROM deg) - volume), 0) AS conductance FROM sums)"""
_SUSPECTS = """
best AS (SELECT place FROM swept WHERE volume <= 0.5 * (SELECT sum(d) FROM deg) ORDER BY conductance, place LIMIT 1),
own0 AS (SELECT node FROM swept WHERE place <= (SELECT place FROM best)),
own1 AS (SELECT 0 AS node UNION SELECT u.src AS node FROM u1 u LEFT JOIN own0 o ON o.node = u.dst GROUP BY u.src HAVING sum(CASE WHEN o.node IS NULL THEN -u.w ELSE u.w END) > 0),
own AS (SELECT 0 AS node UNION SELECT u.src AS node FROM u1 u LEFT JOIN own1 o ON o.node = u.dst GROUP BY u.src HAVING sum(CASE WHEN o.node IS NULL THEN -u.w ELSE u.w END) > 0),
steps AS (SELECT node AS src, lead(node) OVER (PARTITION BY walk_id ORDER BY step) AS dst FROM walk1),
crossed AS (SELECT src, dst, count(*) AS crossings FROM steps WHERE dst IS NOT NULL GROUP BY 1, 2),
suspects AS (SELECT * FROM crossed WHERE (src IN (SELECT node FROM own)) <> (dst IN (SELECT node FROM own)))"""

ORACLE_SQL = {
    "sybil_honest_region": s.final(_HONEST, select="SELECT src, dst, w FROM honest"),
    "sybil_region": s.final(_SYBIL, select="SELECT src, dst, w FROM syb"),
    "sybil_attack_edges": s.final(_ATTACK.replace("FROM range(1, 501) i", "FROM (SELECT o_orderkey AS range FROM orders WHERE o_orderkey BETWEEN 1 AND 500) i"), select="SELECT i, src, dst, w FROM attack"),
    "sybil_walk_scores": s.final(*_BASE, _SCORES, select="SELECT attack, alpha, node, round(score, 8) AS score FROM sc"),
    "sybil_roc": s.final(*_BASE, _SCORES, _LABELLED, _roc(), select="SELECT attack, alpha, cut, node, round(fpr, 8) AS fpr, round(tpr, 8) AS tpr FROM roc"),
    "sybil_roc_blocks": s.final(*_BASE, _SCORES, _LABELLED, _roc(), select="SELECT attack, alpha, max(cut) AS cut, round(max(fpr), 8) AS fpr, round(max(tpr), 8) AS tpr FROM roc GROUP BY attack, alpha, score"),
    "sybil_measures": s.final(*_BASE, _SCORES, _LABELLED, _roc(), _measure_sql("lab"), select=_MEASURE_SELECT),
    "sybil_measures_visited": s.final(*_BASE, _SCORES, _LABELLED, _VISITED, _roc("vis"), _measure_sql("vis"), select=_MEASURE_SELECT),
    "sybil_auroc_trapezoid": s.final(*_BASE, _SCORES, _LABELLED, _roc(), select="""SELECT attack, alpha, round(sum(area), 8) AS auroc FROM (
  SELECT attack, alpha, (fpr - coalesce(lag(fpr) OVER w, 0)) * (tpr + coalesce(lag(tpr) OVER w, 0)) / 2 AS area FROM roc WINDOW w AS (PARTITION BY attack, alpha ORDER BY cut)) GROUP BY attack, alpha"""),
    "sybil_region_flow": s.final(*_BASE, _FLOW, select=f"""SELECT count(*) FILTER (WHERE h) AS honest_visits, count(*) FILTER (WHERE NOT h) AS sybil_visits, count(*) FILTER (WHERE h AND next >= {_H}) AS entries,
count(*) FILTER (WHERE NOT h AND next < {_H}) AS escapes, count(DISTINCT node) AS nodes_seen FROM hops"""),
    "sybil_sweep": s.final(*_BASE, _SWEEP, select="SELECT place, node, volume, cut, round(conductance, 8) AS conductance FROM swept"),
    "sybil_suspect_edges": s.final(*_BASE, _SWEEP, _SUSPECTS, select="SELECT src, dst, crossings FROM suspects"),
    "sybil_cap_seed_share": s.final(s.PEER, select="SELECT src, dst, CASE WHEN src = 0 THEN greatest(1, least(w, CAST(floor((sum(w) OVER (PARTITION BY src)) * 0.05) AS BIGINT))) ELSE w END AS w FROM edges"),
    "detection_review_roc": s.final(_REVIEW, _roc(by=""), select="SELECT cut, node, round(fpr, 8) AS fpr, round(tpr, 8) AS tpr FROM roc"),
    "detection_review_auroc": s.final(_REVIEW, select="""SELECT round(sum(CASE WHEN a.score > b.score THEN 1.0 WHEN a.score = b.score THEN 0.5 ELSE 0 END) / count(*), 8)::DOUBLE AS auroc FROM lab a JOIN lab b ON a.is_honest AND NOT b.is_honest"""),
    "detection_review_cuts": s.final(_REVIEW, _roc(by=""), select="SELECT cut, round(tpr, 8) AS sensitivity, round(1 - fpr, 8) AS specificity, round(tpr - fpr, 8) AS youden FROM roc"),
    "detection_review_rates": s.final(_REVIEW, _roc(by=""), select="""SELECT round(avg(fpr), 8) AS fp_mean, round(avg(1 - tpr), 8) AS fn_mean, round(max(fpr) FILTER (WHERE cut = 100), 8) AS fp_at,
round(max(1 - tpr) FILTER (WHERE cut = 100), 8) AS fn_at FROM roc"""),
}
