"""Queries on walks that follow a changing graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from peertrust import estimate as est
from peertrust import graph, incremental, power, walks
from peertrust.sources import tables as t

from . import sqltext as s
from .ranking import ALPHA, K, SEED, WALKS

HELD_NODES, HELD_EDGES = 5, 20


def holdout(edges: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The graph less its five largest nodes and twenty hashed edges, and all of it."""
    edges = t.cut(edges)
    gone = graph.nodes(edges).orderBy(F.desc("node")).limit(HELD_NODES).select(F.col("node").alias("_n"))
    rest = edges.join(F.broadcast(gone), edges.src == F.col("_n"), "left_anti").join(F.broadcast(gone), edges.dst == F.col("_n"), "left_anti")
    held = rest.orderBy(F.md5(F.concat_ws("|", "src", "dst")), "src", "dst").limit(HELD_EDGES).select(F.col("src").alias("_s"), F.col("dst").alias("_d"))
    return t.cut(rest.join(F.broadcast(held), (rest.src == F.col("_s")) & (rest.dst == F.col("_d")), "left_anti")), edges


def updated(spark, d, policy="source_visit"):
    old, new = holdout(t.peer_edges(spark, d))
    before = t.cut(walks.simulate_walks(old, SEED, WALKS, ALPHA))
    return before, t.cut(incremental.apply_changes(before, old, new, 1, ALPHA, policy)), old, new


def _once(spark, d, policy):
    return updated(spark, d, policy)


def arrivals(edges: DataFrame, n: int = HELD_EDGES) -> tuple[DataFrame, DataFrame]:
    """The graph without ``n`` hashed edges, and all of it."""
    edges = t.cut(edges)
    held = edges.orderBy(F.md5(F.concat_ws("|", "src", "dst")), "src", "dst").limit(n).select(F.col("src").alias("_s"), F.col("dst").alias("_d"))
    return t.cut(edges.join(F.broadcast(held), (edges.src == F.col("_s")) & (edges.dst == F.col("_d")), "left_anti")), edges


def _coin(spark, d):
    """Edges arrive: a coin at each visit of their sources."""
    old, new = arrivals(t.peer_edges(spark, d))
    before = t.cut(walks.simulate_walks(old, SEED, WALKS, ALPHA))
    return incremental.apply_changes(before, old, new, 1, ALPHA, "coin")


def _crossing(spark, d):
    """The same edges leave: only walks that crossed them hop again."""
    new, old = arrivals(t.peer_edges(spark, d))
    before = t.cut(walks.simulate_walks(old, SEED, WALKS, ALPHA))
    return incremental.apply_changes(before, old, new, 1, ALPHA, "crossing")


_OPS = "op string, src long, dst long, w_old long, w_new long"


def _newcomer(spark):
    """A node that comes with three edges, and one that goes."""
    return spark.createDataFrame([("add_node", 1_000_000, None, None, None), ("add_node", 1_000_001, None, None, None), ("add", 0, 1_000_000, None, 50_000), ("add", 1_000_000, 7, None, 100), ("add", 1_000_000, 0, None, 300)], _OPS)


def _add_node(spark, d):
    """Walks after a node came with its edges."""
    edges = t.cut(t.peer_edges(spark, d))
    before = t.cut(walks.simulate_walks(edges, SEED, WALKS, ALPHA))
    new = t.cut(incremental.apply_to_edges(edges, incremental.expand_changes(_newcomer(spark), edges)))
    return incremental.apply_changes(before, edges, new, 1, ALPHA, "coin", seed_must_stay=True)


def _nodes_after(spark, d):
    edges = t.cut(t.peer_edges(spark, d))
    ops = _newcomer(spark).union(spark.createDataFrame([("drop_node", 3, None, None, None)], _OPS))
    return incremental.apply_to_nodes(graph.nodes(edges), ops)


def _tables_form(spark, d, policy):
    """The same update by joins, as graphs beyond one place need it."""
    old, new = holdout(t.peer_edges(spark, d))
    before = t.cut(walks.simulate_walks(old, SEED, WALKS, ALPHA))
    return incremental.apply_changes(before, old, new, 1, ALPHA, policy, strategy="joins")


def _drop_node(spark, d):
    edges = t.cut(t.peer_edges(spark, d))
    before = t.cut(walks.simulate_walks(edges, SEED, WALKS, ALPHA))
    ops = spark.createDataFrame([("drop_node", 7, None, None, None)], "op string, src long, dst long, w_old long, w_new long")
    new = t.cut(incremental.apply_to_edges(edges, incremental.expand_changes(ops, edges)))
    return incremental.apply_changes(before, edges, new, 1, ALPHA)


def _ops(spark, d):
    """Two edges removed, two flipped, one reweighted, one node dropped."""
    edges = t.peer_edges(spark, d)
    some = edges.orderBy(F.md5(F.concat_ws("|", "src", "dst")), "src", "dst").limit(5)
    ranked = some.select("src", "dst", "w", F.row_number().over(_by_md5()).alias("r"))
    null = F.lit(None).cast("long")
    rows = ranked.filter("r <= 2").select(F.lit("remove").alias("op"), "src", "dst", F.col("w").alias("w_old"), null.alias("w_new"))
    rows = rows.union(ranked.filter("r in (3, 4)").select(F.lit("flip"), "src", "dst", F.col("w"), F.col("w")))
    rows = rows.union(ranked.filter("r = 5").select(F.lit("reweight"), "src", "dst", F.col("w"), F.col("w") * 2))
    rows = rows.union(spark.createDataFrame([("drop_node", 3, None, None, None)], "op string, src long, dst long, w_old long, w_new long"))
    return incremental.expand_changes(rows, edges)


def _by_md5():
    return Window.orderBy(F.md5(F.concat_ws("|", "src", "dst")), "src", "dst")


def _costs(spark, d):
    out = None
    for policy in ("source_visit", "coupling"):
        before, after, _, _ = _once(spark, d, policy)
        row = incremental.update_cost(before, after, 1).withColumn("policy", F.lit(policy)).withColumn("kept_share", F.round("kept_share", 8))
        out = row if out is None else out.unionByName(row)
    return out


def _merged(spark, d):
    """Counts moved by what was cut off and redone, not counted anew."""
    before, after, _, _ = updated(spark, d)
    key = ["walk_id", "gen", "step", "node"]
    gone, fresh = before.join(after, key, "left_anti"), after.join(before, key, "left_anti")
    counts = before.groupBy("node").agg(F.count(F.lit(1)).alias("visits"))
    return est.merge_counts(counts, gone, fresh)


def _bounds(spark, d):
    edges = t.peer_edges(spark, d)
    w = walks.simulate_walks(edges, SEED, WALKS, ALPHA)
    one = w.agg(F.count(F.lit(1)).alias("visits")).join(edges.agg(F.count(F.lit(1)).alias("m")), how="cross")
    harmonic = F.aggregate(F.sequence(F.lit(1), F.col("m").cast("int")), F.lit(0.0), lambda a, i: a + 1.0 / i)
    rows = one.select("visits", "m", F.explode(F.array(*[F.lit(x) for x in (0.1, 0.5, 1.0)])).alias("part"), harmonic.alias("h"))
    at = F.floor(F.col("m") * F.col("part"))
    return rows.select(at.alias("arrival"), F.round(F.col("visits") / at, 8).alias("bound_arrival"), F.round(F.col("visits") / ALPHA * F.col("h"), 4).alias("bound_total"), F.round(F.col("visits") / ALPHA, 6).alias("bound_removal"), F.round(F.col("visits") / ALPHA / F.col("m"), 8).alias("bound_removal_edge"))


def _load(spark, d):
    edges = t.peer_edges(spark, d)
    out = incremental.edge_load(power.power_iteration(edges, SEED, ALPHA), edges)
    return out.select(F.round("expected", 10).alias("expected"), F.round("mean_load", 10).alias("mean_load"), "n_edges")


QUERIES = {
    "update_expand_changes": _ops,
    "update_affected": lambda spark, d: (lambda old, new: incremental.affected(walks.simulate_walks(old, SEED, WALKS, ALPHA), incremental.changed_sources(old, new)))(*holdout(t.peer_edges(spark, d))),
    "update_source_visit": lambda spark, d: updated(spark, d)[1],
    "update_coupling": lambda spark, d: updated(spark, d, "coupling")[1],
    "update_source_visit_joins": lambda spark, d: _tables_form(spark, d, "source_visit"),
    "update_coupling_joins": lambda spark, d: _tables_form(spark, d, "coupling"),
    "update_coin": _coin,
    "update_crossing": _crossing,
    "update_add_node": _add_node,
    "update_nodes": _nodes_after,
    "update_drop_node": _drop_node,
    "update_cost": _costs,
    "update_merged_counts": _merged,
    "update_bounds": _bounds,
    "update_edge_load": _load,
}

HOLD = f"""
gone AS (SELECT node FROM (SELECT src AS node FROM edges UNION SELECT dst FROM edges) ORDER BY node DESC LIMIT {HELD_NODES}),
rest AS (SELECT * FROM edges WHERE src NOT IN (SELECT node FROM gone) AND dst NOT IN (SELECT node FROM gone)),
held AS (SELECT src, dst FROM rest ORDER BY md5(src || '|' || dst), src, dst LIMIT {HELD_EDGES}),
old AS (SELECT r.* FROM rest r ANTI JOIN held h USING (src, dst))"""
_CHANGED = """
changed AS (SELECT DISTINCT src FROM (SELECT src, dst, o.w AS a, e.w AS b FROM old o FULL JOIN edges e USING (src, dst)) WHERE a IS DISTINCT FROM b)"""
_CUT = """
cuts AS (SELECT walk_id, min(step) AS cut FROM walk WHERE node IN (SELECT src FROM changed) GROUP BY walk_id),
again AS (SELECT w.walk_id, w.seed, 1 AS gen, w.step, w.node FROM walk w JOIN cuts c ON c.walk_id = w.walk_id AND c.cut = w.step)"""
_MOVED = (s.cdf("old", "cdf0"), s.cdf("edges", "cdf"), s.starts([SEED], WALKS), s.walk(ALPHA, table="cdf0"), _CHANGED, _CUT, s.walk(ALPHA, begin="again", name="redo"))
_AFTER = """
after AS (SELECT w.walk_id, w.seed, w.gen, w.step, w.node FROM walk w LEFT JOIN cuts c USING (walk_id) WHERE c.cut IS NULL OR w.step <= c.cut
  UNION ALL SELECT r.walk_id, r.seed, r.gen, r.step, r.node FROM redo r JOIN cuts c USING (walk_id) WHERE r.step > c.cut)"""
_ALL = "SELECT walk_id, seed, gen, step, node FROM after"
_WITHOUT = """
old AS (SELECT * FROM edges),
edges2 AS (SELECT * FROM edges WHERE src <> 7 AND dst <> 7),
changed AS (SELECT DISTINCT src FROM edges WHERE src = 7 OR dst = 7)"""

_ARRIVALS = f"""
held AS (SELECT src, dst FROM edges ORDER BY md5(src || '|' || dst), src, dst LIMIT {HELD_EDGES}),
less AS (SELECT e.* FROM edges e ANTI JOIN held h USING (src, dst))"""
_REROUTED = """
moved AS (SELECT c.walk_id, w.seed, 1 AS gen, c.cut + 1 AS step, c.next AS node FROM cuts c JOIN walk w ON w.walk_id = c.walk_id AND w.step = 0 WHERE c.next IS NOT NULL)"""
_AFTER_MOVE = """
after AS (SELECT w.walk_id, w.seed, w.gen, w.step, w.node FROM walk w LEFT JOIN cuts c USING (walk_id) WHERE c.cut IS NULL OR w.step <= c.cut UNION ALL SELECT walk_id, seed, gen, step, node FROM redo)"""
_HOPS = """
hops AS (SELECT *, lead(node) OVER (PARTITION BY walk_id ORDER BY step) AS next FROM walk)"""


def _draw(tag):
    return s.u32_sql(s.RNG_SEED, tag, "walk_id", "1", "step")


def _coin_sql(old, new):
    """Coins at visits of sources whose edges grew."""
    return (
        s.cdf(old, "cdf0"), s.starts([SEED], WALKS), s.walk(ALPHA, table="cdf0"), _HOPS,
        f"""
grown AS (SELECT n.src, n.dst, n.w - coalesce(o.w, 0) AS g FROM {new} n LEFT JOIN {old} o USING (src, dst) WHERE n.w > coalesce(o.w, 0)),
ivl AS (SELECT src, dst, CAST(sum(g) OVER (PARTITION BY src ORDER BY dst) AS BIGINT) AS hi, CAST(sum(g) OVER (PARTITION BY src ORDER BY dst) AS BIGINT) - g AS lo FROM grown),
tot AS (SELECT src, CAST(sum(w) AS BIGINT) AS tot FROM {new} GROUP BY src),
st AS (SELECT src, CAST(sum(g) AS BIGINT) AS g, any_value(tot) AS tot FROM grown JOIN tot USING (src) GROUP BY src),
turns AS (SELECT h.walk_id, h.step, h.node, ({_draw('coin')} * tot) >> 32 AS pick FROM hops h JOIN st ON st.src = h.node
  WHERE (next IS NOT NULL AND ({_draw('coin')} * tot) >> 32 < g) OR (next IS NULL AND g = tot AND {_draw('wake')} >= {s.stop_limit(ALPHA)})),
cuts AS (SELECT t.walk_id, t.step AS cut, i.dst AS next FROM (SELECT walk_id, min(step) AS step, arg_min(node, step) AS node, arg_min(pick, step) AS pick FROM turns GROUP BY walk_id) t JOIN ivl i ON i.src = t.node AND lo <= pick AND pick < hi)""",
        s.cdf(new, "cdf"), _REROUTED, s.walk(ALPHA, begin="moved", name="redo"), _AFTER_MOVE,
    )


_CROSSING = (
    s.cdf("edges", "cdf0"), s.starts([SEED], WALKS), s.walk(ALPHA, table="cdf0"), _HOPS, s.cdf("less", "cdf"), f"""
first AS (SELECT walk_id, min(step) AS step, arg_min(node, step) AS node FROM hops SEMI JOIN (SELECT src AS node, dst AS next FROM held) x USING (node, next) GROUP BY walk_id),
cuts AS (SELECT walk_id, step AS cut, c.dst AS next FROM first LEFT JOIN cdf c ON c.src = node AND ({_draw('move')} * tot) >> 32 >= lo AND ({_draw('move')} * tot) >> 32 < hi)""",
    _REROUTED, s.walk(ALPHA, begin="moved", name="redo"), _AFTER_MOVE,
)
_COUPLING = (
    s.cdf("old", "cdf0"), s.starts([SEED], WALKS), s.walk(ALPHA, table="cdf0"), _HOPS, _CHANGED, f"""
law AS (SELECT src, dst, coalesce(o.p, 0) AS p_old, coalesce(n.p, 0) AS p_new FROM (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS p FROM old) o FULL JOIN (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS p FROM edges) n USING (src, dst) WHERE src IN (SELECT src FROM changed)),
more AS (SELECT src, dst, p_new - p_old AS d, sum(p_new - p_old) OVER (PARTITION BY src ORDER BY dst) AS hi, sum(p_new - p_old) OVER (PARTITION BY src) AS mass, row_number() OVER (PARTITION BY src ORDER BY dst DESC) AS back FROM law WHERE p_new > p_old),
st AS (SELECT src, sum(p_old) > 0 AS had, sum(p_new) > 0 AS has FROM law GROUP BY src),
hit AS (SELECT walk_id, min(h.step) AS step, arg_min(h.node, h.step) AS node, arg_min(st.has, h.step) AS has FROM hops h JOIN st ON st.src = h.node LEFT JOIN law l ON l.src = h.node AND l.dst = h.next
  WHERE (h.next IS NOT NULL AND {_draw('keep')} / 4294967296.0::DOUBLE >= l.p_new / l.p_old) OR (h.next IS NULL AND NOT had AND has AND {_draw('wake')} >= {s.stop_limit(ALPHA)}) GROUP BY walk_id),
cuts AS (SELECT walk_id, step AS cut, CASE WHEN has THEN m.dst END AS next FROM hit LEFT JOIN more m ON m.src = node AND has AND {_draw('move')} / 4294967296.0::DOUBLE * mass >= hi - d AND ({_draw('move')} / 4294967296.0::DOUBLE * mass < hi OR back = 1))""",
    s.cdf("edges", "cdf"), _REROUTED, s.walk(ALPHA, begin="moved", name="redo"), _AFTER_MOVE,
)
_NEWCOMER = """
new AS (SELECT src, dst, w FROM edges UNION ALL SELECT * FROM (VALUES (0::BIGINT, 1000000::BIGINT, 50000::BIGINT), (1000000, 7, 100), (1000000, 0, 300)) v(src, dst, w))"""
_COST = """
key AS (SELECT walk_id, gen, step, node FROM walk EXCEPT SELECT walk_id, gen, step, node FROM after),
cost AS (SELECT (SELECT count(DISTINCT walk_id) FROM (SELECT walk_id FROM after WHERE gen = 1 UNION SELECT walk_id FROM key)) AS touched, (SELECT count(*) FROM after WHERE gen = 1) AS redone,
  (SELECT count(*) FROM walk) AS visits_before, (SELECT count(*) FROM after) AS visits_after)"""


def _cost_sql(policy, *ctes):
    return f"SELECT touched, redone, visits_before, visits_after, round((visits_after - redone) / visits_after, 8) AS kept_share, '{policy}' AS policy FROM ({s.final(s.PEER, HOLD, *ctes, _COST, select='SELECT * FROM cost')})"


ORACLE_SQL = {
    "update_expand_changes": s.final(s.PEER, """
chosen AS (SELECT *, row_number() OVER (ORDER BY md5(src || '|' || dst), src, dst) AS r FROM edges)""", select="""
SELECT 'remove' AS op, src, dst, w AS w_old, NULL::BIGINT AS w_new FROM chosen WHERE r <= 4
UNION ALL SELECT 'add', dst, src, NULL, w FROM chosen WHERE r IN (3, 4) UNION ALL SELECT 'reweight', src, dst, w, w * 2 FROM chosen WHERE r = 5
UNION ALL SELECT 'remove', src, dst, w, NULL FROM edges WHERE src = 3 OR dst = 3"""),
    "update_affected": s.final(s.PEER, HOLD, *_MOVED, select="SELECT walk_id, cut FROM cuts"),
    "update_source_visit": s.final(s.PEER, HOLD, *_MOVED, _AFTER, select=_ALL),
    "update_source_visit_joins": s.final(s.PEER, HOLD, *_MOVED, _AFTER, select=_ALL),
    "update_coupling": s.final(s.PEER, HOLD, *_COUPLING, select=_ALL),
    "update_coupling_joins": s.final(s.PEER, HOLD, *_COUPLING, select=_ALL),
    "update_coin": s.final(s.PEER, _ARRIVALS, *_coin_sql("less", "edges"), select=_ALL),
    "update_crossing": s.final(s.PEER, _ARRIVALS, *_CROSSING, select=_ALL),
    "update_add_node": s.final(s.PEER, _NEWCOMER, *_coin_sql("edges", "new"), select=_ALL),
    "update_nodes": s.final(s.PEER, s.nodes(), select="SELECT node FROM nodes WHERE node <> 3 UNION SELECT 1000000 UNION SELECT 1000001"),
    "update_cost": _cost_sql("source_visit", *_MOVED, _AFTER) + " UNION ALL " + _cost_sql("coupling", *_COUPLING),
    "update_drop_node": s.final(s.PEER, _WITHOUT, s.cdf("old", "cdf0"), s.cdf("edges2", "cdf"), s.starts([SEED], WALKS), s.walk(ALPHA, table="cdf0"), _CUT, s.walk(ALPHA, begin="again", name="redo"), _AFTER, select=_ALL),
    "update_merged_counts": s.final(s.PEER, HOLD, *_MOVED, _AFTER, select="SELECT node, count(*) AS visits FROM after GROUP BY node"),
    "update_bounds": s.final(s.PEER, s.cdf(), s.starts([SEED], WALKS), s.walk(ALPHA), """
one AS (SELECT (SELECT count(*) FROM walk) AS visits, (SELECT count(*) FROM edges) AS m, (SELECT sum(1.0::DOUBLE / i.range) FROM range(1, (SELECT count(*) + 1 FROM edges)) i) AS h)""", select=f"""
SELECT CAST(floor(m * part) AS BIGINT) AS arrival, round(visits / floor(m * part), 8) AS bound_arrival, round(visits / {ALPHA} * h, 4) AS bound_total, round(visits / {ALPHA}::DOUBLE, 6) AS bound_removal,
round(visits / {ALPHA}::DOUBLE / m, 8) AS bound_removal_edge FROM one, (VALUES (0.1::DOUBLE), (0.5), (1.0)) p(part)"""),
    "update_edge_load": s.final(s.PEER, s.nodes(extra=SEED), s.power(ALPHA, K, SEED), select=f"""
SELECT round(sum(x) / count(*), 10) AS expected, round(avg(x), 10) AS mean_load, count(*) AS n_edges
FROM (SELECT coalesce(p.score, 0) / count(*) OVER (PARTITION BY e.src) AS x FROM edges e LEFT JOIN power p ON p.node = e.src AND p.k = {K})"""),
}
