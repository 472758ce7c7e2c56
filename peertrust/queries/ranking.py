"""Queries on hop laws, power iteration, walks and scores."""

from __future__ import annotations

from pyspark.sql import functions as F

from peertrust import estimate as est
from peertrust import doubling, graph, locality, metrics, power, transition, walks
from peertrust.functions.rng import RNG_SEED, u32
from peertrust.sources import tables as t

from . import sqltext as s

SEED, WALKS, ALPHA, K = 0, 300, 0.3, power.ROUNDS


def _round(df, *columns, digits=8):
    for c in columns:
        df = df.withColumn(c, F.round(c, digits))
    return df


def _walks(spark, d, **options):
    return walks.simulate_walks(t.peer_edges(spark, d), SEED, WALKS, ALPHA, **options)


def _hops(spark, d, binned):
    """One hop from every node with 50 draws, through plain or binned intervals."""
    table = t.cut(transition.cdf(t.peer_edges(spark, d)))
    per = table.select("src", "tot").distinct().select("src", "tot", F.explode(F.sequence(F.lit(0), F.lit(49))).alias("i"))
    pick = per.withColumn("pick", F.shiftright(u32(RNG_SEED, "one", F.col("src"), F.col("i")) * F.col("tot"), 32))
    if binned:
        b = transition.binned_cdf(table)
        pick = pick.join(b.select("src", "bins").distinct(), "src").withColumn("bin", F.floor(F.col("pick") * F.col("bins") / F.col("tot")).cast("long"))
        return pick.join(b.select("src", "bin", "dst", "lo", "hi"), ["src", "bin"]).filter("lo <= pick AND pick < hi").select("src", "i", "dst")
    return pick.join(table.select("src", "dst", "lo", "hi"), "src").filter("lo <= pick AND pick < hi").select("src", "i", "dst")


def _alias_law(spark, d):
    """Probabilities that the alias table gives, summed per edge."""
    a = transition.alias_table(t.peer_edges(spark, d))
    both = a.select("src", "dst", (F.col("keep") / F.col("n")).alias("p")).union(a.select("src", F.col("other").alias("dst"), ((1 - F.col("keep")) / F.col("n")).alias("p")))
    return _round(both.groupBy("src", "dst").agg(F.sum("p").alias("p")).filter("p > 1e-12"), "p", digits=6)


def _variant(name, graph_of=t.peer_edges):
    def run(spark, d):
        e = t.cut(graph_of(spark, d))
        if name in ("endpoint_cyclic", "path_stop"):
            begin = walks.starts_everywhere(graph.nodes(e), 3)
        elif name == "path_jump":
            begin = walks.starts_everywhere(graph.nodes(e), 2)
        else:
            begin = walks.starts_at_random(graph.nodes(e), WALKS)
        w = begin.unionByName(walks.advance(e, begin, ALPHA, jump=graph.nodes(e) if name == "path_jump" else None))
        return est.endpoint_scores(w) if name.startswith("endpoint") else est.estimate(w)

    return run


def _power(**options):
    return lambda spark, d: _round(power.power_iteration(t.peer_edges(spark, d), alpha=ALPHA, **options), "score")


def _reached(scores):
    """Without the nodes that no trust has come to in the rounds made: SQL that starts at
    the seed has no rows of them."""
    return scores.filter("score > 0")


def _from_seed(**options):
    return lambda spark, d: _round(_reached(power.power_iteration(t.peer_edges(spark, d), SEED, ALPHA, **options)), "score")


def _linked_graph(spark, d):
    """Hosts and targets as numbers: all targets are dangling."""
    pairs = t.link_pairs(spark, d)
    key = lambda c: F.pmod(F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("long"), F.lit(1 << 30))
    return pairs.select((key("host") * 2).alias("src"), (key("target") * 2 + 1).alias("dst"), F.col("n").alias("w")).groupBy("src", "dst").agg(F.sum("w").alias("w"))


def _first_host(spark, d):
    return _linked_graph(spark, d).agg(F.min("src")).first()[0]


def _swarm(spark, d):
    """Candidates for a download: peers that have made a purchase."""
    return t.load(spark, d, "events").filter("event_type = 'purchase'").select(F.col("user_id").alias("node")).distinct()


def _exact(spark, d, seed=SEED, alpha=ALPHA):
    return power.power_iteration(t.peer_edges(spark, d), seed, alpha)


QUERIES = {
    "transition_weight": lambda spark, d: _round(transition.transitions(t.peer_edges(spark, d)), "p"),
    "transition_outdegree": lambda spark, d: _round(transition.transitions(t.peer_edges(spark, d), "outdegree"), "p"),
    "transition_dangling": lambda spark, d: transition.dangling(_linked_graph(spark, d)),
    "transition_dense_global": lambda spark, d: _round(transition.dense_transition(t.peer_edges(spark, d), ALPHA), "p"),
    "transition_dense_seed": lambda spark, d: _round(transition.dense_transition(t.peer_edges(spark, d), ALPHA, SEED), "p"),
    "transition_cdf": lambda spark, d: transition.cdf(t.peer_edges(spark, d)),
    "transition_hop": lambda spark, d: _hops(spark, d, False),
    "transition_hop_binned": lambda spark, d: _hops(spark, d, True),
    "transition_alias": _alias_law,
    "power_global": _power(),
    "power_personal": _from_seed(),
    "power_dangling_uniform": lambda spark, d: _round(power.power_iteration(_linked_graph(spark, d), None, ALPHA), "score"),
    "power_dangling_seed": lambda spark, d: _round(power.power_iteration(_linked_graph(spark, d), _first_host(spark, d), ALPHA), "score"),
    "power_dangling_drop": lambda spark, d: _round(power.power_iteration(_linked_graph(spark, d), _first_host(spark, d), ALPHA, "drop"), "score"),
    "power_outdegree": _from_seed(weighting="outdegree"),
    "power_distributed": _from_seed(rounds=12, distributed=True),
    "power_trace": lambda spark, d: _round(power.residual_trace(t.peer_edges(spark, d), SEED, ALPHA, 20), "residual"),
    "power_neumann": lambda spark, d: _round(_reached(power.neumann_scores(t.peer_edges(spark, d), SEED, ALPHA)), "score"),
    "power_many_seeds": lambda spark, d: _round(_reached(power.power_iteration_many(t.peer_edges(spark, d), [0, 1, 2], [ALPHA])), "score").select("seed", "node", "score"),
    "power_early_stop": lambda spark, d: _round(power.power_iteration(t.peer_edges(spark, d), SEED, ALPHA, tol=1e-2, init="uniform"), "score"),
    "walks_visits": _walks,
    "walks_frontier": lambda spark, d: walks.simulate_walks(t.peer_edges(spark, d), SEED, 40, 0.5, strategy="frontier"),
    "walks_binned": lambda spark, d: walks.simulate_walks(t.peer_edges(spark, d), SEED, 40, 0.5, strategy="binned"),
    "walks_recursive_sql": lambda spark, d: _walks(spark, d, strategy="recursive"),
    "walks_hop_limited": lambda spark, d: _walks(spark, d, max_steps=3),
    "walks_scores": lambda spark, d: _round(est.estimate(_walks(spark, d)), "score"),
    "walks_endpoint_random": lambda spark, d: _round(_variant("endpoint_random")(spark, d), "score"),
    "walks_endpoint_cyclic": lambda spark, d: _round(_variant("endpoint_cyclic")(spark, d), "score"),
    "walks_path_jump": lambda spark, d: _round(_variant("path_jump", _linked_graph)(spark, d), "score"),
    "walks_path_stop_all": lambda spark, d: _round(_variant("path_stop")(spark, d), "score"),
    "walks_path_random": lambda spark, d: _round(_variant("path_random")(spark, d), "score"),
    "walks_many_seeds": lambda spark, d: _round(est.estimate(walks.simulate_walks(t.peer_edges(spark, d), [0, 1, 2], 100, ALPHA), ["seed"]), "score"),
    "walks_lengths": lambda spark, d: _round(est.walk_lengths(_walks(spark, d)), "mean_length"),
    "walks_ends": lambda spark, d: walks.walk_ends(_walks(spark, d), t.peer_edges(spark, d), walks.step_cap(ALPHA)),
    "walks_visit_counts": lambda spark, d: est.visit_counts(_walks(spark, d)),
    "walks_confidence": lambda spark, d: _round(est.score_ci(_walks(spark, d)), "score", "se", "low", "high"),
    "walks_needed": lambda spark, d: est.walks_for_errors(t.load(spark, d, "lineitem"), "l_discount", 0.05, ALPHA),
    "walks_doubling": lambda spark, d: _round(est.estimate(doubling.doubling_walks(t.peer_edges(spark, d), 4, 0.5, miss=1e-3), ["seed"]), "score"),
    "rank_top10": lambda spark, d: _round(est.rank(est.estimate(_walks(spark, d)), 10), "score"),
    "rank_choose_peer": lambda spark, d: _round(est.choose_peer(est.estimate(_walks(spark, d)), _swarm(spark, d)), "score"),
    "walks_paths": lambda spark, d: walks.paths(_walks(spark, d)),
    "locality_hops": lambda spark, d: locality.hop_distance(t.peer_edges(spark, d), SEED, 6),
    "locality_mass_by_hop": lambda spark, d: _round(locality.mass_by_hop(_reached(_exact(spark, d)), locality.hop_distance(t.peer_edges(spark, d), SEED, 6)), "mass", digits=6),
    "locality_mass_by_step": lambda spark, d: _round(locality.mass_by_step(_walks(spark, d)), "share"),
    "metric_differences": lambda spark, d: _round(metrics.differences(est.estimate(_walks(spark, d)), _exact(spark, d)), "l2", "linf", "l1", "relative"),
    "metric_topk_error": lambda spark, d: _round(metrics.topk_relative_error(est.estimate(_walks(spark, d)), _exact(spark, d)), "mean_relative_error"),
    "metric_topk_agreement": lambda spark, d: _round(metrics.topk_agreement(est.estimate(_walks(spark, d)), _exact(spark, d)), "spearman", "ndcg", "kendall"),
    "metric_error_by_walks": lambda spark, d: _round(metrics.error_by_walks(_walks(spark, d), _exact(spark, d), [10, 30, 100, 300]), "l2", "linf", "relative"),
    "metric_walk_work": lambda spark, d: metrics.walk_work(_walks(spark, d)),
}

_WALK = (s.PEER, s.cdf(), s.starts([SEED], WALKS), s.walk(ALPHA))
_SCORED = (*_WALK, s.scores())
_ROWS = "SELECT walk_id, seed, gen, step, node FROM walk"
_SCORE = "SELECT node, round(score, 8) AS score FROM scores"
_POWER = (s.PEER, s.nodes(extra=SEED), s.power(ALPHA, K, SEED))
_EXACT = (*_POWER, f"\nexact AS (SELECT node, score FROM power WHERE k = {K})")
_POWER_ROWS = f"SELECT node, round(score, 8) AS score FROM power WHERE k = {K}"
_KEY = "CAST('0x' || substr(md5({}), 1, 8) AS BIGINT) % 1073741824"
_LINKS = f"""
links AS (SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS target FROM pages),
edges AS (SELECT {_KEY.format('host')} * 2 AS src, {_KEY.format('target')} * 2 + 1 AS dst, count(*) AS w FROM links GROUP BY 1, 2)"""


def _dangling_power(rule):
    # the seed is the smallest host, so its place in the matrix is a query of its own
    text = s.power(ALPHA, K, -1, rule).replace("CAST(-1 AS BIGINT)", "(SELECT min(src) FROM edges)")
    if rule == "drop":
        select = f"SELECT node, round(score / (SELECT sum(score) FROM power WHERE k = {K} AND node <> -9), 8) AS score FROM power WHERE k = {K} AND node <> -9"
        return s.final(_LINKS, s.nodes(), text, select=f"SELECT n.node, coalesce(x.score, 0.0) AS score FROM nodes n LEFT JOIN ({select}) x USING (node)")
    return s.final(_LINKS, s.nodes(), text, select=f"SELECT n.node, coalesce(x.score, 0.0) AS score FROM nodes n LEFT JOIN ({_POWER_ROWS}) x USING (node)")


def _from_everywhere(each):
    return f"""
starts AS (SELECT node * {each} + r.range AS walk_id, node AS seed, 0 AS gen, 0 AS step, node FROM nodes, range({each}) r)"""


_LISTED = """
listed AS (SELECT node, row_number() OVER (ORDER BY node) - 1 AS i FROM nodes)"""
_RANDOM = f"""{_LISTED},
starts AS (SELECT r.range AS walk_id, node AS seed, 0 AS gen, 0 AS step, node FROM range({WALKS}) r JOIN listed ON i = ({s.u32_sql(42, 'start', 'r.range', '0', '0')} * (SELECT count(*) FROM listed)) >> 32)"""
_ENDPOINT = "SELECT node, round(count(*) / (SELECT count(DISTINCT walk_id) FROM walk), 8) AS score FROM (SELECT arg_max(node, step) AS node FROM walk GROUP BY walk_id) GROUP BY node"
_HOP = f"""
picks AS (SELECT src, tot, r.range AS i, ({s.u32_sql(42, 'one', 'src', 'r.range')} * tot) >> 32 AS pick FROM (SELECT DISTINCT src, tot FROM cdf), range(50) r)"""
_HOP_SELECT = "SELECT p.src, p.i, c.dst FROM picks p JOIN cdf c ON c.src = p.src AND lo <= pick AND pick < hi"
_DENSE = """SELECT a.node AS src, b.node AS dst, round({} * coalesce(t.p, 0) + {} * {}, 8) AS p FROM nodes a CROSS JOIN nodes b LEFT JOIN (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS p FROM edges) t ON t.src = a.node AND t.dst = b.node"""
_BFS = """
bfs AS (SELECT CAST(0 AS BIGINT) AS node, 0 AS hop UNION SELECT e.dst, b.hop + 1 FROM bfs b JOIN edges e ON e.src = b.node WHERE b.hop < 6),
hops AS (SELECT node, min(hop) AS hop FROM bfs GROUP BY node)"""
_BOTH = """
both_ AS (SELECT coalesce(s.score, 0) AS x, coalesce(e.score, 0) AS y, node FROM scores s FULL JOIN exact e USING (node))"""
_GRID = """
cnt AS (SELECT n.n AS n_walks, node, count(*) AS v FROM walk JOIN (VALUES (10), (30), (100), (300)) n(n) ON walk_id < n.n GROUP BY 1, 2),
est AS (SELECT n_walks, node, v / sum(v) OVER (PARTITION BY n_walks) AS x FROM cnt),
grid AS (SELECT n.n AS n_walks, node, score AS y FROM exact, (VALUES (10), (30), (100), (300)) n(n)),
err AS (SELECT coalesce(g.n_walks, e.n_walks) AS n_walks, coalesce(x, 0) AS x, coalesce(y, 0) AS y FROM grid g FULL JOIN est e ON g.n_walks = e.n_walks AND g.node = e.node)"""

ORACLE_SQL = {
    "transition_weight": s.final(s.PEER, select="SELECT src, dst, round(w / sum(w) OVER (PARTITION BY src), 8) AS p FROM edges"),
    "transition_outdegree": s.final(s.PEER, select="SELECT src, dst, round(1.0 / count(*) OVER (PARTITION BY src), 8)::DOUBLE AS p FROM edges"),
    "transition_dangling": s.final(_LINKS, s.nodes(), select="SELECT node FROM nodes EXCEPT SELECT src FROM edges"),
    "transition_dense_global": s.final(s.PEER, s.nodes(), select=_DENSE.format(1 - ALPHA, ALPHA, "(1.0::DOUBLE / (SELECT count(*) FROM nodes))")),
    "transition_dense_seed": s.final(s.PEER, s.nodes(), select=_DENSE.format(1 - ALPHA, ALPHA, "CASE WHEN b.node = 0 THEN 1.0::DOUBLE ELSE 0 END")),
    "transition_cdf": s.final(s.PEER, s.cdf(), select="SELECT src, dst, w, lo, hi, tot FROM cdf"),
    "transition_hop": s.final(s.PEER, s.cdf(), _HOP, select=_HOP_SELECT),
    "transition_hop_binned": s.final(s.PEER, s.cdf(), _HOP, select=_HOP_SELECT),
    "transition_alias": s.final(s.PEER, select="SELECT src, dst, round(w / sum(w) OVER (PARTITION BY src), 6) AS p FROM edges"),
    "power_global": s.final(s.PEER, s.nodes(), s.power(ALPHA, K, None, "uniform"), select=_POWER_ROWS),
    "power_personal": s.final(*_POWER, select=_POWER_ROWS),
    "power_dangling_uniform": s.final(_LINKS, s.nodes(), s.power(ALPHA, K, None, "uniform"), select=_POWER_ROWS),
    "power_dangling_seed": _dangling_power("seed"),
    "power_dangling_drop": _dangling_power("drop"),
    "power_outdegree": s.final(s.PEER, s.nodes(extra=SEED), s.power(ALPHA, K, SEED, weighting="outdegree"), select=_POWER_ROWS),
    "power_distributed": s.final(s.PEER, s.nodes(extra=SEED), s.power(ALPHA, 12, SEED), select="SELECT node, round(score, 8) AS score FROM power WHERE k = 12"),
    "power_trace": s.final(s.PEER, s.nodes(extra=SEED), s.power(ALPHA, 20, SEED), select="""
SELECT b.k, round(sum(abs(coalesce(b.score, 0) - coalesce(a.score, 0))), 8) AS residual FROM (SELECT k.range AS k, node, score FROM range(1, 21) k CROSS JOIN nodes n LEFT JOIN power p ON p.k = k.range AND p.node = n.node) b(k, node, score)
LEFT JOIN power a ON a.k = b.k - 1 AND a.node = b.node GROUP BY b.k""".replace("SELECT k.range AS k, node, score", "SELECT k.range AS k, n.node, p.score").replace("SELECT b.k,", "SELECT CAST(b.k AS INTEGER) AS k,")),
    "power_neumann": s.final(s.PEER, f"""
nm AS (SELECT 0 AS k, CAST({SEED} AS BIGINT) AS node, 1.0::DOUBLE AS x UNION ALL
  SELECT any_value(m.k) + 1, e.dst, sum({1 - ALPHA} * m.x * e.p) FROM nm m JOIN (SELECT src, dst, w / sum(w) OVER (PARTITION BY src) AS p FROM edges) e ON e.src = m.node WHERE m.k < {K} GROUP BY e.dst)""",
        select=f"SELECT node, round({ALPHA} * sum(x), 8) AS score FROM nm GROUP BY node"),
    "power_many_seeds": s.final(s.PEER, s.nodes(), *(s.power(ALPHA, K, i, name=f"power{i}") for i in range(3)), select=" UNION ALL ".join(f"SELECT {i}::BIGINT AS seed, node, round(score, 8) AS score FROM power{i} WHERE k = {K}" for i in range(3))),
    "power_early_stop": s.final(s.PEER, s.nodes(extra=SEED), s.power(ALPHA, K, SEED, init="uniform"), """
change AS (SELECT b.k, sum(abs(b.score - a.score)) AS r FROM power b JOIN power a ON a.k = b.k - 1 AND a.node = b.node GROUP BY b.k)""",
        select="SELECT node, round(score, 8) AS score FROM power WHERE k = (SELECT min(k) FROM change WHERE r < 0.01)"),
    "walks_visits": s.final(*_WALK, select=_ROWS),
    "walks_frontier": s.final(s.PEER, s.cdf(), s.starts([SEED], 40), s.walk(0.5), select=_ROWS),
    "walks_binned": s.final(s.PEER, s.cdf(), s.starts([SEED], 40), s.walk(0.5), select=_ROWS),
    "walks_recursive_sql": s.final(*_WALK, select=_ROWS),
    "walks_hop_limited": s.final(s.PEER, s.cdf(), s.starts([SEED], WALKS), s.walk(ALPHA, cap=3), select=_ROWS),
    "walks_scores": s.final(*_SCORED, select=_SCORE),
    "walks_endpoint_random": s.final(s.PEER, s.nodes(), s.cdf(), _RANDOM, s.walk(ALPHA), select=_ENDPOINT),
    "walks_endpoint_cyclic": s.final(s.PEER, s.nodes(), s.cdf(), _from_everywhere(3), s.walk(ALPHA), select=_ENDPOINT),
    "walks_path_jump": s.final(_LINKS, s.nodes(), s.cdf(), _LISTED, _from_everywhere(2), s.walk(ALPHA, jump="listed"), s.scores(), select=_SCORE),
    "walks_paths": s.final(*_WALK, select="SELECT walk_id, list(node ORDER BY step) AS path FROM walk GROUP BY walk_id"),
    "walks_path_stop_all": s.final(s.PEER, s.nodes(), s.cdf(), _from_everywhere(3), s.walk(ALPHA), s.scores(), select=_SCORE),
    "walks_path_random": s.final(s.PEER, s.nodes(), s.cdf(), _RANDOM, s.walk(ALPHA), s.scores(), select=_SCORE),
    "walks_many_seeds": s.final(s.PEER, s.cdf(), s.starts([0, 1, 2], 100), s.walk(ALPHA), select="SELECT seed, node, round(count(*) / sum(count(*)) OVER (PARTITION BY seed), 8) AS score FROM walk GROUP BY seed, node"),
    "walks_lengths": s.final(*_WALK, select="SELECT count(*) AS n_walks, CAST(sum(n) AS BIGINT) AS visits, round(avg(n), 8) AS mean_length, CAST(max(n) AS INTEGER) AS max_length FROM (SELECT count(*) AS n FROM walk GROUP BY walk_id)"),
    "walks_ends": s.final(*_WALK, select=f"""SELECT walk_id, CAST(length AS INTEGER) AS length, node, CASE WHEN node NOT IN (SELECT src FROM edges) THEN 'dangling' WHEN length > {walks.step_cap(ALPHA)} THEN 'cap' ELSE 'stop' END AS reason
FROM (SELECT walk_id, max(step) + 1 AS length, arg_max(node, step) AS node FROM walk GROUP BY walk_id)"""),
    "walks_visit_counts": s.final(*_WALK, select="SELECT walk_id, node, count(*) AS visits FROM walk GROUP BY walk_id, node"),
    "rank_top10": s.final(*_SCORED, select="SELECT CAST(row_number() OVER (ORDER BY score DESC, node) AS INTEGER) AS place, node, round(score, 8) AS score FROM scores QUALIFY place <= 10"),
    "rank_choose_peer": s.final(*_SCORED, s.nodes(), select="""SELECT CAST(row_number() OVER (ORDER BY coalesce(score, 0) DESC, node) AS INTEGER) AS place, node, round(coalesce(score, 0), 8) AS score
FROM (SELECT DISTINCT user_id AS node FROM events WHERE event_type = 'purchase') LEFT JOIN scores USING (node) QUALIFY place <= 5"""),
    "locality_hops": s.final(s.PEER, _BFS, select="SELECT node, hop FROM hops"),
    "locality_mass_by_hop": s.final(*_EXACT, _BFS, select="SELECT hop, count(*) AS nodes, round(sum(score), 6) AS mass FROM exact LEFT JOIN hops USING (node) GROUP BY hop"),
    "locality_mass_by_step": s.final(*_WALK, select=f"SELECT step, count(*) AS visits, round(count(*) / {float(WALKS)}, 8) AS share FROM walk GROUP BY step"),
    "metric_differences": s.final(*_EXACT, s.cdf(), s.starts([SEED], WALKS), s.walk(ALPHA), s.scores(), _BOTH, select="""SELECT round(sqrt(sum((x - y) * (x - y))), 8) AS l2, round(max(abs(x - y)), 8) AS linf, round(sum(abs(x - y)), 8) AS l1,
round(sqrt(sum((x - y) * (x - y))) / sqrt(sum(y * y)), 8) AS relative FROM both_"""),
    "metric_topk_error": s.final(*_EXACT, s.cdf(), s.starts([SEED], WALKS), s.walk(ALPHA), s.scores(), select="""SELECT round(avg(abs(coalesce(s.score, 0) - e.score) / e.score), 8) AS mean_relative_error
FROM (SELECT * FROM exact ORDER BY score DESC, node LIMIT 12) e LEFT JOIN scores s USING (node)"""),
    "metric_error_by_walks": s.final(*_EXACT, s.cdf(), s.starts([SEED], WALKS), s.walk(ALPHA), _GRID, select="""SELECT CAST(n_walks AS BIGINT) AS n_walks, round(sqrt(sum((x - y) * (x - y))), 8) AS l2, round(max(abs(x - y)), 8) AS linf,
round(sqrt(sum((x - y) * (x - y))) / sqrt(sum(y * y)), 8) AS relative FROM err GROUP BY n_walks"""),
    "metric_topk_agreement": s.final(*_EXACT, s.cdf(), s.starts([SEED], WALKS), s.walk(ALPHA), s.scores(), """
ta AS (SELECT node, row_number() OVER (ORDER BY score DESC, node) AS ra FROM scores QUALIFY ra <= 5),
tb AS (SELECT node, row_number() OVER (ORDER BY score DESC, node) AS rb, score AS sb FROM exact QUALIFY rb <= 5),
tt AS (SELECT node, coalesce(ra, 6) AS ra, coalesce(rb, 6) AS rb, coalesce(sb, 0) AS sb FROM ta FULL JOIN tb USING (node)),
pr AS (SELECT sign(i.ra - j.ra) AS da, sign(i.rb - j.rb) AS db FROM tt i JOIN tt j ON i.node < j.node)""", select="""
SELECT count(*) FILTER (WHERE ra <= 5 AND rb <= 5) / 5 AS precision, bool_and(rb > 5 OR ra = rb) AS same_order, round(corr(ra, rb), 8) AS spearman,
round(sum(CASE WHEN ra <= 5 THEN sb / log2(ra + 1) ELSE 0 END) / sum(CASE WHEN rb <= 5 THEN sb / log2(rb + 1) ELSE 0 END), 8) AS ndcg, (SELECT round(sum(da * db) / sqrt(sum(da * da) * sum(db * db)), 8) FROM pr) AS kendall FROM tt"""),
    "walks_confidence": s.final(*_WALK, """
per AS (SELECT walk_id, node, count(*) AS v FROM walk GROUP BY 1, 2),
len AS (SELECT walk_id, count(*) AS l FROM walk GROUP BY 1),
tot AS (SELECT count(*) AS n, sum(l) AS vis FROM len),
est AS (SELECT node, sum(v) / (SELECT vis FROM tot) AS score FROM per GROUP BY node),
dev AS (SELECT e.node, e.score, sum((coalesce(p.v, 0) - e.score * l.l) ** 2) AS sq FROM est e CROSS JOIN len l LEFT JOIN per p ON p.node = e.node AND p.walk_id = l.walk_id GROUP BY 1, 2),
se AS (SELECT node, score, sqrt(sq * n / (n - 1)) / vis AS se FROM dev, tot)""", select="SELECT node, round(score, 8) AS score, round(se, 8) AS se, round(score - 1.96 * se, 8) AS low, round(score + 1.96 * se, 8) AS high FROM se"),
    "walks_needed": f"SELECT CAST(e AS DOUBLE) AS eps, CAST(ceil(ln(2 / 0.05) / (2 * e * e) * {ALPHA}) AS BIGINT) AS n_walks FROM (SELECT DISTINCT l_discount AS e FROM lineitem WHERE l_discount > 0)",
    "metric_walk_work": s.final(*_WALK, select="SELECT gen, count(*) AS visits, count(DISTINCT walk_id) AS walks FROM walk GROUP BY gen"),
}
