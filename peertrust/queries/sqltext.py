"""Pieces of independent SQL (DuckDB) that must give the same rows."""

from __future__ import annotations

from peertrust.functions.rng import RNG_SEED, stop_limit, u32_sql
from peertrust.walks import step_cap

TRANSFERS = """
np AS (SELECT count(DISTINCT user_id) AS n FROM events),
tr AS (SELECT * FROM (
  SELECT event_id AS id, user_id AS p, (user_id + 1 + CAST(json_extract_string(props, '$.k') AS BIGINT)) % n AS q,
    CASE WHEN event_type IN ('click', 'view', 'purchase') THEN CAST(round(value * 100) AS BIGINT) ELSE 0 END AS up,
    CASE WHEN event_type IN ('error', 'signup') THEN CAST(round(value * 100) AS BIGINT) ELSE 0 END AS down, ts, event_type AS kind
  FROM events, np) WHERE p <> q)"""

PAIRS = """
pn AS (SELECT least(p, q) AS a, greatest(p, q) AS b, CAST(sum(CASE WHEN p < q THEN up - down ELSE down - up END) AS BIGINT) AS net FROM tr GROUP BY 1, 2)"""

EDGES = """
edges AS (SELECT CASE WHEN net > 0 THEN b ELSE a END AS src, CASE WHEN net > 0 THEN a ELSE b END AS dst, abs(net) AS w FROM pn WHERE net <> 0)"""

PEER = ",".join((TRANSFERS, PAIRS, EDGES))


def cdf(edges: str = "edges", name: str = "cdf") -> str:
    return f"""
{name} AS (SELECT src, dst, w, CAST(sum(w) OVER (PARTITION BY src ORDER BY dst) AS BIGINT) - w AS lo,
  CAST(sum(w) OVER (PARTITION BY src ORDER BY dst) AS BIGINT) AS hi, CAST(sum(w) OVER (PARTITION BY src) AS BIGINT) AS tot FROM {edges})"""


def starts(seeds: list[int], n: int, name: str = "starts") -> str:
    rows = ", ".join(f"({i}, {s})" for i, s in enumerate(seeds))
    return f"""
{name} AS (SELECT s.i * {n} + r.range AS walk_id, CAST(s.seed AS BIGINT) AS seed, 0 AS gen, 0 AS step, CAST(s.seed AS BIGINT) AS node FROM (VALUES {rows}) s(i, seed), range({n}) r)"""


def walk(alpha: float, begin: str = "starts", table: str = "cdf", name: str = "walk", cap: int | None = None, seed: int = RNG_SEED, jump: str | None = None) -> str:
    """``jump``: a table ``node, i`` in which a walker at a dangling node goes on."""
    cap = step_cap(alpha) if cap is None else cap
    stop, hop = u32_sql(seed, "stop", "w.walk_id", "w.gen", "w.step"), u32_sql(seed, "hop", "w.walk_id", "w.gen", "w.step")
    if jump:
        return f"""
{name}_d AS (SELECT node FROM nodes EXCEPT SELECT src FROM {table}),
{name} AS (SELECT walk_id, seed, gen, step, node FROM {begin} UNION ALL
  SELECT w.walk_id, w.seed, w.gen, w.step + 1, CASE WHEN d.node IS NULL THEN c.dst ELSE j.node END FROM {name} w LEFT JOIN {name}_d d ON d.node = w.node
  LEFT JOIN {table} c ON c.src = w.node AND ({hop} * c.tot) >> 32 >= c.lo AND ({hop} * c.tot) >> 32 < c.hi LEFT JOIN {jump} j ON d.node IS NOT NULL AND j.i = ({hop} * (SELECT count(*) FROM {jump})) >> 32
  WHERE {stop} >= {stop_limit(alpha)} AND w.step < {cap})"""
    return f"""
{name} AS (SELECT walk_id, seed, gen, step, node FROM {begin} UNION ALL
  SELECT w.walk_id, w.seed, w.gen, w.step + 1, c.dst FROM {name} w JOIN {table} c ON c.src = w.node
  WHERE {stop} >= {stop_limit(alpha)} AND w.step < {cap} AND ({hop} * c.tot) >> 32 >= c.lo AND ({hop} * c.tot) >> 32 < c.hi)"""


def scores(walks: str = "walk", name: str = "scores") -> str:
    return f"""
{name} AS (SELECT node, count(*) / (SELECT count(*) FROM {walks}) AS score FROM {walks} GROUP BY node)"""


def nodes(edges: str = "edges", name: str = "nodes", extra: int | None = None) -> str:
    more = f" UNION SELECT {extra}" if extra is not None else ""
    return f"""
{name} AS (SELECT src AS node FROM {edges} UNION SELECT dst FROM {edges}{more})"""


def power(alpha: float, rounds: int, seed: int | None, dangling: str = "seed", weighting: str = "weight", init: str = "seed", edges: str = "edges", node_table: str = "nodes", name: str = "power") -> str:
    """Scores after each round, ``k, node, score``; reset and lost mass are entries
    of one sparse matrix, so a round is one join and one sum."""
    p = "w / sum(w) OVER (PARTITION BY src)" if weighting == "weight" else "1.0 / count(*) OVER (PARTITION BY src)"
    target = f"(SELECT CAST({seed} AS BIGINT) AS node, 1.0 AS t)" if seed is not None else f"(SELECT node, 1.0 / (SELECT count(*) FROM {node_table}) AS t FROM {node_table})"
    uniform = f"(SELECT node, 1.0 / (SELECT count(*) FROM {node_table}) AS t FROM {node_table})"
    stuck = f"(SELECT node FROM {node_table} EXCEPT SELECT src FROM {edges})"
    parts = [f"SELECT src, dst, {1 - alpha} * p AS p FROM (SELECT src, dst, {p} AS p FROM {edges})"]
    if dangling == "drop":
        # a node of its own keeps mass 1 and sends the reset
        parts += ["SELECT -9, -9, 1.0", f"SELECT -9, t.node, {alpha} * t.t FROM {target} t"]
        first = f"SELECT 0 AS k, CAST(node AS BIGINT) AS node, CAST(t AS DOUBLE) AS score FROM {target} UNION ALL SELECT 0, -9, 1.0"
    else:
        parts.append(f"SELECT n.node, t.node, {alpha} * t.t FROM {node_table} n, {target} t")
        parts.append(f"SELECT s.node, t.node, {1 - alpha} * t.t FROM {stuck} s, {target if dangling == 'seed' else uniform} t")
        first = f"SELECT 0 AS k, CAST(node AS BIGINT) AS node, CAST(t AS DOUBLE) AS score FROM {target if init == 'seed' else uniform}"
    return f"""
{name}_m AS (SELECT src, dst, sum(p) AS p FROM ({' UNION ALL '.join(parts)}) GROUP BY src, dst),
{name} AS ({first} UNION ALL SELECT any_value(x.k) + 1, m.dst, sum(x.score * m.p) FROM {name} x JOIN {name}_m m ON m.src = x.node WHERE x.k < {rounds} GROUP BY m.dst)"""


def final(*ctes: str, select: str) -> str:
    return "WITH RECURSIVE " + ",".join(ctes) + "\n" + select
