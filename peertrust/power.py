"""Power iteration: the exact baseline, global and personalized.

``dangling`` says where the mass of nodes without out-edges goes: back to the seed
(``seed``, the law of walks that stop there), to all nodes (``uniform``), or nowhere
(``drop``: the vector is normalised at the end).

Small graphs (counted first) are solved in one task per ``(seed, alpha)``, or, if the
driver had better not hold them, by one task that gathers them; larger ones
iterate a join and an aggregation for all pairs at once.  While the vector is small
(counted, too) it is broadcast to the edges, which then stay where they are.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peertrust import packed, walks
from peertrust.graph import nodes as graph_nodes
from peertrust.sources.tables import cut
from peertrust.transition import transitions
from peertrust.walks import LOCAL_EDGES, gathered, local_edges

ROUNDS = 40
#: Scores up to which a round broadcasts them (some 40 bytes each).
BROADCAST_SCORES = 1_000_000
#: Pairs of seed and reset probability up to which the task that gathers a graph solves all.
GATHERED_PAIRS = 3


def _places(node: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Where each of ``of`` stands among the sorted nodes."""
    if not len(node) or node[0] < 0 or node[-1] > 4 * len(of) + 1_000_000:
        return np.searchsorted(node, of)
    place = np.zeros(int(node[-1]) + 1, np.int64)
    place[node] = np.arange(len(node))
    return place[of]


def solve(src: np.ndarray, dst: np.ndarray, w: np.ndarray, node: np.ndarray, seed: int | None, alpha: float, dangling: str, rounds: int, tol: float | None = None, init: str = "seed", weighting: str = "weight") -> tuple[np.ndarray, list[float]]:
    """Scores of ``node`` (sorted), and the change of each round."""
    n = len(node)
    s, d = _places(node, src), _places(node, dst)
    w = w.astype(float) if weighting == "weight" else np.ones(len(w))
    out = np.bincount(s, weights=w, minlength=n)
    p = w / out[s]
    stuck = out == 0
    reset = np.full(n, 1.0 / n)
    if seed is not None:
        reset = (node == seed).astype(float)
        if not reset.any():
            raise ValueError(f"seed {seed} is no node of the graph")
    x = reset.copy() if init == "seed" else np.full(n, 1.0 / n)
    trace = []
    for _ in range(rounds):
        y = (1 - alpha) * np.bincount(d, weights=x[s] * p, minlength=n)
        lost = (1 - alpha) * x[stuck].sum()
        y += alpha * reset
        if dangling == "seed":
            y += lost * reset
        elif dangling == "uniform":
            y += lost / n
        trace.append(float(np.abs(y - x).sum()))
        x = y
        if tol is not None and trace[-1] < tol:
            break
    return (x / x.sum() if dangling == "drop" else x), trace


def _arrays(edges: DataFrame, extra: list[int] = (), limit: int | None = None):
    """Edges and nodes as arrays (None: too many), and the edges computed once."""
    found, edges = local_edges(edges, limit)
    if found is None:
        return None, edges
    src, dst, w = (found[c].to_numpy() for c in ("src", "dst", "w"))
    return (src, dst, w, np.unique(np.concatenate([np.unique(src), np.unique(dst), np.array(extra, np.int64)]))), edges


def _own_limit() -> int:
    """Edges up to which the driver iterates itself."""
    return min(LOCAL_EDGES, walks.BROADCAST_EDGES)


def power_iteration_many(edges: DataFrame, seeds: list[int | None], alphas: list[float], dangling: str = "seed", rounds: int = ROUNDS, **options) -> DataFrame:
    """``seed, alpha, node, score`` for every pair; a task solves one pair.  A seed
    without edges is a node of its own."""
    spark = edges.sparkSession
    extra, few = [s for s in seeds if s is not None], len(seeds) * len(alphas) <= GATHERED_PAIRS
    arrays, edges = _arrays(edges, extra, _own_limit() if few else None)
    if arrays is None and edges._peertrust_rows <= walks.BROADCAST_EDGES:

        def work(src: np.ndarray, dst: np.ndarray, w: np.ndarray) -> pd.DataFrame:
            node = np.unique(np.concatenate([np.unique(src), np.unique(dst), np.array(extra, np.int64)]))
            out = [pd.DataFrame({"seed": pd.array([s] * len(node), "Int64"), "alpha": float(a), "node": node, "score": solve(src, dst, w, node, s, a, dangling, rounds, **options)[0]}) for s in seeds for a in alphas]
            return pd.concat(out, ignore_index=True)

        return gathered(edges, work, "seed long, alpha double, node long, score double")
    if arrays is None:
        return distributed_power(edges, [(s, float(a)) for s in seeds for a in alphas], dangling, rounds, **options)[0]
    shared = spark.sparkContext.broadcast(arrays)
    grid = spark.createDataFrame([(s, float(a)) for s in seeds for a in alphas], "seed long, alpha double").repartition(max(1, len(seeds) * len(alphas)))

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for part in parts:
            for s, a in part.itertuples(index=False):
                s = None if pd.isna(s) else int(s)
                node = shared.value[3]
                score, _ = solve(*shared.value, s, a, dangling, rounds, **options)
                yield pd.DataFrame({"seed": pd.Series([s] * len(node), dtype="Int64"), "alpha": a, "node": node, "score": score})

    return grid.mapInPandas(run, "seed long, alpha double, node long, score double")


def power_iteration(edges: DataFrame, seed: int | None = None, alpha: float = 0.3, dangling: str | None = None, rounds: int = ROUNDS, tol: float | None = None, init: str = "seed", weighting: str = "weight", distributed: bool | None = None) -> DataFrame:
    """``node, score``; ``seed`` None is the global ranking."""
    dangling = dangling or ("uniform" if seed is None else "seed")
    options = {"tol": tol, "init": init, "weighting": weighting}
    if distributed:
        return distributed_power(edges, [(seed, alpha)], dangling, rounds, **options)[0].select("node", "score")
    return power_iteration_many(edges, [seed], [alpha], dangling, rounds, **options).select("node", "score")


def distributed_power(edges: DataFrame, grid: list[tuple[int | None, float]], dangling: str, rounds: int = ROUNDS, tol: float | None = None, init: str = "seed", weighting: str = "weight", every: int = 5) -> tuple[DataFrame, dict[int, list[float]]]:
    """``seed, alpha, node, score`` for every pair of ``grid``, and the changes that were
    looked at, by its place.  Scores meet transitions on ``src``, sums go to ``dst``
    with map-side combining.  Lineage is cut each ``every`` rounds; with ``tol`` every
    round is looked at, and a pair stops changing once its change is below."""
    spark = edges.sparkSession
    counted = getattr(edges, "_peertrust_rows", None)
    if tol is None and counted is not None and counted > walks.BROADCAST_EDGES:
        found = _by_blocks(edges, grid, dangling, rounds, init, weighting, every)
        if found is not None:
            return found
    every = 1 if tol is not None else every
    seeds = spark.createDataFrame(sorted({(s,) for s, _ in grid if s is not None}), "node long")
    node = cut(graph_nodes(edges).union(seeds).distinct())
    n = node.count()
    pairs = F.broadcast(spark.createDataFrame([(i, s, float(a)) for i, (s, a) in enumerate(grid)], "i int, seed long, alpha double"))
    pt = cut(transitions(edges, weighting).repartition("src"))
    sources = pt.select(F.col("src").alias("node"), F.lit(True).alias("goes_on")).distinct()
    reset = F.when(F.col("seed").isNull(), F.lit(1.0 / n)).when(F.col("node") == F.col("seed"), 1.0).otherwise(0.0)
    base = node.join(sources, "node", "left").select("node", F.col("goes_on").isNull().alias("stuck")).join(pairs, how="cross")
    x = cut(base.select("i", "node", "stuck", "alpha", reset.alias("reset")).withColumn("score", F.lit(1.0 / n) if init == "uniform" else F.col("reset")))
    small = n * len(grid) <= BROADCAST_SCORES
    traces: dict[int, list[float]] = {i: [] for i in range(len(grid))}
    done: list[int] = []
    for k in range(rounds):
        vector = x.select("i", "node", "score")
        flow = (F.broadcast(vector) if small else vector).join(pt, F.col("node") == pt.src).groupBy("i", "dst").agg(F.sum(F.col("score") * F.col("p")).alias("inflow"))
        lost = x.filter("stuck").groupBy(F.col("i").alias("j")).agg(F.sum("score").alias("lost"))  # a row a pair
        back = F.coalesce("lost", F.lit(0.0)) * (F.col("reset") if dangling == "seed" else F.lit(1.0 / n)) if dangling != "drop" else F.lit(0.0)
        new = (1 - F.col("alpha")) * (F.coalesce("inflow", F.lit(0.0)) + back) + F.col("alpha") * F.col("reset")
        to = flow.select(F.col("i").alias("fi"), "dst", "inflow")
        joined = x.withColumnRenamed("score", "old").join(to, (F.col("i") == F.col("fi")) & (F.col("node") == F.col("dst")), "left").join(F.broadcast(lost), F.col("i") == F.col("j"), "left")
        score = F.when(F.col("i").isin(done), F.col("old")).otherwise(new) if done else new
        step = joined.select("i", "node", "stuck", "alpha", "reset", "old", score.alias("score"))
        if k % every == every - 1 or k == rounds - 1:
            step = cut(step)
            for r in step.groupBy("i").agg(F.sum(F.abs(F.col("score") - F.col("old"))).alias("change")).collect():  # a row a pair
                if r.i not in done:
                    traces[r.i].append(r.change)
                    if tol is not None and r.change < tol:
                        done.append(r.i)
        x = step.drop("old")
        if len(done) == len(grid):
            break
    if dangling == "drop":
        total = x.groupBy(F.col("i").alias("j")).agg(F.sum("score").alias("total"))
        x = x.join(F.broadcast(total), F.col("i") == F.col("j")).withColumn("score", F.col("score") / F.col("total"))
    out = x.select("i", "node", "score").join(pairs, "i")
    return out.select("seed", "alpha", "node", "score"), traces


def _by_blocks(edges: DataFrame, grid: list[tuple[int | None, float]], dangling: str, rounds: int, init: str, weighting: str, every: int) -> tuple[DataFrame, dict[int, list[float]]] | None:
    """``distributed_power`` with the edges as blocks of arrays by target, which stay where
    they are; the driver holds the vectors.  None if these are counted to be large."""
    spark = edges.sparkSession
    out = cut(packed.out_weights(edges, weighting))
    extra = spark.createDataFrame(sorted({(s,) for s, _ in grid if s is not None}), "node long")
    names = cut(out.select("node").union(packed.targets(edges)).union(extra).distinct())
    n = names.count()
    if n * len(grid) > BROADCAST_SCORES:
        return None
    node, sources = np.sort(walks.collected(names)["node"].to_numpy()), walks.collected(out)
    total = np.zeros(n)
    total[np.searchsorted(node, sources["node"].to_numpy())] = sources["out"].to_numpy()
    stuck, blocks = total == 0, packed.placed(edges, node)
    reset = np.array([np.full(n, 1.0 / n) if s is None else (node == s).astype(float) for s, _ in grid])
    alpha = np.array([[a] for _, a in grid])
    x = np.full((len(grid), n), 1.0 / n) if init == "uniform" else reset
    traces: dict[int, list[float]] = {i: [] for i in range(len(grid))}
    for k in range(rounds):
        y = packed.flows(blocks, np.where(stuck, 0.0, x / np.where(stuck, 1.0, total)), weighting)
        if dangling != "drop":
            y += x[:, stuck].sum(axis=1, keepdims=True) * (reset if dangling == "seed" else 1.0 / n)
        y = (1 - alpha) * y + alpha * reset
        if k % every == every - 1 or k == rounds - 1:
            for i, change in enumerate(np.abs(y - x).sum(axis=1).tolist()):
                traces[i].append(change)
        x = y
    if dangling == "drop":
        x = x / x.sum(axis=1, keepdims=True)
    rows = pa.concat_tables(pa.table({"seed": pa.array([s] * n, pa.int64()), "alpha": pa.array(np.full(n, a)), "node": node, "score": v}) for (s, a), v in zip(grid, x, strict=True))
    return spark.createDataFrame(rows, "seed long, alpha double, node long, score double"), traces


def residual_trace(edges: DataFrame, seed: int | None, alpha: float, rounds: int = ROUNDS, tol: float | None = None, dangling: str = "seed", init: str = "seed") -> DataFrame:
    """``k, residual``: the change that each round makes."""
    arrays, edges = _arrays(edges, [] if seed is None else [seed], _own_limit())
    trace = solve(*arrays, seed, alpha, dangling, rounds, tol, init)[1] if arrays else distributed_power(edges, [(seed, alpha)], dangling, rounds, tol, init, every=1)[1][0]
    return edges.sparkSession.createDataFrame([(i + 1, r) for i, r in enumerate(trace)], "k int, residual double")


def neumann_scores(edges: DataFrame, seed: int, alpha: float, terms: int = ROUNDS) -> DataFrame:
    """``alpha`` times the sum of ``((1 - alpha) P)**k`` from the seed, cut off after
    ``terms``: expected visits of a walk, times ``alpha``."""
    arrays, edges = _arrays(edges, [seed], _own_limit())
    if arrays is None:
        return _neumann_distributed(edges, seed, alpha, terms)
    src, dst, w, node = arrays
    s, d = np.searchsorted(node, src), np.searchsorted(node, dst)
    p = w / np.bincount(s, weights=w, minlength=len(node))[s]
    x = (node == seed).astype(float)
    total = np.zeros(len(node))
    for _ in range(terms + 1):
        total += alpha * x
        x = (1 - alpha) * np.bincount(d, weights=x[s] * p, minlength=len(node))
    return edges.sparkSession.createDataFrame(pd.DataFrame({"node": node, "score": total}))


def _neumann_distributed(edges: DataFrame, seed: int, alpha: float, terms: int, every: int = 5) -> DataFrame:
    spark = edges.sparkSession
    pt = cut(transitions(edges).repartition("src"))
    x = total = spark.createDataFrame([(seed, 1.0)], "node long, score double")
    for k in range(terms):
        x = x.join(pt, x.node == pt.src).groupBy(F.col("dst").alias("node")).agg(((1 - alpha) * F.sum(F.col("score") * F.col("p"))).alias("score"))
        if k % every == every - 1:
            x = cut(x)
        total = total.union(x)
        if k % every == every - 1:
            total = cut(total.groupBy("node").agg(F.sum("score").alias("score")))
    summed = total.groupBy("node").agg((alpha * F.sum("score")).alias("score"))
    everyone = graph_nodes(edges).union(spark.createDataFrame([(seed,)], "node long")).distinct()
    return everyone.join(summed, "node", "left").select("node", F.coalesce("score", F.lit(0.0)).alias("score"))
