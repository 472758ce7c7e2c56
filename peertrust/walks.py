"""Random walks with restart, as rows of visits.

A walk at a node: the visit is noted; without out-edges it ends; with probability
``alpha`` it ends; otherwise it hops along an out-edge in proportion to weight.
Coins and hops are hashes of ``(walk, gen, step)``, and hops pick from whole-number
intervals, so every strategy below gives the same rows:

* ``broadcast``: the adjacency, checked to be small enough, goes to all tasks and
  walks run there from end to end, all walks of a task in step.  No shuffle.  If the
  driver had better not hold it, one task gathers it and runs all walks, if these are few.
* ``frontier``: the ends of the walks meet the intervals in a join, a round a step.
  For graphs that fit no executor.
  Few walks on such a graph hop where the edges of their nodes are, in blocks of arrays.
* ``binned``: ``frontier`` on binned intervals, an equality join that a hub cannot
  blow up.
* ``recursive``: one recursive SQL query, for small graphs and short walks.

A walk may also go on from a dangling node, at one drawn from a table of nodes
(``jump``), with either of the first three.
"""

from __future__ import annotations

import functools
import hashlib
import math
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from peertrust import packed
from peertrust.functions.rng import RNG_SEED, TWO32, stop_limit, u32
from peertrust.packed import by_two
from peertrust.schemas import WALK
from peertrust.sources.tables import cut, numbered
from peertrust.transition import binned_cdf, cdf

#: Edges up to which the adjacency (12 to 24 bytes an edge) is sent to every task.
BROADCAST_EDGES = 8_000_000
#: Edges up to which the driver works on them itself; it only passes on larger graphs.
LOCAL_EDGES = 1_000_000
#: Walks up to which one task runs all of them, where the driver does not pass on the graph.
GATHERED_WALKS = 200_000


def step_cap(alpha: float, miss: float = 1e-9) -> int:
    """Steps that a walk outlives with probability ``miss``."""
    return math.ceil(math.log(miss) / math.log(1 - alpha))


class Adjacency:
    """Out-edges as arrays: hops of many walkers at once."""

    def __init__(self, src: np.ndarray, dst: np.ndarray, w: np.ndarray):
        order = by_two(src, dst)
        self.dst, w = dst[order], w[order].astype(np.int64)
        self.sources, first = np.unique(src[order], return_index=True)
        self.ends = np.cumsum(w)
        self.base = np.concatenate([[0], self.ends])[first] if len(first) else np.empty(0, np.int64)
        self.total = np.add.reduceat(w, first) if len(first) else np.empty(0, np.int64)
        if len(w) and (w.min() <= 0 or int(self.total.max()) >= 1 << 31):
            raise ValueError("weights must be positive, and those of a source sum to less than 2**31")

    def place(self, node: np.ndarray) -> np.ndarray:
        """Where each node stands among the sources, or -1."""
        if not len(self.sources):
            return np.full(len(node), -1)
        i = np.minimum(np.searchsorted(self.sources, node), len(self.sources) - 1)
        return np.where(self.sources[i] == node, i, -1)

    def hop(self, place: np.ndarray, draw: np.ndarray) -> np.ndarray:
        pick = draw * self.total[place] >> 32
        return self.dst[np.searchsorted(self.ends, self.base[place] + pick, side="right")].astype(np.int64)


def draws(seed: int, tag: str, walk: np.ndarray, gen: np.ndarray, step) -> np.ndarray:
    """The draws of ``functions.rng.u32`` for arrays of walks (and steps)."""
    step = np.broadcast_to(step, walk.shape).tolist()
    md5, head = hashlib.md5, f"{seed}|{tag}|"
    return np.array([int(md5(f"{head}{w}|{g}|{i}".encode()).hexdigest()[:8], 16) for w, g, i in zip(walk.tolist(), gen.tolist(), step, strict=True)], np.int64)


def run_walks(graph: Adjacency, tasks: pd.DataFrame, alpha: np.ndarray, rng_seed: int, cap: int, jump: np.ndarray | None = None) -> pd.DataFrame:
    """Visits behind the start of each task (``walk_id, seed, gen, step, node``).
    ``jump``: nodes among which a walker at a dangling node goes on."""
    out = []
    for start in np.unique(tasks["step"].to_numpy()) if len(tasks) else ():
        group = (tasks["step"] == start).to_numpy()
        walk, seed, gen, node = (tasks[c].to_numpy()[group] for c in ("walk_id", "seed", "gen", "node"))
        limit = np.array([stop_limit(a) for a in alpha[group]])
        for step in range(int(start), cap):
            if not len(walk):
                break
            at = graph.place(node)
            go = np.ones(len(walk), bool) if jump is not None else at >= 0
            go &= draws(rng_seed, "stop", walk, gen, step) >= limit
            walk, seed, gen, node, limit, at = (x[go] for x in (walk, seed, gen, node, limit, at))
            draw = draws(rng_seed, "hop", walk, gen, step)
            node = np.where(at >= 0, graph.hop(np.maximum(at, 0), draw), -1) if len(graph.sources) else np.full(len(walk), -1)
            if jump is not None and (lost := at < 0).any():
                node[lost] = jump[draw[lost] * len(jump) >> 32]
            out.append(pd.DataFrame({"walk_id": walk, "seed": seed, "gen": gen, "step": np.int32(step + 1), "node": node}))
    columns = {"walk_id": "int64", "seed": "int64", "gen": "int32", "step": "int32", "node": "int64"}
    return pd.concat(out)[list(columns)].astype(columns) if out else pd.DataFrame({c: pd.Series(dtype=t) for c, t in columns.items()})


def collected(df: DataFrame) -> pd.DataFrame:
    """``df`` on the driver, as Arrow columns and not as objects of Python."""
    return df.toArrow().to_pandas(split_blocks=True, self_destruct=True)


def _narrow(column: np.ndarray) -> np.ndarray:
    """Whole numbers in four bytes where they fit."""
    fits = not len(column) or (column.min() >= -(1 << 31) and column.max() < 1 << 31)
    return column.astype(np.int32) if fits else column


def local_edges(edges: DataFrame, limit: int | None = None) -> tuple[pd.DataFrame | None, DataFrame]:
    """The edges on the driver, if they are few enough to be broadcast, and the edges
    computed once.  They are counted before any is sent."""
    kept = edges if getattr(edges, "_peertrust_cut", False) else cut(edges.select("src", "dst", "w"))
    limit = BROADCAST_EDGES if limit is None else limit
    if getattr(kept, "_peertrust_rows", None) is None:
        kept._peertrust_rows = kept.count()
    if kept._peertrust_rows > limit:
        return None, kept
    if getattr(kept, "_peertrust_local", None) is None:
        rows = kept.select("src", "dst", "w").toArrow()
        kept._peertrust_local = pd.DataFrame({c: _narrow(rows.column(c).to_numpy()) for c in rows.column_names}, copy=False)
    return kept._peertrust_local, kept


def gathered(edges: DataFrame, work: Callable[[np.ndarray, np.ndarray, np.ndarray], pd.DataFrame], schema: str) -> DataFrame:
    """The rows of ``work`` on all edges (``src, dst, w``), computed once, in one task of an
    executor: the edges do not pass the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = [[_narrow(b.column(c).to_numpy()) for c in ("src", "dst", "w")] for b in batches]
        columns = [np.concatenate(c) for c in zip(*parts, strict=True)] or [np.empty(0, np.int32)] * 3
        del parts
        yield from pa.Table.from_pandas(work(*columns), preserve_index=False).to_batches(10_000)

    return cut(edges.select("src", "dst", "w").repartition(1).mapInArrow(run, schema))


def shared_edges(spark: SparkSession, found: pd.DataFrame, kept: DataFrame):
    """Collected edges as a broadcast of arrays, made once a frame."""
    if getattr(kept, "_peertrust_shared", None) is None:
        kept._peertrust_shared = spark.sparkContext.broadcast(tuple(found[c].to_numpy() for c in ("src", "dst", "w")))
    return kept._peertrust_shared


def starts(spark: SparkSession, seeds: list[int] | int, n_walks: int) -> DataFrame:
    """``n_walks`` walks from each seed; ``walk_id`` is unique over seeds."""
    seeds = [seeds] if isinstance(seeds, int) else list(seeds)
    table = F.array(*[F.lit(s).cast("long") for s in seeds])
    return spark.range(len(seeds) * n_walks).select(
        F.col("id").alias("walk_id"), table[F.floor(F.col("id") / n_walks).cast("int")].alias("seed"), F.lit(0).alias("gen"), F.lit(0).alias("step"), table[F.floor(F.col("id") / n_walks).cast("int")].alias("node")
    )


def starts_everywhere(node_table: DataFrame, each: int) -> DataFrame:
    """``each`` walks from every node."""
    i = F.explode(F.sequence(F.lit(0), F.lit(each - 1)))
    return node_table.select("node", i.alias("i")).select((F.col("node") * each + F.col("i")).alias("walk_id"), F.col("node").alias("seed"), F.lit(0).alias("gen"), F.lit(0).alias("step"), "node")


def starts_at_random(node_table: DataFrame, n_walks: int, rng_seed: int = RNG_SEED) -> DataFrame:
    """Walks from hashed places in the order of the nodes."""
    places = cut(numbered(node_table.select("node").distinct(), "node"))
    n = places.count()
    pick = F.shiftright(u32(rng_seed, "start", F.col("id"), F.lit(0), F.lit(0)) * F.lit(n), 32)
    drawn = node_table.sparkSession.range(n_walks).select(F.col("id").alias("walk_id"), pick.alias("place")).join(places, "place")
    return drawn.select("walk_id", F.col("node").alias("seed"), F.lit(0).alias("gen"), F.lit(0).alias("step"), "node")


def advance(edges: DataFrame, tasks: DataFrame, alpha: float, rng_seed: int = RNG_SEED, strategy: str = "auto", cap: int | None = None, jump: DataFrame | None = None) -> DataFrame:
    """Visits behind the start of each task.  ``jump``: a table of nodes, one of which a
    walker at a dangling node goes on from."""
    cap = step_cap(alpha) if cap is None else cap
    jump = None if jump is None else cut(jump.select("node").distinct())
    n_jump = 0 if jump is None else jump.count()
    if strategy in ("auto", "broadcast"):
        found, edges = local_edges(edges, min(LOCAL_EDGES, BROADCAST_EDGES))
        fits = max(edges._peertrust_rows, n_jump) <= BROADCAST_EDGES
        if not fits and strategy == "broadcast":
            raise ValueError(f"more than {BROADCAST_EDGES} edges or nodes cannot be broadcast")
        if fits:
            nodes = None if jump is None else np.sort(collected(jump)["node"].to_numpy())
            if found is None:
                tasks = cut(tasks.select("walk_id", "seed", "gen", "step", "node"))
                if tasks.count() <= GATHERED_WALKS:
                    few = collected(tasks)
                    return gathered(edges, lambda *e: run_walks(Adjacency(*e), few, np.full(len(few), alpha), rng_seed, cap, nodes), WALK)
                found, edges = local_edges(edges)
            shared = shared_edges(tasks.sparkSession, found, edges)

            def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
                graph = Adjacency(*shared.value)
                for part in parts:
                    yield run_walks(graph, part, np.full(len(part), alpha), rng_seed, cap, nodes)

            return tasks.select("walk_id", "seed", "gen", "step", "node").mapInPandas(run, WALK)
        if jump is None:
            tasks = cut(tasks.select("walk_id", "seed", "gen", "step", "node"))
            if tasks.count() <= GATHERED_WALKS:
                return _advance_few(edges, collected(tasks), alpha, rng_seed, cap)
        strategy = "binned"
    places = None if jump is None else cut(numbered(jump, "node").withColumnRenamed("node", "next"))
    table = cut(binned_cdf(cdf(edges)) if strategy == "binned" else cdf(edges))
    per_source = table.select("src", "tot", *(["bins"] if strategy == "binned" else [])).distinct()
    frontier, rounds = cut(tasks.select("walk_id", "seed", "gen", "step", "node")), []
    coin = u32(rng_seed, "stop", F.col("walk_id"), F.col("gen"), F.col("step"))
    draw = u32(rng_seed, "hop", F.col("walk_id"), F.col("gen"), F.col("step"))
    pick = F.shiftright(draw * F.col("tot"), 32)
    # until every walk has ended: at most ``cap`` rounds, checked each time
    for _ in range(cap):
        alive = frontier.filter(coin >= stop_limit(alpha)).filter(F.col("step") < cap)
        picked = alive.join(per_source.withColumnRenamed("src", "node"), "node").withColumn("pick", pick)
        if strategy == "binned":
            picked = picked.withColumn("bin", F.floor(F.col("pick") * F.col("bins") / F.col("tot")).cast("long"))
        t = table.select(F.col("src").alias("node"), F.col("dst").alias("next"), "lo", "hi", *(["bin"] if strategy == "binned" else []))
        joined = picked.join(t, ["node", "bin"] if strategy == "binned" else ["node"]).filter("lo <= pick AND pick < hi")
        hops = joined.select("walk_id", "seed", "gen", "step", "next")
        if places is not None:
            lost = alive.join(per_source.select(F.col("src").alias("node")), "node", "left_anti").withColumn("place", F.shiftright(draw * F.lit(n_jump), 32))
            hops = hops.union(lost.join(places, "place").select("walk_id", "seed", "gen", "step", "next"))
        frontier = cut(hops.select("walk_id", "seed", "gen", (F.col("step") + 1).cast("int").alias("step"), F.col("next").alias("node")))
        if frontier.isEmpty():
            break
        rounds.append(frontier)
    out = tasks.sparkSession.createDataFrame([], WALK)
    for r in rounds:
        out = out.union(r)
    return out


def _advance_few(edges: DataFrame, tasks: pd.DataFrame, alpha: float, rng_seed: int, cap: int) -> DataFrame:
    """Few walks on a large graph: all hop at once, each where its node's edges are."""
    spark, out = edges.sparkSession, []
    walk, seed, gen, step, node = (tasks[c].to_numpy().astype(np.int64) for c in ("walk_id", "seed", "gen", "step", "node"))
    while len(walk):
        go = (step < cap) & (draws(rng_seed, "stop", walk, gen, step) >= stop_limit(alpha))
        walk, seed, gen, step, node = (x[go] for x in (walk, seed, gen, step, node))
        if not len(walk):
            break
        to = packed.hops(edges, node, draws(rng_seed, "hop", walk, gen, step))
        walk, seed, gen, step, node = (x[to >= 0] for x in (walk, seed, gen, step + 1, to))
        out.append(pd.DataFrame({"walk_id": walk, "seed": seed, "gen": gen.astype(np.int32), "step": step.astype(np.int32), "node": node}))
    return spark.createDataFrame(pa.Table.from_pandas(pd.concat(out), preserve_index=False), WALK) if out else spark.createDataFrame([], WALK)


def simulate_walks(edges: DataFrame, seeds: list[int] | int, n_walks: int = 300, alpha: float = 0.3, rng_seed: int = RNG_SEED, strategy: str = "auto", max_steps: int | None = None) -> DataFrame:
    """All visits of ``n_walks`` walks from each seed."""
    spark = edges.sparkSession
    if strategy == "recursive":
        return recursive_walks(edges, seeds, n_walks, alpha, rng_seed, max_steps)
    first = starts(spark, seeds, n_walks)
    return first.unionByName(advance(edges, first, alpha, rng_seed, strategy, max_steps))


def simulate_runs(edges: DataFrame, seed: int, rng_seeds: list[int], n_walks: int = 300, alpha: float = 0.3) -> DataFrame:
    """``run`` (from 0) and the visits of ``simulate_walks`` with each of ``rng_seeds``; the
    adjacency is made once for all runs."""
    spark, cap = edges.sparkSession, step_cap(alpha)
    found, edges = local_edges(edges, min(LOCAL_EDGES, BROADCAST_EDGES))
    if edges._peertrust_rows > BROADCAST_EDGES or len(rng_seeds) * n_walks > GATHERED_WALKS:
        out = [simulate_walks(edges, seed, n_walks, alpha, s).withColumn("run", F.lit(i)) for i, s in enumerate(rng_seeds)]
        return functools.reduce(DataFrame.unionByName, out).select("run", "walk_id", "seed", "gen", "step", "node")
    first = pd.DataFrame({"walk_id": np.arange(n_walks), "seed": seed, "gen": np.int32(0), "step": np.int32(0), "node": seed})

    def work(*e: np.ndarray) -> pd.DataFrame:
        graph = Adjacency(*e)
        runs = [pd.concat([first, run_walks(graph, first, np.full(n_walks, alpha), s, cap)]) for s in rng_seeds]
        return pd.concat([r.assign(run=np.int32(i)) for i, r in enumerate(runs)], ignore_index=True)[["run", *first.columns]]

    schema = f"run int, {WALK}"
    if found is None:
        return gathered(edges, work, schema)
    return spark.createDataFrame(pa.Table.from_pandas(work(*(found[c].to_numpy() for c in ("src", "dst", "w"))), preserve_index=False), schema)


def recursive_walks(edges: DataFrame, seed: int, n_walks: int, alpha: float, rng_seed: int = RNG_SEED, max_steps: int | None = None) -> DataFrame:
    """The walks as one recursive query."""
    spark, cap = edges.sparkSession, step_cap(alpha) if max_steps is None else max_steps
    levels = int(spark.conf.get("spark.sql.cteRecursionLevelLimit", "100"))
    if cap >= levels:
        raise ValueError(f"walks of up to {cap} steps need more than the {levels} levels of spark.sql.cteRecursionLevelLimit; use another strategy or max_steps")
    cdf(edges).createOrReplaceTempView("walk_intervals")
    draw = "CAST(conv(substring(md5(concat_ws('|', '{}', '{}', w.walk_id, 0, w.step)), 1, 8), 16, 10) AS BIGINT)"
    stop, hop = draw.format(rng_seed, "stop"), draw.format(rng_seed, "hop")
    return spark.sql(f"""
        WITH RECURSIVE w(walk_id, seed, gen, step, node) AS (
          SELECT id, CAST({seed} AS BIGINT), 0, 0, CAST({seed} AS BIGINT) FROM range({n_walks})
          UNION ALL
          SELECT w.walk_id, w.seed, w.gen, w.step + 1, c.dst FROM w JOIN walk_intervals c ON c.src = w.node
          WHERE {stop} >= {stop_limit(alpha)} AND w.step < {cap} AND shiftright({hop} * c.tot, 32) >= c.lo AND shiftright({hop} * c.tot, 32) < c.hi)
        SELECT walk_id, seed, gen, step, node FROM w""")


def walk_ends(walks: DataFrame, edges: DataFrame, cap: int) -> DataFrame:
    """``walk_id, length, node, reason``: how each walk ended."""
    last = walks.groupBy("walk_id").agg(F.max_by("node", "step").alias("node"), (F.max("step") + 1).alias("length"))
    sources = edges.select(F.col("src").alias("node"), F.lit(True).alias("goes_on")).distinct()
    reason = F.when(F.col("goes_on").isNull(), "dangling").when(F.col("length") > cap, "cap").otherwise("stop")
    return last.join(sources, "node", "left").select("walk_id", "length", "node", reason.alias("reason"))


def paths(walks: DataFrame) -> DataFrame:
    """``walk_id, path``: the nodes of each walk in the order of its steps."""
    visits = F.array_sort(F.collect_list(F.struct("step", "node")))
    return walks.groupBy("walk_id").agg(F.transform(visits, lambda v: v["node"]).alias("path"))


__all__ = ["Adjacency", "TWO32", "advance", "recursive_walks", "simulate_walks", "starts", "starts_at_random", "starts_everywhere", "step_cap", "walk_ends"]
