"""Keeping walks up to date as the graph changes.

All walks are kept; a change re-routes the suffixes that it touches.  A walk is cut
at its earliest affected visit, over all changes of a batch, and goes on from there
on the new graph with a generation of its own, so its draws are fresh.

Policies.
* ``source_visit``: every walk that visits a changed source is cut at its first
  visit there and redrawn from that visit on, stop coin included.
* ``coupling``: a hop of the old law is kept with probability
  ``min(1, p_new / p_old)`` and otherwise redrawn from what the new law has more of.
  Exact too, for any change, and it touches far fewer walks.
* ``coin``, for edges that arrive or grow: every visit of a changed source flips a
  coin that turns it to one of the grown edges with their share of the new weight;
  walks without such a turn stay.
* ``crossing``, for edges that leave: only walks that crossed one of them are cut, at
  the first crossing, and hop again by the new law; all others already have it.
A walk that ended for want of out-edges flips its stop coin when it gets some.

Graphs and walks that are small (counted first) are updated in one place, as arrays
(``local_update``); the rows are the same.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from peertrust import packed
from peertrust.functions.rng import RNG_SEED, TWO32, stop_limit, u32
from peertrust.graph import diff_edges
from peertrust.schemas import WALK
from peertrust.sources.tables import cut
from peertrust.transition import cdf, transitions
from peertrust.walks import LOCAL_EDGES, Adjacency, advance, collected, draws, local_edges, run_walks, step_cap

POLICIES = ("source_visit", "coupling", "coin", "crossing")


def expand_changes(ops: DataFrame, edges: DataFrame) -> DataFrame:
    """``op, src, dst, w_old, w_new`` per edge from operations on edges and nodes:
    ``drop_node`` (in ``src``) takes all its edges, ``flip`` removes an edge and adds
    its reverse.  ``add_node`` stays a row of its own, without ``dst``: it changes the
    nodes and no edge."""
    plain = ops.filter(F.col("op").isin("add", "remove", "reweight")).select("op", "src", "dst", "w_old", "w_new")
    flips = ops.filter("op = 'flip'")
    away = flips.select(F.lit("remove").alias("op"), "src", "dst", "w_old", F.lit(None).cast("long").alias("w_new"))
    back = flips.select(F.lit("add").alias("op"), F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(None).cast("long").alias("w_old"), "w_new")
    gone = ops.filter("op = 'drop_node'").select(F.col("src").alias("_n")).distinct()
    lost = edges.join(F.broadcast(gone), (edges.src == F.col("_n")) | (edges.dst == F.col("_n"))).select(F.lit("remove").alias("op"), "src", "dst", F.col("w").alias("w_old"), F.lit(None).cast("long").alias("w_new")).distinct()
    null = F.lit(None).cast("long")
    come = ops.filter("op = 'add_node'").select("op", "src", null.alias("dst"), null.alias("w_old"), null.alias("w_new")).distinct()
    return plain.unionByName(away).unionByName(back).unionByName(lost).unionByName(come)


def apply_to_edges(edges: DataFrame, changes: DataFrame) -> DataFrame:
    """The graph after ``changes``."""
    new = changes.filter("dst IS NOT NULL").select("src", "dst", F.struct("w_new").alias("c")).groupBy("src", "dst").agg(F.first("c").alias("c"))
    both = edges.join(new, ["src", "dst"], "full_outer")
    return both.select("src", "dst", F.when(F.col("c").isNotNull(), F.col("c.w_new")).otherwise(F.col("w")).alias("w")).filter("w > 0")


def apply_to_nodes(nodes: DataFrame, ops: DataFrame) -> DataFrame:
    """The nodes after operations: added ones, and ends of added edges, without those
    dropped."""
    more = ops.filter("op = 'add_node'").select(F.col("src").alias("node")).union(ops.filter("op IN ('add', 'flip')").select(F.explode(F.array("src", "dst")).alias("node")))
    gone = ops.filter("op = 'drop_node'").select(F.col("src").alias("node"))
    return nodes.select("node").union(more).distinct().join(gone, "node", "left_anti")


def changed_sources(old: DataFrame, new: DataFrame) -> DataFrame:
    """Sources whose hop law differs between two graphs."""
    return diff_edges(old, new).select(F.col("src").alias("node")).distinct()


def affected(walks: DataFrame, sources: DataFrame) -> DataFrame:
    """``walk_id, cut``: the first visit of each walk to a changed source."""
    return walks.join(sources, "node", "left_semi").groupBy("walk_id").agg(F.min("step").alias("cut"))


def _one_sided(diff: DataFrame, arrive: bool) -> None:
    wrong = diff.filter("w_old IS NOT NULL AND (w_new IS NULL OR w_new < w_old)" if arrive else "w_new IS NOT NULL")
    if not wrong.isEmpty():
        raise ValueError("coin is for edges that arrive or grow" if arrive else "crossing is for edges that leave")


def _coin_cuts(walks: DataFrame, old: DataFrame, new: DataFrame, gen: int, alpha: float, rng_seed: int) -> DataFrame:
    """``walk_id, cut, node, next`` of walks that a coin turns to a grown edge."""
    diff = cut(diff_edges(old, new))
    _one_sided(diff, True)
    order = Window.partitionBy("src").orderBy("next")
    grown = diff.select("src", F.col("dst").alias("next"), (F.col("w_new") - F.coalesce("w_old", F.lit(0))).alias("g"))
    grown = cut(grown.withColumn("hi", F.sum("g").over(order.rowsBetween(Window.unboundedPreceding, 0))).withColumn("lo", F.col("hi") - F.col("g")))
    total = new.groupBy("src").agg(F.sum("w").alias("tot"))
    state = grown.groupBy("src").agg(F.sum("g").alias("grown")).join(total, "src").select(F.col("src").alias("node"), "grown", "tot")
    visits = walks.withColumn("dst", F.lead("node").over(Window.partitionBy("walk_id").orderBy("step"))).join(state, "node")
    draw = lambda tag: u32(rng_seed, tag, F.col("walk_id"), F.lit(gen), F.col("step"))
    pick = F.shiftright(draw("coin") * F.col("tot"), 32)
    turned = F.col("dst").isNotNull() & (pick < F.col("grown"))
    woken = F.col("dst").isNull() & (F.col("grown") == F.col("tot")) & (draw("wake") >= stop_limit(alpha))
    hit = visits.filter(turned | woken).select("walk_id", "step", "node", pick.alias("pick")).groupBy("walk_id").agg(F.min(F.struct("step", "node", "pick")).alias("v")).select("walk_id", "v.*")
    chosen = hit.join(grown.withColumnRenamed("src", "node"), "node").filter("lo <= pick AND pick < hi")
    return chosen.select("walk_id", F.col("step").alias("cut"), "node", "next")


def _crossing_cuts(walks: DataFrame, old: DataFrame, new: DataFrame, gen: int, rng_seed: int) -> DataFrame:
    """``walk_id, cut, node, next`` of walks that crossed an edge that is gone."""
    diff = cut(diff_edges(old, new))
    _one_sided(diff, False)
    lost = diff.select(F.col("src").alias("node"), "dst")
    hops = walks.withColumn("dst", F.lead("node").over(Window.partitionBy("walk_id").orderBy("step")))
    hit = hops.join(lost, ["node", "dst"], "left_semi").groupBy("walk_id").agg(F.min(F.struct("step", "node")).alias("v")).select("walk_id", "v.step", "v.node")
    law = cdf(new.join(lost.select(F.col("node").alias("src")).distinct(), "src", "left_semi")).select(F.col("src").alias("node"), F.col("dst").alias("next"), "lo", "hi", "tot")
    pick = F.shiftright(u32(rng_seed, "move", F.col("walk_id"), F.lit(gen), F.col("step")) * F.col("tot"), 32)
    chosen = hit.join(law, "node", "left").filter(F.col("tot").isNull() | ((pick >= F.col("lo")) & (pick < F.col("hi"))))
    return chosen.select("walk_id", F.col("step").alias("cut"), "node", "next")


def _cuts(walks: DataFrame, old: DataFrame, new: DataFrame, gen: int, alpha: float, rng_seed: int) -> DataFrame:
    """``walk_id, cut, node, next``: earliest visit that the coupling changes; the
    redrawn next node, or null where the walk now ends there."""
    sources = cut(changed_sources(old, new))
    p_old = transitions(old).join(sources.withColumnRenamed("node", "src"), "src", "left_semi").withColumnRenamed("p", "p_old")
    p_new = transitions(new).join(sources.withColumnRenamed("node", "src"), "src", "left_semi").withColumnRenamed("p", "p_new")
    law = cut(p_old.join(p_new, ["src", "dst"], "full_outer").select("src", "dst", F.coalesce("p_old", F.lit(0.0)).alias("p_old"), F.coalesce("p_new", F.lit(0.0)).alias("p_new")))
    order = Window.partitionBy("src").orderBy("dst")
    more = law.filter("p_new > p_old").select("src", "dst", (F.col("p_new") - F.col("p_old")).alias("d"))
    more = more.withColumn("hi", F.sum("d").over(order.rowsBetween(Window.unboundedPreceding, 0))).withColumn("mass", F.sum("d").over(Window.partitionBy("src")))
    # the last interval ends at the mass itself
    last = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("dst"))) == 1
    more = more.withColumn("last", last).select("src", F.col("dst").alias("next"), (F.col("hi") - F.col("d")).alias("lo"), F.when(F.col("last"), F.col("mass") + 1).otherwise(F.col("hi")).alias("hi"), "mass")
    state = law.groupBy("src").agg((F.sum("p_old") > 0).alias("had"), (F.sum("p_new") > 0).alias("has"))
    hop = F.lead("node").over(Window.partitionBy("walk_id").orderBy("step"))
    visits = walks.withColumn("dst", hop).join(state.withColumnRenamed("src", "node"), "node").join(law.select(F.col("src").alias("node"), "dst", "p_old", "p_new"), ["node", "dst"], "left")
    draw = lambda tag: u32(rng_seed, tag, F.col("walk_id"), F.lit(gen), F.col("step"))
    switched = F.col("dst").isNotNull() & (draw("keep") / float(TWO32) >= F.col("p_new") / F.col("p_old"))
    woken = F.col("dst").isNull() & ~F.col("had") & F.col("has") & (draw("wake") >= stop_limit(alpha))
    hit = visits.filter(switched | woken).groupBy("walk_id").agg(F.min(F.struct("step", "node", "has")).alias("v")).select("walk_id", F.col("v.step").alias("step"), F.col("v.node").alias("node"), F.col("v.has").alias("has"))
    pick = draw("move") / float(TWO32) * F.col("mass")
    chosen = hit.join(more, F.col("node") == F.col("src"), "left").filter(F.col("src").isNull() | ((pick >= F.col("lo")) & (pick < F.col("hi"))))
    return chosen.select("walk_id", F.col("step").alias("cut"), "node", F.when(F.col("has"), F.col("next")).alias("next"))


def apply_changes(walks: DataFrame, old: DataFrame, new: DataFrame, gen: int, alpha: float = 0.3, policy: str = "source_visit", rng_seed: int = RNG_SEED, strategy: str = "auto", cap: int | None = None, seed_must_stay: bool = False) -> DataFrame:
    """The walks on the graph ``new``.  ``gen`` numbers the update, from 1 on.
    Untouched walks keep their rows.  ``seed_must_stay``: a seed that has lost its last
    edge is an error.  ``strategy`` ``joins``: by tables, whatever the sizes."""
    if policy not in POLICIES:
        raise ValueError(f"unknown policy {policy}")
    if seed_must_stay:
        for row in walks.filter("step = 0").select("seed").distinct().collect():  # as many as there are seeds
            drop_seed_check(new, row.seed)
    if strategy in ("auto", "local"):
        small = _small(walks, old, new)
        if small is None and strategy == "local":
            raise ValueError("the graph or its walks are too large for one place")
        if small is not None:
            after = local_update(small[0], *small[1:], gen, alpha, policy, rng_seed, cap)
            return walks.sparkSession.createDataFrame(after, WALK)
    if strategy in ("local", "joins"):
        strategy = "auto"
    was, now = (_seen(walks, e) for e in (old, new)) if policy in ("source_visit", "coupling") else (old, new)
    seeds = walks.filter("step = 0").select("walk_id", "seed")
    if policy == "source_visit":
        cuts = cut(affected(walks, changed_sources(was, now)))
        tasks = walks.join(cuts.withColumnRenamed("cut", "step"), ["walk_id", "step"]).select("walk_id", "seed", F.lit(gen).alias("gen"), "step", "node")
        first = None
    else:
        found = {
            "coupling": lambda: _cuts(walks, was, now, gen, alpha, rng_seed), "coin": lambda: _coin_cuts(walks, old, new, gen, alpha, rng_seed), "crossing": lambda: _crossing_cuts(walks, old, new, gen, rng_seed)
        }[policy]()
        cuts = cut(found)
        first = cuts.filter("next IS NOT NULL").join(seeds, "walk_id").select("walk_id", "seed", F.lit(gen).alias("gen"), (F.col("cut") + 1).cast("int").alias("step"), F.col("next").alias("node"))
        tasks = first
    suffix = advance(new, tasks, alpha, rng_seed, strategy, cap)
    kept = walks.join(cuts.select("walk_id", "cut"), "walk_id", "left").filter("cut IS NULL OR step <= cut").select(*walks.columns)
    out = kept.unionByName(suffix)
    return out.unionByName(first) if first is not None else out


#: Visited nodes up to which they are sent to the edges.
BROADCAST_NODES = 100_000


def _seen(walks: DataFrame, edges: DataFrame) -> DataFrame:
    """Edges of the sources that walks visit: no other law can change a walk."""
    visited = cut(walks.select(F.col("node").alias("src")).distinct())
    blocks = getattr(edges, "_peertrust_blocks", None)
    if blocks is not None and visited.count() <= BROADCAST_NODES:
        return cut(packed.edges_of(blocks, edges._peertrust_before, collected(visited)["src"].to_numpy()))
    few = F.broadcast(visited) if visited.count() <= BROADCAST_NODES else visited
    return cut(edges.join(few, "src", "left_semi").select("src", "dst", "w"))


#: Visits up to which walks are updated in one place (32 bytes each).
LOCAL_VISITS = 4_000_000


def _small(walks: DataFrame, old: DataFrame, new: DataFrame) -> tuple | None:
    """Walks and both graphs on the driver, if they are counted to be small."""
    a, _ = local_edges(old, LOCAL_EDGES)
    if a is None:
        return None
    b, _ = local_edges(new, LOCAL_EDGES)
    kept = cut(walks.select("walk_id", "seed", "gen", "step", "node"))
    if b is None or kept.count() > LOCAL_VISITS:
        return None
    return collected(kept), a, b


def local_update(walks: pd.DataFrame, old: pd.DataFrame, new: pd.DataFrame, gen: int, alpha: float = 0.3, policy: str = "source_visit", rng_seed: int = RNG_SEED, cap: int | None = None, graph: Adjacency | None = None) -> pd.DataFrame:
    """``apply_changes`` on arrays: ``walks`` and both graphs (``src, dst, w``) as pandas
    frames; with the adjacency of the new ``graph`` at hand, the edges of sources that
    walks visit will do."""
    cap = step_cap(alpha) if cap is None else cap
    walks = walks.sort_values(["walk_id", "step"], ignore_index=True)
    both = old.merge(new, on=["src", "dst"], how="outer", suffixes=("_old", "_new")).fillna(0).astype("int64")
    both = both.sort_values(["src", "dst"], ignore_index=True)
    differs = both["w_old"] != both["w_new"]
    if policy == "coin" and (both["w_new"] < both["w_old"]).any():
        raise ValueError("coin is for edges that arrive or grow")
    if policy == "crossing" and (both["w_new"][differs] > 0).any():
        raise ValueError("crossing is for edges that leave")
    both = both[both["src"].isin(both["src"][differs])]
    walk, step, node = (walks[c].to_numpy() for c in ("walk_id", "step", "node"))
    last = np.append(walk[1:] != walk[:-1], True) if len(walk) else np.empty(0, bool)
    next_ = np.append(node[1:], -1) if len(walk) else node
    at = np.flatnonzero(np.isin(node, both["src"].to_numpy()))  # visits of changed sources
    draw = lambda tag, i: draws(rng_seed, tag, walk[i], np.full(len(i), gen), step[i])
    law = both.groupby("src")[["w_old", "w_new"]].sum()
    had, has = (law[c].reindex(node[at]).to_numpy() for c in ("w_old", "w_new"))

    def wakes(woken: np.ndarray) -> np.ndarray:
        out = np.zeros(len(at), bool)
        out[woken] = draw("wake", at[woken]) >= stop_limit(alpha)
        return out

    asleep = np.flatnonzero(last[at] & (had == 0) & (has > 0))
    if policy == "source_visit":
        hit = np.ones(len(at), bool)
    elif policy == "coin":
        grown = (has - had).astype(np.int64)
        pick = draw("coin", at) * has.astype(np.int64) >> 32
        hit = (~last[at] & (pick < grown)) | wakes(asleep)
    elif policy == "crossing":
        gone = set(zip(both["src"][differs], both["dst"][differs], strict=True))
        hit = np.array([not e and (a, b) in gone for a, b, e in zip(node[at].tolist(), next_[at].tolist(), last[at].tolist(), strict=True)], bool)
    else:
        hops = pd.DataFrame({"src": node[at], "dst": next_[at]}).merge(both, on=["src", "dst"], how="left")
        p_old, p_new = (hops[w].to_numpy() / np.maximum(t, 1) for w, t in (("w_old", had), ("w_new", has)))
        going = np.flatnonzero(~last[at])
        hit = wakes(asleep)
        hit[going] = draw("keep", at[going]) / float(TWO32) >= p_new[going] / p_old[going]
    first = at[hit][np.unique(walk[at[hit]], return_index=True)[1]]  # a walk's earliest
    task = walks.iloc[first].assign(gen=np.int32(gen))
    begin = None
    if policy != "source_visit":
        moved = _moves(policy, both, law, node[first], draw, first)
        task = task.assign(step=task["step"] + 1, node=moved)[moved >= 0]
        begin = task
    cut_at = pd.Series(step[first], index=walk[first]).reindex(walk).fillna(np.iinfo(np.int32).max).to_numpy()
    graph = Adjacency(*(new[c].to_numpy() for c in ("src", "dst", "w"))) if graph is None else graph
    suffix = run_walks(graph, task, np.full(len(task), alpha), rng_seed, cap)
    parts = [walks[step <= cut_at], suffix, *([begin] if begin is not None else [])]
    return pd.concat([x for x in parts if len(x)] or [walks], ignore_index=True).astype({"gen": "int32", "step": "int32"})


def _moves(policy: str, both: pd.DataFrame, law: pd.DataFrame, node: np.ndarray, draw, visit: np.ndarray) -> np.ndarray:
    """Where cut walks go on (-1: they end there)."""
    old, new = both["w_old"].to_numpy(), both["w_new"].to_numpy()
    src, dst = both["src"].to_numpy(), both["dst"].to_numpy()
    tot_old, tot_new = (law[c].reindex(src).to_numpy() for c in ("w_old", "w_new"))
    has = law["w_new"].reindex(node).to_numpy()
    if policy == "coupling":
        more = np.maximum(new / np.maximum(tot_new, 1) - old / np.maximum(tot_old, 1), 0)
        unit = draw("move", visit) / float(TWO32)
    else:
        more = (new - old if policy == "coin" else new).astype(np.int64)
        unit = draw("coin" if policy == "coin" else "move", visit)
    keep = more > 0
    src, dst, more = src[keep], dst[keep], more[keep]
    out = np.full(len(node), -1, np.int64)
    for i, u in enumerate(node.tolist()):
        if not has[i]:
            continue
        a, b = np.searchsorted(src, u, side="left"), np.searchsorted(src, u, side="right")
        ends = np.cumsum(more[a:b])
        pick = unit[i] * ends[-1] if policy == "coupling" else int(unit[i]) * int(has[i]) >> 32
        out[i] = dst[a + min(int(np.searchsorted(ends, pick, side="right")), b - a - 1)]
    return out


def drop_seed_check(new: DataFrame, seed: int) -> None:
    """A seed without edges is fine (it trusts itself alone); callers that remove
    the seed itself are told."""
    if new.filter((F.col("src") == seed) | (F.col("dst") == seed)).isEmpty():
        raise ValueError(f"seed {seed} is no longer in the graph")


def update_cost(before: DataFrame, after: DataFrame, gen: int) -> DataFrame:
    """One row: walks touched, hops redone, visits kept, and their share."""
    fresh = after.filter(F.col("gen") == gen).select("walk_id", "step", "node")
    lost = before.join(after, ["walk_id", "gen", "step", "node"], "left_anti").select("walk_id")
    touched = fresh.select("walk_id").union(lost).agg(F.count_distinct("walk_id").alias("touched"))
    redone = fresh.agg(F.count(F.lit(1)).alias("redone")).join(touched, how="cross")
    totals = before.agg(F.count(F.lit(1)).alias("visits_before")).join(after.agg(F.count(F.lit(1)).alias("visits_after")), how="cross")
    kept = (F.col("visits_after") - F.col("redone")) / F.col("visits_after")
    return totals.join(redone, how="cross").select("touched", "redone", "visits_before", "visits_after", kept.alias("kept_share"))


def bound_arrival(t: int, visits: int) -> float:
    """Expected segments that the ``t``-th random edge touches, at most."""
    return visits / t


def bound_total(m: int, alpha: float, visits: int) -> float:
    """Expected work over ``m`` random arrivals, at most."""
    return visits / alpha * float(np.sum(1.0 / np.arange(1, m + 1)))


def bound_removal(alpha: float, visits: int, m: int | None = None) -> float:
    """Expected work of one removal, at most; with ``m`` that of a random edge."""
    return visits / alpha / (m or 1)


def edge_load(scores: DataFrame, edges: DataFrame) -> DataFrame:
    """One row: the mean over edges of ``score(src) / outdegree(src)``, and what it
    must be, the share of mass on sources over the number of edges."""
    degree = edges.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    per = degree.join(scores.withColumnRenamed("node", "src"), "src", "left").withColumn("score", F.coalesce("score", F.lit(0.0)))
    # deg edges of a source carry score / deg each
    return per.agg((F.sum("score") / F.sum("deg")).alias("expected"), (F.sum(F.col("deg") * (F.col("score") / F.col("deg"))) / F.sum("deg")).alias("mean_load"), F.sum("deg").alias("n_edges"))


class RefreshPolicy:
    """When to walk anew instead of updating: every ``k`` batches, or when the
    measured error has passed ``max_error``."""

    def __init__(self, k: int | None = None, max_error: float | None = None):
        self.k, self.max_error = k, max_error

    def due(self, batch: int, error: float | None = None) -> bool:
        return bool(self.k and batch and batch % self.k == 0) or (self.max_error is not None and error is not None and error > self.max_error)


def drift_trace(rows: list[tuple[int, float, float]], spark) -> DataFrame:
    """``batch, incremental_error, scratch_error``."""
    return spark.createDataFrame(pd.DataFrame(rows, columns=["batch", "incremental_error", "scratch_error"]))
