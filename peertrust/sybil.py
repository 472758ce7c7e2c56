"""Resistance to sybil regions: graphs, attack edges, and the whole experiment."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from peertrust import metrics
from peertrust.functions.rng import RNG_SEED, u32
from peertrust.graph import edges_from_net
from peertrust.sources.tables import cut, load, numbered, running_sums
from peertrust.walks import BROADCAST_EDGES, Adjacency, local_edges, run_walks, simulate_walks, step_cap


def honest_region(orders: DataFrame, n: int = 500, n_edges: int = 2_000, net: bool = False) -> DataFrame:
    """``n_edges`` hashed edges of weight 1 to 10 among ``n`` honest nodes."""
    i = F.col("o_orderkey") - 1
    draw = lambda tag, m: F.pmod(u32(RNG_SEED, tag, F.col("i")), F.lit(m))
    rows = orders.select(i.alias("i")).filter((F.col("i") >= 0) & (F.col("i") < n_edges)).select(draw("hs", n).alias("src"), draw("hd", n).alias("dst"), (draw("hw", 10) + 1).alias("w"))
    rows = rows.filter("src <> dst")
    if net:
        pair = rows.select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b"), F.when(F.col("src") > F.col("dst"), F.col("w")).otherwise(-F.col("w")).alias("g"))
        return edges_from_net(pair.groupBy("a", "b").agg(F.sum("g").alias("net")))
    return rows.groupBy("src", "dst").agg(F.sum("w").alias("w"))


def sybil_region(customer: DataFrame, first: int = 500, n: int = 1_000, degree: int = 10) -> DataFrame:
    """``degree`` hashed edges from each of ``n`` sybil nodes, numbered from ``first``."""
    own = customer.select((F.col("c_custkey") - 1).alias("i")).filter((F.col("i") >= 0) & (F.col("i") < n))
    rows = own.select("i", F.explode(F.sequence(F.lit(1), F.lit(degree))).alias("j"))
    dst = F.pmod(u32(RNG_SEED, "sd", F.col("i"), F.col("j")), F.lit(n))
    w = F.pmod(u32(RNG_SEED, "sw", F.col("i"), F.col("j")), F.lit(10)) + 1
    rows = rows.select((F.col("i") + first).alias("src"), (dst + first).alias("dst"), w.alias("w")).filter("src <> dst")
    return rows.groupBy("src", "dst").agg(F.sum("w").alias("w"))


def attack_edges(spark: SparkSession, count: int, n_honest: int = 500, n_sybil: int = 1_000, direction: str = "both", first_sybil: int | None = None, numbers: DataFrame | None = None) -> DataFrame:
    """``i, src, dst, w`` for ``i = 1..count``; a smaller attack is the part with
    smaller ``i``.  Every fiftieth one from the fifth on touches the seed (node 0).
    ``numbers``: a table of ``i``, of which those up to ``count`` are taken."""
    i = F.col("i")
    numbers = spark.range(1, count + 1).select(F.col("id").alias("i")) if numbers is None else numbers.filter((i >= 1) & (i <= count))
    base = n_honest if first_sybil is None else first_sybil
    honest = F.when(F.pmod(i, F.lit(50)) == 5, F.lit(0).cast("long")).otherwise(F.pmod(u32(RNG_SEED, "ah", i), F.lit(n_honest)))
    sybil = F.pmod(u32(RNG_SEED, "as", i), F.lit(n_sybil)) + base
    w = F.pmod(u32(RNG_SEED, "aw", i), F.lit(10)) + 1
    rows = numbers.select("i", honest.alias("h"), sybil.alias("s"), w.alias("w"))
    out = rows.select("i", F.col("h").alias("src"), F.col("s").alias("dst"), "w")
    back = rows.select("i", F.col("s").alias("src"), F.col("h").alias("dst"), "w")
    return {"out": out, "in": back, "both": out.union(back)}[direction]


def regions(spark: SparkSession, n_honest: int = 500, n_sybil: int = 1_000) -> DataFrame:
    return spark.range(n_honest + n_sybil).select(F.col("id").alias("node"), (F.col("id") < n_honest).alias("is_honest"))


def scenario_walks(edges: DataFrame, attacks: DataFrame, grid: list[tuple[int, float]], n_walks: int = 200, seed: int = 0, rng_seed: int = RNG_SEED) -> DataFrame:
    """``attack, alpha, walk_id, step, node`` for every scenario.  Scenarios share
    walk ids and so their draws: curves differ by parameter and not by noise.  Every
    task gets the graphs, if they are few enough edges (counted first); else the
    scenarios walk one after another, by joins."""
    spark = edges.sparkSession
    base, edges = local_edges(edges)
    extra, attacks = (None, attacks) if base is None or attacks.count() > BROADCAST_EDGES else (attacks.select("i", "src", "dst", "w").toPandas(), attacks)
    if extra is None:
        out = None
        for attack, alpha in grid:
            both = edges.union(attacks.filter(F.col("i") <= attack).select("src", "dst", "w")).groupBy("src", "dst").agg(F.sum("w").alias("w"))
            w = simulate_walks(both, seed, n_walks, alpha, rng_seed, "binned").select(F.lit(attack).cast("long").alias("attack"), F.lit(float(alpha)).alias("alpha"), "walk_id", "step", "node")
            out = w if out is None else out.union(w)
        return out
    shared = spark.sparkContext.broadcast((base, extra))
    tasks = spark.createDataFrame([(a, float(p)) for a, p in grid], "attack long, alpha double").repartition(max(1, len(grid)))

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        base, extra = shared.value
        for part in parts:
            for attack, alpha in part.itertuples(index=False):
                walks = _one_scenario(base, extra, attack, alpha, n_walks, seed, rng_seed)
                yield pd.DataFrame({"attack": attack, "alpha": alpha, "walk_id": walks["walk_id"], "step": walks["step"].astype("int32"), "node": walks["node"]})

    return tasks.mapInPandas(run, "attack long, alpha double, walk_id long, step int, node long")


def _one_scenario(base: pd.DataFrame, extra: pd.DataFrame, attack: int, alpha: float, n_walks: int, seed: int, rng_seed: int, graph: Adjacency | None = None) -> pd.DataFrame:
    graph = graph or _attacked(base, extra, attack)
    first = pd.DataFrame({"walk_id": np.arange(n_walks), "seed": seed, "gen": 0, "step": 0, "node": seed})
    return pd.concat([first, run_walks(graph, first, np.full(n_walks, alpha), rng_seed, step_cap(alpha))])


def _attacked(base: pd.DataFrame, extra: pd.DataFrame, attack: int) -> Adjacency:
    more = extra[extra["i"] <= attack][["src", "dst", "w"]]
    both = pd.concat([base, more]).groupby(["src", "dst"], as_index=False)["w"].sum() if len(more) else base
    return Adjacency(*(both[c].to_numpy() for c in ("src", "dst", "w")))


def scenario_measures(edges: DataFrame, attacks: DataFrame, labels: DataFrame, grid: list[tuple[int, float]], n_honest: int, n_walks: int = 200, seed: int = 0, rng_seed: int = RNG_SEED, drop_unvisited: bool = False) -> DataFrame:
    """``evaluate`` of every scenario where its walks are, so a grid of thousands of
    scenarios shuffles nothing; for graphs that are few enough to be sent (counted)."""
    spark = edges.sparkSession
    base, edges = local_edges(edges)
    labels = cut(labels)
    if base is None or max(labels.count(), attacks.count()) > BROADCAST_EDGES:
        return evaluate(cut(scenario_walks(edges, attacks, grid, n_walks, seed, rng_seed)), labels, n_honest, drop_unvisited)
    mark = labels.toPandas().sort_values("node")
    shared = spark.sparkContext.broadcast((base, attacks.select("i", "src", "dst", "w").toPandas(), mark["node"].to_numpy(), mark["is_honest"].to_numpy(bool)))
    by_attack: dict[int, list[float]] = {}
    for a, p in grid:
        by_attack.setdefault(a, []).append(float(p))
    tasks = spark.createDataFrame(sorted(by_attack.items()), "attack long, alphas array<double>").repartition(max(1, min(len(by_attack), 4 * spark.sparkContext.defaultParallelism)))

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        base, extra, node, honest = shared.value
        for part in parts:
            out = []
            for attack, alphas in part.itertuples(index=False):
                graph = _attacked(base, extra, attack)
                for alpha in alphas:
                    walks = _one_scenario(base, extra, attack, alpha, n_walks, seed, rng_seed, graph)
                    found, count = np.unique(walks["node"].to_numpy(), return_counts=True)
                    score = np.zeros(len(node))
                    at = np.searchsorted(node, found)
                    known = (at < len(node)) & (node[np.minimum(at, len(node) - 1)] == found)
                    score[at[known]] = count[known] / len(walks)
                    out.append((attack, alpha, *measures(node, score, honest, n_honest, drop_unvisited)))
            yield pd.DataFrame(out, columns=["attack", "alpha", "auroc", "fp_mean", "fn_mean", "fp_at", "fn_at"])

    return tasks.mapInPandas(run, "attack long, alpha double, auroc double, fp_mean double, fn_mean double, fp_at double, fn_at double")


def measures(node: np.ndarray, score: np.ndarray, honest: np.ndarray, n_honest: int, drop_unvisited: bool = False) -> tuple[float, ...]:
    """``auroc, fp_mean, fn_mean, fp_at, fn_at`` of one list (``node`` in order); NaN
    where a class is empty or the list too short."""
    if drop_unvisited:
        node, score, honest = (x[score > 0] for x in (node, score, honest))
    order = np.argsort(-score, kind="stable")
    h, n = honest[order], len(node)
    good, bad = int(h.sum()), n - int(h.sum())
    tpr = np.cumsum(h) / good if good else np.full(n, np.nan)
    fpr = np.cumsum(~h) / bad if bad else np.full(n, np.nan)
    mean = lambda x: float(x.mean()) if len(x) else np.nan
    at = lambda x: float(x[n_honest - 1]) if 0 < n_honest <= n else np.nan
    area = np.nan
    if good and bad:
        _, place = np.unique(score, return_inverse=True)
        a, b = np.bincount(place, weights=honest), np.bincount(place, weights=~honest)
        area = float((a * (np.cumsum(b) - b + b / 2)).sum() / (good * bad))
    return area, mean(fpr), mean(1 - tpr), at(fpr), at(1 - tpr)


def scenario_scores(walks: DataFrame) -> DataFrame:
    by = ["attack", "alpha"]
    counts = walks.groupBy(*by, "node").agg(F.count(F.lit(1)).alias("v"))
    total = walks.groupBy(*by).agg(F.count(F.lit(1)).alias("t"))
    return counts.join(total, by).select(*by, "node", (F.col("v") / F.col("t")).alias("score"))


def evaluate(walks: DataFrame, labels: DataFrame, n_honest: int, drop_unvisited: bool = False) -> DataFrame:
    """``attack, alpha, auroc, fp_mean, fn_mean, fp_at, fn_at``."""
    by = ["attack", "alpha"]
    rows = cut(metrics.labelled(scenario_scores(walks), labels, drop_unvisited, by))
    curve = metrics.roc(rows, by)
    return metrics.auroc(rows, by).join(metrics.error_rates(curve, n_honest, by), by)


#: Honest nodes, their edges, sybil nodes.
SIZES = (500, 2_000, 1_000)


def build(spark: SparkSession, sf_dir: str, max_attack: int, direction: str = "both", sizes: tuple[int, int, int] = SIZES) -> tuple[DataFrame, DataFrame, DataFrame, int]:
    """Edges of both regions, attack edges, labels, and the number of honest nodes.
    The tables must have a row for each honest edge and for each sybil node."""
    h, e, s = sizes
    orders, customer = load(spark, sf_dir, "orders"), load(spark, sf_dir, "customer")
    have = orders.filter(F.col("o_orderkey").between(1, e)).count(), customer.filter(F.col("c_custkey").between(1, s)).count()
    if have != (e, s):
        raise ValueError(f"the regions need orders 1 to {e} and customers 1 to {s}; the tables have {have[0]} and {have[1]} of them: give smaller sizes")
    both = honest_region(orders, h, e).union(sybil_region(customer, h, s))
    return both, attack_edges(spark, max_attack, h, s, direction), regions(spark, h, s), h


def sybil_experiment(spark: SparkSession, sf_dir: str, attacks: list[int], alphas: list[float], n_walks: int = 200, direction: str = "both", drop_unvisited: bool = False, sizes: tuple[int, int, int] = SIZES) -> DataFrame:
    edges, extra, labels, h = build(spark, sf_dir, max(attacks), direction, sizes)
    return scenario_measures(edges, extra, labels, [(a, p) for a in attacks for p in alphas], h, n_walks, drop_unvisited=drop_unvisited)


def both_ways(edges: DataFrame) -> DataFrame:
    """Every edge and its reverse."""
    return edges.select("src", "dst", "w").union(edges.select("dst", "src", "w")).groupBy("src", "dst").agg(F.sum("w").alias("w"))


def sweep(scores: DataFrame, edges: DataFrame) -> DataFrame:
    """``place, node, volume, cut, conductance``: nodes by falling score per weight at
    them, and for each beginning of the list the weight on its edges that leave it over
    the weight at its nodes (or at all others, if that is less)."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("node"), "w")
    degree = ends.groupBy("node").agg(F.sum("w").alias("d"))
    total = degree.agg(F.sum("d").alias("total"))
    listed = scores.filter("score > 0").join(degree, "node").select("node", "d", F.struct((-F.round(F.col("score") / F.col("d"), 12)).alias("s"), "node").alias("order"))
    ranked = cut(numbered(listed, "order").select((F.col("place") + 1).alias("place"), "node", "d"))
    # an edge leaves the list from the place of its first end to that before its second
    a, b = ranked.select(F.col("node").alias("src"), F.col("place").alias("pa")), ranked.select(F.col("node").alias("dst"), F.col("place").alias("pb"))
    both = edges.join(a, "src", "left").join(b, "dst", "left")
    steps = both.select(F.explode(F.array(F.struct(F.least("pa", "pb").alias("place"), F.col("w").alias("c")), F.struct(F.when(F.col("pa").isNotNull() & F.col("pb").isNotNull(), F.greatest("pa", "pb")).alias("place"), (-F.col("w")).alias("c")))).alias("s")).select("s.*")
    change = steps.filter("place IS NOT NULL").groupBy("place").agg(F.sum("c").alias("c"))
    rows = running_sums(ranked.join(change, "place", "left").select("place", "node", F.col("d").alias("volume"), F.coalesce("c", F.lit(0)).alias("cut")), "place", ["volume", "cut"])
    least = F.least(F.col("volume"), F.col("total") - F.col("volume"))
    return rows.join(F.broadcast(total), how="cross").select("place", "node", "volume", "cut", F.when(least > 0, F.col("cut") / least).alias("conductance"))


def community(scores: DataFrame, edges: DataFrame, share: float = 0.5) -> DataFrame:
    """The nodes of the best-parted beginning of the sweep (of at most ``share`` of all
    weight): the seed's own community, without any label."""
    rows = cut(sweep(scores, edges))
    total = edges.agg((2 * F.sum("w")).alias("total"))
    best = rows.join(F.broadcast(total), how="cross").filter(F.col("volume") <= share * F.col("total")).agg(F.min_by("place", F.struct("conductance", "place")).alias("last"))
    return rows.join(F.broadcast(best), F.col("place") <= F.col("last")).select("node")


def settled(own: DataFrame, edges: DataFrame, seed: int, rounds: int = 2) -> DataFrame:
    """``own`` after every node has gone to the side that has most of its weight, a few
    times over: nodes at a border, whose trust comes over it, go back where they belong.
    The seed stays, however many attack edges it has."""
    ends = both_ways(edges)
    first = own.sparkSession.createDataFrame([(seed,)], "node long")
    for _ in range(rounds):
        mark = own.select(F.col("node").alias("dst"), F.lit(True).alias("inside"))
        side = F.when(F.col("inside"), F.col("w")).otherwise(-F.col("w"))
        own = cut(ends.join(mark, "dst", "left").groupBy(F.col("src").alias("node")).agg(F.sum(side).alias("s")).filter("s > 0").select("node").union(first).distinct())
    return own


def suspect_edges(walks: DataFrame, own: DataFrame) -> DataFrame:
    """``src, dst, crossings``: hops of walks between ``own`` (the seed's community) and
    all other nodes, candidates for attack edges."""
    w = Window.partitionBy("walk_id").orderBy("step")
    hops = walks.select(F.col("node").alias("src"), F.lead("node").over(w).alias("dst")).filter("dst IS NOT NULL").groupBy("src", "dst").agg(F.count(F.lit(1)).alias("crossings"))
    a, b = own.select(F.col("node").alias("src"), F.lit(True).alias("ca")), own.select(F.col("node").alias("dst"), F.lit(True).alias("cb"))
    both = hops.join(a, "src", "left").join(b, "dst", "left")
    return both.filter(F.coalesce("ca", F.lit(False)) != F.coalesce("cb", F.lit(False))).select("src", "dst", "crossings")


def detection_quality(suspects: DataFrame, walks: DataFrame, edges: DataFrame, true: DataFrame) -> DataFrame:
    """One row: how many of the attack edges that walks have crossed are suspected, how
    many suspects are attack edges, and the area under the curve of all crossed edges
    by their suspicion."""
    w = Window.partitionBy("walk_id").orderBy("step")
    crossed = walks.select(F.col("node").alias("src"), F.lead("node").over(w).alias("dst")).filter("dst IS NOT NULL").distinct()
    marked = crossed.join(true.select("src", "dst", F.lit(True).alias("attack")).distinct(), ["src", "dst"], "left").join(suspects, ["src", "dst"], "left")
    rows = cut(marked.select(F.coalesce("attack", F.lit(False)).alias("is_honest"), F.coalesce("crossings", F.lit(0)).cast("double").alias("score")))
    hit = F.count_if(F.col("is_honest") & (F.col("score") > 0))
    counts = rows.agg(F.count_if("is_honest").alias("attack_edges"), F.count_if(F.col("score") > 0).alias("suspects"), hit.alias("hits"))
    return counts.join(metrics.auroc(rows), how="cross")


def cap_seed_share(edges: DataFrame, seed: int, share: float) -> DataFrame:
    """Out-edges of the seed with no more than ``share`` of its weight each."""
    total = F.sum("w").over(Window.partitionBy("src"))
    capped = F.greatest(F.lit(1).cast("long"), F.least(F.col("w"), F.floor(total * F.lit(share)).cast("long")))
    return edges.select("src", "dst", F.when(F.col("src") == seed, capped).otherwise(F.col("w")).alias("w"))
