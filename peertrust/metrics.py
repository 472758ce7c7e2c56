"""Accuracy, ranking and detection measures on score tables (``node, score``)."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _both(a: DataFrame, b: DataFrame) -> DataFrame:
    """``node, x, y``; a missing node scores 0."""
    x, y = a.select("node", F.col("score").alias("x")), b.select("node", F.col("score").alias("y"))
    return x.join(y, "node", "full_outer").select("node", F.coalesce("x", F.lit(0.0)).alias("x"), F.coalesce("y", F.lit(0.0)).alias("y"))


def differences(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: Euclidean, supremum and absolute distance, and the Euclidean one
    relative to ``b``."""
    d = F.col("x") - F.col("y")
    l2, norm = F.sqrt(F.sum(d * d)), F.sqrt(F.sum(F.col("y") * F.col("y")))
    return _both(a, b).agg(l2.alias("l2"), F.max(F.abs(d)).alias("linf"), F.sum(F.abs(d)).alias("l1"), (l2 / norm).alias("relative"))


def l2(a: DataFrame, b: DataFrame) -> float:
    return differences(a, b).first().l2


def linf(a: DataFrame, b: DataFrame) -> float:
    return differences(a, b).first().linf


def l1(a: DataFrame, b: DataFrame) -> float:
    return differences(a, b).first().l1


def within(a: DataFrame, b: DataFrame, bound: float = 0.10) -> bool:
    return differences(a, b).first().relative <= bound


def topk_relative_error(a: DataFrame, b: DataFrame, k: int = 12) -> DataFrame:
    """Mean relative error of ``a`` on the ``k`` best nodes of ``b``."""
    best = b.orderBy(F.desc("score"), "node").limit(k)
    rows = best.select("node", F.col("score").alias("y")).join(a.select("node", F.col("score").alias("x")), "node", "left")
    return rows.agg(F.avg(F.abs(F.coalesce("x", F.lit(0.0)) - F.col("y")) / F.col("y")).alias("mean_relative_error"))


def topk_agreement(a: DataFrame, b: DataFrame, k: int = 5) -> DataFrame:
    """One row on the ``k`` best: precision, same order, Kendall's tau-b and
    Spearman's rho over the union of both lists, and discounted gain."""

    def top(s: DataFrame, place: str, score: str) -> DataFrame:
        return s.orderBy(F.desc("score"), "node").limit(k).select("node", F.row_number().over(Window.orderBy(F.desc("score"), "node")).alias(place), F.col("score").alias(score))

    rows = top(a, "ra", "sa").join(top(b, "rb", "sb"), "node", "full_outer").select("node", F.coalesce("ra", F.lit(k + 1)).alias("ra"), F.coalesce("rb", F.lit(k + 1)).alias("rb"), F.coalesce("sb", F.lit(0.0)).alias("sb"))
    i, j = rows.alias("i"), rows.alias("j")
    pairs = i.join(j, F.col("i.node") < F.col("j.node"))  # at most k squared
    da, db = F.signum(F.col("i.ra") - F.col("j.ra")), F.signum(F.col("i.rb") - F.col("j.rb"))
    tau = pairs.agg((F.sum(da * db) / F.sqrt(F.sum(da * da) * F.sum(db * db))).alias("kendall"))
    gain = lambda r: F.sum(F.when(F.col(r) <= k, F.col("sb") / F.log2(F.col(r) + 1)).otherwise(0.0))
    out = rows.agg(
        (F.sum(F.when((F.col("ra") <= k) & (F.col("rb") <= k), 1).otherwise(0)) / k).alias("precision"),
        (F.min(F.when(F.col("rb") <= k, F.col("ra") == F.col("rb")).otherwise(True))).alias("same_order"),
        F.corr("ra", "rb").alias("spearman"), (gain("ra") / gain("rb")).alias("ndcg"),
    )
    return out.join(tau, how="cross")


# --- detection: honest nodes are the positives --------------------------------------


def labelled(scores: DataFrame, labels: DataFrame, drop_unvisited: bool = False, by: list[str] | None = None) -> DataFrame:
    """``by..., node, is_honest, score`` for every labelled node (of every scenario)."""
    by = by or []
    if by:
        base = scores.select(*by).distinct().join(F.broadcast(labels), how="cross")
        rows = base.join(scores, [*by, "node"], "left")
    else:
        rows = labels.join(scores, "node", "left")
    rows = rows.select(*by, "node", "is_honest", F.coalesce("score", F.lit(0.0)).alias("score"))
    return rows.filter("score > 0") if drop_unvisited else rows


def roc(rows: DataFrame, by: list[str] | None = None, ties: str = "node") -> DataFrame:
    """``by..., cut, node, fpr, tpr``: a point per cut of the list by falling score.
    ``ties='block'`` keeps one point per distinct score."""
    by = by or []
    order = Window.partitionBy(*by).orderBy(F.desc("score"), "node").rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy(*by)
    tp, fp = F.sum(F.when(F.col("is_honest"), 1).otherwise(0)), F.sum(F.when(F.col("is_honest"), 0).otherwise(1))
    out = rows.select(*by, "node", "score", F.count(F.lit(1)).over(order).alias("cut"), (fp.over(order) / F.nullif(fp.over(whole), F.lit(0))).alias("fpr"), (tp.over(order) / F.nullif(tp.over(whole), F.lit(0))).alias("tpr"))
    if ties == "block":
        return out.groupBy(*by, "score").agg(F.max("cut").alias("cut"), F.max("fpr").alias("fpr"), F.max("tpr").alias("tpr")).drop("score")
    return out.drop("score")


def auroc(rows: DataFrame, by: list[str] | None = None) -> DataFrame:
    """``by..., auroc``: the chance that an honest node outscores another one, ties
    counting half (rank sum with midranks); null where a class is empty."""
    by = by or []
    per = rows.groupBy(*by, "score").agg(F.sum(F.when(F.col("is_honest"), 1).otherwise(0)).alias("h"), F.sum(F.when(F.col("is_honest"), 0).otherwise(1)).alias("s"))
    below = F.coalesce(F.sum("s").over(Window.partitionBy(*by).orderBy("score").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    wins = per.select(*by, "h", "s", (F.col("h") * (below + F.col("s") / 2)).alias("wins"))
    agg = [(F.sum("wins") / F.nullif(F.sum("h") * F.sum("s"), F.lit(0))).alias("auroc")]
    return wins.groupBy(*by).agg(*agg) if by else wins.agg(*agg)


def auroc_trapezoid(curve: DataFrame, by: list[str] | None = None) -> DataFrame:
    """``by..., auroc`` under the points of ``roc``."""
    by = by or []
    w = Window.partitionBy(*by).orderBy("cut")
    area = (F.col("fpr") - F.coalesce(F.lag("fpr").over(w), F.lit(0.0))) * (F.col("tpr") + F.coalesce(F.lag("tpr").over(w), F.lit(0.0))) / 2
    rows = curve.withColumn("area", area)
    return rows.groupBy(*by).agg(F.sum("area").alias("auroc")) if by else rows.agg(F.sum("area").alias("auroc"))


def error_rates(curve: DataFrame, n_honest: int, by: list[str] | None = None) -> DataFrame:
    """Others deemed honest (false positives) and honest ones deemed otherwise
    (false negatives): the mean over all cuts, and at the cut of ``n_honest``."""
    by = by or []
    at = lambda c: F.max(F.when(F.col("cut") == n_honest, c))
    aggs = [F.avg("fpr").alias("fp_mean"), F.avg(1 - F.col("tpr")).alias("fn_mean"), at(F.col("fpr")).alias("fp_at"), at(1 - F.col("tpr")).alias("fn_at")]
    return curve.groupBy(*by).agg(*aggs) if by else curve.agg(*aggs)


def cut_table(curve: DataFrame) -> DataFrame:
    """Sensitivity, specificity and Youden's index of each cut."""
    return curve.select("cut", F.col("tpr").alias("sensitivity"), (1 - F.col("fpr")).alias("specificity"), (F.col("tpr") - F.col("fpr")).alias("youden"))


def region_flow(walks: DataFrame, labels: DataFrame) -> DataFrame:
    """One row: visits in each region, entries into the other one, and escapes."""
    rows = walks.join(labels, "node")
    after = F.lead("is_honest").over(Window.partitionBy("walk_id").orderBy("step"))
    rows = rows.withColumn("after", after)
    h = F.col("is_honest")
    return rows.agg(
        F.count_if(h).alias("honest_visits"), F.count_if(~h).alias("sybil_visits"), F.count_if(h & ~F.col("after")).alias("entries"), F.count_if(~h & F.col("after")).alias("escapes"), F.count_distinct("node").alias("nodes_seen")
    )


# --- errors over parameters ---------------------------------------------------------


def error_by_walks(walks: DataFrame, exact: DataFrame, sizes: list[int]) -> DataFrame:
    """``n_walks, l2, linf, relative`` from one run: the first ``n`` walks are a run
    of ``n``."""
    spark = walks.sparkSession
    grid = F.broadcast(spark.createDataFrame([(n,) for n in sizes], "n_walks long"))
    counts = walks.join(grid, F.col("walk_id") < F.col("n_walks")).groupBy("n_walks", "node").agg(F.count(F.lit(1)).alias("v"))
    total = counts.groupBy("n_walks").agg(F.sum("v").alias("t"))
    x = counts.join(total, "n_walks").select("n_walks", "node", (F.col("v") / F.col("t")).alias("x"))
    y = exact.select("node", F.col("score").alias("y")).join(grid, how="cross")
    both = y.join(x, ["n_walks", "node"], "full_outer").select("n_walks", F.coalesce("x", F.lit(0.0)).alias("x"), F.coalesce("y", F.lit(0.0)).alias("y"))
    d = F.col("x") - F.col("y")
    return both.groupBy("n_walks").agg(F.sqrt(F.sum(d * d)).alias("l2"), F.max(F.abs(d)).alias("linf"), (F.sqrt(F.sum(d * d)) / F.sqrt(F.sum(F.col("y") * F.col("y")))).alias("relative"))


def run_errors(walks: DataFrame, exact: DataFrame, sizes: list[int]) -> DataFrame:
    """``run, n_walks, l2`` of each run, as in ``error_by_walks``; nodes that no walk came to
    add up once for all runs."""
    grid = F.broadcast(walks.sparkSession.createDataFrame([(n,) for n in sizes], "n_walks long"))
    key = ["run", "n_walks"]
    counts = walks.join(grid, F.col("walk_id") < F.col("n_walks")).groupBy(*key, "node").agg(F.count(F.lit(1)).alias("v"))
    x = counts.withColumn("x", F.col("v") / F.sum("v").over(Window.partitionBy(*key)))
    seen = walks.select("node").distinct()
    y = exact.select("node", F.col("score").alias("y"))
    y2 = F.col("y") * F.col("y")
    away = y.join(seen, "node", "left_anti").agg(F.coalesce(F.sum(y2), F.lit(0.0)).alias("away"))
    cells = walks.select("run").distinct().join(grid, how="cross").join(seen.join(y, "node", "left"), how="cross")
    d = F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))
    near = cells.join(x.select(*key, "node", "x"), [*key, "node"], "left").groupBy(*key).agg(F.sum(d * d).alias("near"))
    return near.join(F.broadcast(away), how="cross").select(*key, F.sqrt(F.col("near") + F.col("away")).alias("l2"))


def convergence_slope(errors: DataFrame, column: str = "l2") -> DataFrame:
    """Slope of log error over log walks: about -1/2."""
    return errors.agg(F.regr_slope(F.ln(F.col(column)), F.ln("n_walks")).alias("slope"))


def score_spread(runs: DataFrame, exact: DataFrame, n_runs: int) -> DataFrame:
    """``node, mean, sd, bias`` over runs (``run, node, score``); a run that misses a
    node counts as 0."""
    sums = runs.groupBy("node").agg(F.sum("score").alias("s"), F.sum(F.col("score") * F.col("score")).alias("s2"))
    mean = F.coalesce("s", F.lit(0.0)) / n_runs
    sd = F.sqrt(F.greatest((F.coalesce("s2", F.lit(0.0)) - n_runs * F.col("mean") * F.col("mean")) / (n_runs - 1), F.lit(0.0)))
    rows = exact.join(sums, "node", "full_outer").withColumn("mean", mean)
    return rows.select("node", "mean", sd.alias("sd"), (F.col("mean") - F.coalesce("score", F.lit(0.0))).alias("bias"))


def timed(run: Callable[[], DataFrame]) -> tuple[float, DataFrame]:
    """Seconds to compute all rows, which go nowhere, and the frame."""
    start = time.perf_counter()
    df = run()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start, df


def walk_work(walks: DataFrame) -> DataFrame:
    """``gen, visits, walks``: what each generation had to walk."""
    return walks.groupBy("gen").agg(F.count(F.lit(1)).alias("visits"), F.count_distinct("walk_id").alias("walks"))


def clocked(run: Callable[[], object]) -> tuple[float, float]:
    """Seconds of a run, and the driver's CPU seconds in it; the executors' CPU time is
    in the event log of the stages."""
    wall, cpu = time.perf_counter(), time.process_time()
    run()
    return time.perf_counter() - wall, time.process_time() - cpu
