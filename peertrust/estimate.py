"""Scores from visits, their spread, and rankings."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def visit_counts(walks: DataFrame) -> DataFrame:
    return walks.groupBy("walk_id", "node").agg(F.count(F.lit(1)).alias("visits"))


def estimate(walks: DataFrame, by: list[str] | None = None) -> DataFrame:
    """``node, score``: a node's share of all visits (of each ``by``, such as the seed)."""
    by = by or []
    counts = walks.groupBy(*by, "node").agg(F.count(F.lit(1)).alias("visits"))
    if by:
        total = walks.groupBy(*by).agg(F.count(F.lit(1)).alias("total"))
        return counts.join(total, by).select(*by, "node", (F.col("visits") / F.col("total")).alias("score"))
    total = walks.agg(F.count(F.lit(1)).alias("total"))  # one row
    return counts.join(F.broadcast(total), how="cross").select("node", (F.col("visits") / F.col("total")).alias("score"))


def endpoint_scores(walks: DataFrame) -> DataFrame:
    """The variant that counts only where walks end."""
    ends = walks.groupBy("walk_id").agg(F.max_by("node", "step").alias("node"))
    return estimate(ends)


def walk_lengths(walks: DataFrame) -> DataFrame:
    lengths = walks.groupBy("walk_id").agg((F.max("step") + 1).alias("length"))
    return lengths.agg(F.count(F.lit(1)).alias("n_walks"), F.sum("length").alias("visits"), F.avg("length").alias("mean_length"), F.max("length").alias("max_length"))


def score_ci(walks: DataFrame, z: float = 1.96) -> DataFrame:
    """``node, score, se, low, high``: the ratio estimator's standard error over
    walks.  Walks that miss a node count through the sums, not as rows."""
    lengths = walks.groupBy("walk_id").agg(F.count(F.lit(1)).alias("len"))
    per = visit_counts(walks).join(lengths, "walk_id")
    total = lengths.agg(F.count(F.lit(1)).alias("n"), F.sum("len").alias("visits"), F.sum(F.col("len") * F.col("len")).alias("len2"))
    sums = per.groupBy("node").agg(F.sum("visits").alias("v"), F.sum(F.col("visits") * F.col("visits")).alias("v2"), F.sum(F.col("visits") * F.col("len")).alias("vl"))
    both = sums.join(F.broadcast(total), how="cross").withColumn("score", F.col("v") / F.col("visits"))
    square = F.col("v2") - 2 * F.col("score") * F.col("vl") + F.col("score") * F.col("score") * F.col("len2")
    se = F.sqrt(F.greatest(square, F.lit(0.0)) * F.col("n") / (F.col("n") - 1)) / F.col("visits")
    return both.withColumn("se", se).select("node", "score", "se", (F.col("score") - z * F.col("se")).alias("low"), (F.col("score") + z * F.col("se")).alias("high"))


def walks_for_error(eps: float, delta: float, alpha: float) -> int:
    """Walks for which a score's error exceeds ``eps`` with probability ``delta`` at
    most (Hoeffding's bound on visits, one walk giving ``1 / alpha`` of them)."""
    return math.ceil(math.log(2 / delta) / (2 * eps * eps) * alpha)


def walks_for_errors(table: DataFrame, eps: str, delta: float, alpha: float) -> DataFrame:
    """``eps, n_walks``: the same for each different positive error of a column."""
    e = F.col(eps)
    n = F.ceil(F.lit(math.log(2 / delta)) / (2 * e * e) * alpha)
    return table.filter(e > 0).select(e.alias("eps"), n.alias("n_walks")).distinct()


def rank(scores: DataFrame, k: int | None = None) -> DataFrame:
    """``place, node, score`` by falling score, ties to the smaller node.  With ``k``
    only so many rows reach the one task that numbers them."""
    rows = scores.orderBy(F.desc("score"), "node")
    rows = rows.limit(k) if k is not None else rows
    return rows.select(F.row_number().over(Window.orderBy(F.desc("score"), "node")).alias("place"), "node", "score")


def choose_peer(scores: DataFrame, candidates: DataFrame, k: int = 5) -> DataFrame:
    """The ``k`` best of a swarm's candidates; unknown ones score 0."""
    rows = candidates.select("node").distinct().join(scores, "node", "left").select("node", F.coalesce("score", F.lit(0.0)).alias("score"))
    return rank(rows, k)


def merge_counts(counts: DataFrame, gone: DataFrame, fresh: DataFrame) -> DataFrame:
    """Visit counts after an update: less the visits cut off, plus the redone ones."""
    moves = counts.select("node", "visits").union(gone.groupBy("node").agg((-F.count(F.lit(1))).alias("visits"))).union(fresh.groupBy("node").agg(F.count(F.lit(1)).alias("visits")))
    return moves.groupBy("node").agg(F.sum("visits").alias("visits")).filter("visits > 0")
