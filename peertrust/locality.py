"""How far trust reaches from a seed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peertrust.sources.tables import cut


def hop_distance(edges: DataFrame, seed: int, max_hops: int = 10) -> DataFrame:
    """``node, hop`` of nodes within ``max_hops`` hops, breadth first."""
    reached = edges.sparkSession.createDataFrame([(seed, 0)], "node long, hop int")
    frontier = reached
    for h in range(1, max_hops + 1):
        near = frontier.join(edges, frontier.node == edges.src).select(F.col("dst").alias("node")).distinct()
        frontier = cut(near.join(reached, "node", "left_anti").withColumn("hop", F.lit(h)))
        if frontier.isEmpty():
            break
        reached = cut(reached.union(frontier))
    return reached


def mass_by_hop(scores: DataFrame, hops: DataFrame) -> DataFrame:
    """``hop, nodes, mass``: trust by distance (null: beyond the bound)."""
    return scores.join(hops, "node", "left").groupBy("hop").agg(F.count(F.lit(1)).alias("nodes"), F.sum("score").alias("mass"))


def mass_by_step(walks: DataFrame) -> DataFrame:
    """``step, visits, share``: visits by the walks' own steps; at most
    ``(1 - alpha) ** step`` walks come so far."""
    total = walks.filter("step = 0").agg(F.count(F.lit(1)).alias("walks"))
    return walks.groupBy("step").agg(F.count(F.lit(1)).alias("visits")).join(F.broadcast(total), how="cross").select("step", "visits", (F.col("visits") / F.col("walks")).alias("share"))
