"""Walks from every node by doubling: log-many rounds of one join.

Every node draws many one-step segments.  A round joins the segments with even
numbers to those with odd numbers that start where they end, which doubles the
length and halves the number.  A walk uses a segment number at most once, so its
steps are independent; walks of different nodes may share segments, which leaves
each walk's law as it is.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peertrust.functions.rng import RNG_SEED, stop_limit, u32
from peertrust.graph import nodes
from peertrust.sources.tables import cut
from peertrust.transition import binned_cdf, cdf
from peertrust.walks import step_cap


def doubling_walks(edges: DataFrame, each: int, alpha: float, rng_seed: int = RNG_SEED, miss: float = 1e-6) -> DataFrame:
    """``seed, walk_id, step, node``: ``each`` walks from every node; a walk longer than
    the doubled length (chance ``miss``) ends there."""
    rounds = max(1, math.ceil(math.log2(step_cap(alpha, miss))))
    table = cut(binned_cdf(cdf(edges)))
    per = table.select("src", "tot", "bins").distinct()
    start = nodes(edges).select(F.col("node").alias("start"), F.explode(F.sequence(F.lit(0), F.lit(each * 2**rounds - 1))).alias("i"))
    coin = u32(rng_seed, "dstop", F.col("start"), F.col("i")) >= stop_limit(alpha)
    pick = F.shiftright(u32(rng_seed, "dhop", F.col("start"), F.col("i")) * F.col("tot"), 32)
    going = start.filter(coin).join(per, start.start == per.src).withColumn("pick", pick).withColumn("bin", F.floor(F.col("pick") * F.col("bins") / F.col("tot")).cast("long")).select("start", "i", "pick", "bin")
    hop = table.select(F.col("src").alias("start"), "bin", F.col("dst").alias("end"), "lo", "hi")
    moved = going.join(hop, ["start", "bin"]).filter("lo <= pick AND pick < hi").select("start", "i", "end")
    # a segment without an end has stopped before its first step
    seg = start.join(moved, ["start", "i"], "left").select("start", "i", "end", F.when(F.col("end").isNotNull(), F.array("end")).otherwise(F.array().cast("array<long>")).alias("path"))
    for _ in range(rounds):
        seg = cut(seg)
        left = seg.filter("i % 2 = 0").withColumn("j", F.col("i") / 2)
        right = seg.filter("i % 2 = 1").select(F.col("start").alias("end"), ((F.col("i") - 1) / 2).alias("j"), F.col("end").alias("far"), F.col("path").alias("more"))
        both = left.join(right, ["end", "j"], "left")
        seg = both.select("start", F.col("j").cast("int").alias("i"), F.col("far").alias("end"), F.concat("path", F.coalesce("more", F.array().cast("array<long>"))).alias("path"))
    walks = seg.select(F.col("start").alias("seed"), F.col("i").alias("walk_id"), F.posexplode(F.concat(F.array("start"), "path")).alias("step", "node"))
    return walks.select("seed", "walk_id", "step", "node")
