"""Earlier mechanisms, in runnable form, to compare rankings with."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from peertrust.functions.rng import RNG_SEED, u32


def both_sides(transfers: DataFrame) -> DataFrame:
    """``peer, partner, given, taken, ts, id``: each transfer from both ends."""
    a = F.struct(F.col("p").alias("peer"), F.col("q").alias("partner"), F.col("up").alias("given"), F.col("down").alias("taken"))
    b = F.struct(F.col("q").alias("peer"), F.col("p").alias("partner"), F.col("down").alias("given"), F.col("up").alias("taken"))
    return transfers.select(F.explode(F.array(a, b)).alias("e"), "ts", "id").select("e.*", "ts", "id")


def tit_for_tat(transfers: DataFrame, slots: int = 4) -> DataFrame:
    """``day, peer, partner, slot``: the ``slots - 1`` partners that gave most that
    day, and one hash-random other (``free``), who may so earn a slot."""
    day = both_sides(transfers).groupBy(F.date_trunc("day", "ts").cast("date").alias("day"), "peer", "partner").agg(F.sum("taken").alias("got"))
    by = Window.partitionBy("day", "peer")
    ranked = day.withColumn("r", F.row_number().over(by.orderBy(F.desc("got"), "partner")))
    best = ranked.filter(F.col("r") < slots).filter("got > 0").select("day", "peer", "partner", F.lit("earned").alias("slot"))
    rest = ranked.filter((F.col("r") >= slots) | (F.col("got") <= 0)).withColumn("draw", u32(RNG_SEED, "unchoke", F.col("day"), F.col("peer"), F.col("partner")))
    free = rest.withColumn("f", F.row_number().over(by.orderBy("draw", "partner"))).filter("f = 1").select("day", "peer", "partner", F.lit("free").alias("slot"))
    return best.union(free)


def net_contribution(transfers: DataFrame) -> DataFrame:
    """``node, score, free_rider``: given less taken."""
    rows = both_sides(transfers).groupBy(F.col("peer").alias("node")).agg((F.sum("given") - F.sum("taken")).alias("score"))
    return rows.select("node", "score", (F.col("score") < 0).alias("free_rider"))


def reported_contribution(transfers: DataFrame, liar_every: int = 5, factor: int = 10) -> DataFrame:
    """``node, score``: what peers say they gave; every ``liar_every``-th one
    multiplies it."""
    rows = both_sides(transfers).groupBy(F.col("peer").alias("node")).agg(F.sum("given").alias("given"), F.sum("taken").alias("taken"))
    said = F.when(F.col("node") % liar_every == 0, F.col("given") * factor).otherwise(F.col("given"))
    return rows.select("node", (said - F.col("taken")).alias("score"))


def drop_interested(edges: DataFrame, ranker: int) -> DataFrame:
    """The graph without the nodes that owe the ranker (they want to be served)."""
    interested = edges.filter(F.col("dst") == ranker).select(F.col("src").alias("_i"))
    return edges.join(interested, edges.src == F.col("_i"), "left_anti").join(interested, edges.dst == F.col("_i"), "left_anti")


def review_average(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """``source, reviews, score``: central, tamper-proof review averages."""
    return documents.join(labels, "doc_id").groupBy("source").agg(F.count("quality").alias("reviews"), F.avg("quality").alias("score"))


def random_rank(nodes: DataFrame, rng_seed: int = RNG_SEED) -> DataFrame:
    """``node, score``: a hash-random ranking, as a control."""
    return nodes.select("node", u32(rng_seed, "rank", F.col("node")).cast("double").alias("score"))


def pair_game(transfers: DataFrame) -> DataFrame:
    """``policy, rounds, payoff``: payoffs of fixed policies against the history of
    each pair.  A round is a transfer; its initiator cooperates when it gives.
    Payoffs: both cooperate 3, both defect 1, cheat 5, cheated 0."""
    rows = transfers.select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), "ts", "id", (F.col("up") > 0).alias("coop"))
    before = F.lag("coop").over(Window.partitionBy("a", "b").orderBy("ts", "id"))
    rows = rows.withColumn("before", F.coalesce(before, F.lit(True)))
    policies = F.explode(F.array(*[F.struct(F.lit(n).alias("policy"), mine.alias("mine")) for n, mine in (("cooperate", F.lit(True)), ("defect", F.lit(False)), ("reciprocate", F.col("before")))]))
    played = rows.select("coop", policies.alias("g")).select("coop", "g.*")
    pay = F.when(F.col("mine") & F.col("coop"), 3).when(F.col("mine"), 0).when(F.col("coop"), 5).otherwise(1)
    return played.groupBy("policy").agg(F.count(F.lit(1)).alias("rounds"), F.sum(pay).alias("payoff"))
