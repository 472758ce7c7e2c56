"""From transfers to a directed, weighted graph of net flows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def net_by_pair(transfers: DataFrame, relay_kinds: tuple[str, ...] = (), relay_factor: float = 0.0) -> DataFrame:
    """``a, b, net`` for each unordered pair (``a < b``): what ``a`` gave ``b``, less
    what it took.  One aggregation with map-side combining.  Transfers of relay
    kinds count with ``relay_factor``."""
    up, down = F.col("up"), F.col("down")
    if relay_kinds:
        relay = F.col("kind").isin(*relay_kinds)
        up, down = (F.when(relay, F.floor(c * F.lit(relay_factor)).cast("long")).otherwise(c) for c in (up, down))
    given = F.when(F.col("p") < F.col("q"), up - down).otherwise(down - up)
    rows = transfers.filter("p <> q").select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), given.alias("g"))
    return rows.groupBy("a", "b").agg(F.sum("g").alias("net"))


def edges_from_net(net: DataFrame) -> DataFrame:
    """``src, dst, w``: from the net receiver to the net giver; even pairs have no edge."""
    giver = F.col("net") > 0
    return net.filter("net <> 0").select(F.when(giver, F.col("b")).otherwise(F.col("a")).alias("src"), F.when(giver, F.col("a")).otherwise(F.col("b")).alias("dst"), F.abs("net").alias("w"))


def net_edges(transfers: DataFrame, relay_kinds: tuple[str, ...] = (), relay_factor: float = 0.0) -> DataFrame:
    return edges_from_net(net_by_pair(transfers, relay_kinds, relay_factor))


def gross_edges(transfers: DataFrame) -> DataFrame:
    """Both directions of every pair: who took how much from whom."""
    rows = transfers.select(F.explode(F.array(F.struct(F.col("q").alias("src"), F.col("p").alias("dst"), F.col("up").alias("w")), F.struct(F.col("p").alias("src"), F.col("q").alias("dst"), F.col("down").alias("w")))).alias("e"))
    return rows.select("e.*").groupBy("src", "dst").agg(F.sum("w").alias("w")).filter("w > 0")


def net_edges_from_totals(blocks: DataFrame) -> DataFrame:
    """The same graph from running totals: only the newest block of a pair counts."""
    a, b = F.least("public_key", "link_public_key"), F.greatest("public_key", "link_public_key")
    given = F.col("tx.total_up") - F.col("tx.total_down")
    rows = blocks.select(a.alias("a"), b.alias("b"), F.when(F.col("public_key") < F.col("link_public_key"), given).otherwise(-given).alias("net"), F.struct("block_timestamp", "id").alias("at"))
    return edges_from_net(rows.groupBy("a", "b").agg(F.max_by("net", "at").alias("net")))


def unweighted(edges: DataFrame) -> DataFrame:
    return edges.withColumn("w", F.lit(1).cast("long"))


def nodes(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("src", "dst")).alias("node")).distinct()


def diff_edges(old: DataFrame, new: DataFrame) -> DataFrame:
    """``op, src, dst, w_old, w_new`` between two snapshots; a flipped edge shows as
    the old one removed and the new one added."""
    a = old.select("src", "dst", F.col("w").alias("w_old"))
    b = new.select("src", "dst", F.col("w").alias("w_new"))
    op = F.when(F.col("w_old").isNull(), "add").when(F.col("w_new").isNull(), "remove").otherwise("reweight")
    return a.join(b, ["src", "dst"], "full_outer").filter(~F.col("w_old").eqNullSafe(F.col("w_new"))).select(op.alias("op"), "src", "dst", "w_old", "w_new")


def net_flip_history(transfers: DataFrame) -> DataFrame:
    """``a, b, id, net, flipped``: the running net of each pair, and where its sign
    turns."""
    given = F.when(F.col("p") < F.col("q"), F.col("up") - F.col("down")).otherwise(F.col("down") - F.col("up"))
    order = Window.partitionBy("a", "b").orderBy("ts", "id")
    rows = transfers.select(F.least("p", "q").alias("a"), F.greatest("p", "q").alias("b"), "id", "ts", given.alias("g"))
    running = rows.withColumn("net", F.sum("g").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    before = F.lag(F.signum("net")).over(order)
    return running.select("a", "b", "id", "net", (F.coalesce(before, F.lit(0.0)) * F.signum("net") < 0).alias("flipped"))


def graph_profile(edges: DataFrame) -> DataFrame:
    """One row: nodes, edges, weight, dangling and source-only nodes, largest degrees."""
    ends = edges.select(F.explode(F.array(F.struct(F.col("src").alias("node"), F.lit(1).alias("o"), F.lit(0).alias("i")), F.struct(F.col("dst").alias("node"), F.lit(0).alias("o"), F.lit(1).alias("i")))).alias("e"), "w").select("e.*", "w")
    degree = ends.groupBy("node").agg(F.sum("o").alias("o"), F.sum("i").alias("i"), F.sum(F.col("w") * F.col("o")).alias("strength"))
    return degree.agg(
        F.count(F.lit(1)).alias("n_nodes"), F.sum("o").alias("n_edges"), F.sum("strength").alias("weight"), F.sum(_flag(F.col("o") == 0)).alias("n_dangling"),
        F.sum(_flag(F.col("i") == 0)).alias("n_unreferenced"), F.max("o").alias("max_out"), F.max("i").alias("max_in"),
    )


def _flag(c: Column) -> Column:
    return F.when(c, 1).otherwise(0)


def ban_agents(edges: DataFrame, flagged: DataFrame) -> DataFrame:
    """Edges without the flagged nodes (``flagged.node``)."""
    bad = flagged.select(F.col("node").alias("_bad")).distinct()
    return edges.join(bad, edges.src == F.col("_bad"), "left_anti").join(bad, edges.dst == F.col("_bad"), "left_anti")
