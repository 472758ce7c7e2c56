"""The ledger: blocks, chains of agents, audit, and double spends."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def build_blocks(transfers: DataFrame) -> DataFrame:
    """Eleven-column blocks (and ``id``) from transfers: running totals of the
    initiator with its partner, sequence numbers of both, hash pointers."""
    pair = Window.partitionBy(F.least("p", "q"), F.greatest("p", "q")).orderBy("ts", "id").rowsBetween(Window.unboundedPreceding, 0)
    first = F.col("p") < F.col("q")
    low_up, low_down = F.when(first, F.col("up")).otherwise(F.col("down")), F.when(first, F.col("down")).otherwise(F.col("up"))
    totals = transfers.withColumn("_lu", F.sum(low_up).over(pair)).withColumn("_ld", F.sum(low_down).over(pair))
    rows = totals.withColumn("total_up", F.when(first, F.col("_lu")).otherwise(F.col("_ld"))).withColumn("total_down", F.when(first, F.col("_ld")).otherwise(F.col("_lu")))
    numbered = agent_chains(transfers).select("agent", "id", "seq")
    mine = numbered.select(F.col("agent").alias("p"), "id", F.col("seq").alias("sequence_number"))
    theirs = numbered.select(F.col("agent").alias("q"), "id", F.col("seq").alias("link_sequence_number"))
    rows = rows.join(mine, ["p", "id"]).join(theirs, ["q", "id"])
    content = F.sha2(F.concat_ws("|", "id", "p", "q", "up", "down"), 256)
    rows = rows.withColumn("block_hash", content)
    pointers = link_blocks(agent_chains(transfers)).select(F.col("agent").alias("p"), "id", "previous_hash")
    rows = rows.join(pointers, ["p", "id"])
    return rows.select(
        "id", F.col("kind").alias("type"), F.struct("up", "down", "total_up", "total_down").alias("tx"), F.col("p").alias("public_key"), "sequence_number", F.col("q").alias("link_public_key"),
        "link_sequence_number", "previous_hash", F.md5(F.concat_ws("|", "p", "block_hash")).alias("signature"), F.col("ts").alias("block_timestamp"), F.col("ts").alias("insert_time"), "block_hash",
    )


def agent_chains(transfers: DataFrame) -> DataFrame:
    """``agent, seq, id, hash``: every transfer in the chains of both its parties."""
    both = transfers.select(F.explode(F.array("p", "q")).alias("agent"), "id", "ts", F.sha2(F.concat_ws("|", "id", "p", "q", "up", "down"), 256).alias("hash"))
    return both.withColumn("seq", F.row_number().over(Window.partitionBy("agent").orderBy("ts", "id")).cast("long")).select("agent", "seq", "id", "hash")


def link_blocks(chains: DataFrame) -> DataFrame:
    """Chains with the hash of the block before (genesis: zeros) and the next one's id."""
    w = Window.partitionBy("agent").orderBy("seq")
    return chains.withColumn("previous_hash", F.coalesce(F.lag("hash").over(w), F.lit("0" * 64))).withColumn("next_id", F.lead("id").over(w))


def audit_chain(linked: DataFrame) -> DataFrame:
    """Rows that break their chain: a gap in the sequence, or a pointer that is not
    the hash of the block before."""
    w = Window.partitionBy("agent").orderBy("seq", "id")
    seen = linked.withColumn("_gap", F.col("seq") - F.coalesce(F.lag("seq").over(w), F.lit(0)) != 1).withColumn("_broken", F.col("previous_hash") != F.coalesce(F.lag("hash").over(w), F.lit("0" * 64)))
    return seen.filter("_gap OR _broken").select("agent", "seq", "id", F.col("_gap").alias("gap"), F.col("_broken").alias("broken"))


def find_double_spends(linked: DataFrame) -> DataFrame:
    """``agent, seq, n``: places of a chain that more than one block claims."""
    return linked.groupBy("agent", "seq").agg(F.count_distinct("hash").alias("n")).filter("n > 1")


def check_model(transfers: DataFrame) -> DataFrame:
    """One row of counts that must be zero: transfers with oneself, negative
    amounts, and events that share an agent and a place in its order."""
    ordered = transfers.select(F.explode(F.array("p", "q")).alias("agent"), "ts", "id").groupBy("agent", "ts", "id").count().filter("count > 1").agg(F.count(F.lit(1)).alias("disordered"))
    bad = transfers.agg(F.count_if(F.col("p") == F.col("q")).alias("selfish"), F.count_if((F.col("up") < 0) | (F.col("down") < 0)).alias("negative"))
    return bad.join(ordered, how="cross")
