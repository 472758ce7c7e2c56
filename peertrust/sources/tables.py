"""The given tables, and the graph views that stand for a ledger on them."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from peertrust.functions.rng import RNG_SEED, u32
from peertrust.graph import edges_from_net, net_by_pair
from peertrust.schemas import PROPS

UP_KINDS, DOWN_KINDS = ("click", "view", "purchase"), ("error", "signup")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where the session has none, a folder of its own, on one
    machine only: executors elsewhere would not see it."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    sc = spark.sparkContext
    current = sc._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    if not re.match(r"local(\[|$)", sc.master):
        raise RuntimeError("spark.checkpoint.dir has to name a folder that all executors share")
    path = tempfile.mkdtemp(prefix="peertrust-")
    atexit.register(shutil.rmtree, path, ignore_errors=True)
    sc.setCheckpointDir(path)
    return path


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path in the shared folder; what lies there goes when the session ends."""
    folder = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    target = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = target.getFileSystem(spark._jsc.hadoopConfiguration())
    fs.mkdirs(target)
    fs.deleteOnExit(target)
    return f"{folder}/data"


def cut(df: DataFrame) -> DataFrame:
    """``df`` computed once, its lineage cut in the shared folder (a frame that is cut
    already comes back as it is)."""
    if getattr(df, "_peertrust_cut", False):
        return df
    shared_dir(df.sparkSession)
    out = df.checkpoint()
    # the frame keeps the size that was estimated for its plan; joins multiply it, so in a long
    # loop its digits grow exponentially, and planning with them
    if out._jdf.queryExecution().optimizedPlan().stats().sizeInBytes() > 1 << 128:
        made = df.sparkSession._jsparkSession.internalCreateDataFrame(out._jdf.queryExecution().toRdd(), out._jdf.schema(), False)
        out = DataFrame(made, df.sparkSession)
    out._peertrust_cut = True
    return out


def numbered(df: DataFrame, column: str) -> DataFrame:
    """``df`` with ``place``, its rank by a unique column, from 0 on.  Ranges are
    counted one by one and offset by those before, so no task sees all rows."""
    parts = cut(df.repartitionByRange(column).sortWithinPartitions(column).withColumn("_row", F.monotonically_increasing_id()))
    sizes = parts.groupBy(F.shiftright("_row", 33).alias("_part")).agg(F.count(F.lit(1)).alias("_n"), F.min("_row").alias("_low"))
    before = sizes.withColumn("_before", F.sum("_n").over(Window.orderBy("_part")) - F.col("_n"))  # a row a partition
    both = parts.join(F.broadcast(before), F.shiftright("_row", 33) == F.col("_part"))
    return both.withColumn("place", F.col("_before") + F.col("_row") - F.col("_low")).drop("_row", "_part", "_n", "_low", "_before")


def running_sums(df: DataFrame, place: str, columns: list[str], block: int = 100_000) -> DataFrame:
    """``df`` with its number columns summed up to each row by ``place`` (dense, from 1
    on): within blocks of places, and offset by the blocks before."""
    rows = df.withColumn("_block", F.floor((F.col(place) - 1) / F.lit(block)))
    sums = rows.groupBy("_block").agg(*[F.sum(c).alias(f"_s{i}") for i, c in enumerate(columns)])
    order = Window.orderBy("_block")  # a row a block
    before = sums.select(F.col("_block").alias("_b"), *[(F.sum(f"_s{i}").over(order) - F.col(f"_s{i}")).alias(f"_o{i}") for i in range(len(columns))])
    inside = Window.partitionBy("_block").orderBy(place).rowsBetween(Window.unboundedPreceding, 0)
    both = rows.join(F.broadcast(before), F.col("_block") == F.col("_b"))
    summed = {c: F.sum(c).over(inside) + F.col(f"_o{i}") for i, c in enumerate(columns)}
    return both.select(*[summed.get(c, F.col(c)).alias(c) for c in df.columns])


def interactions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``events`` as transfers: the initiator's partner lies ``k + 1`` peers on, and
    amounts are whole cents.  Transfers with oneself are dropped."""
    events = load(spark, sf_dir, "events")
    n = events.agg(F.count_distinct("user_id").alias("n"))  # one row
    cents = F.round(F.col("value") * 100).cast("long")
    out = events.join(F.broadcast(n), how="cross").select(
        F.col("event_id").alias("id"),
        F.col("user_id").alias("p"),
        F.pmod(F.col("user_id") + 1 + F.from_json("props", PROPS)["k"], F.col("n")).alias("q"),
        F.when(F.col("event_type").isin(*UP_KINDS), cents).otherwise(0).alias("up"),
        F.when(F.col("event_type").isin(*DOWN_KINDS), cents).otherwise(0).alias("down"),
        F.col("ts").cast("timestamp").alias("ts"),
        F.col("event_type").alias("kind"),
    )
    return out.filter("p <> q")


def peer_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The flagship graph: net transfers between peers."""
    return edges_from_net(net_by_pair(interactions(spark, sf_dir)))


def trade_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers (even ids) and suppliers (odd ids), netted over order lines."""
    lines, orders = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "orders")
    cents = F.round(F.col("l_quantity") * 100).cast("long")
    back = F.col("l_returnflag") == "R"
    rows = lines.join(orders, lines.l_orderkey == orders.o_orderkey).select(
        (F.col("o_custkey") * 2).alias("p"), (F.col("l_suppkey") * 2 + 1).alias("q"), F.when(back, 0).otherwise(cents).alias("up"), F.when(back, cents).otherwise(0).alias("down")
    )
    return edges_from_net(net_by_pair(rows))


def link_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``host, target, n``: links of pages by host."""
    pages = load(spark, sf_dir, "pages")
    host = F.regexp_extract("url", r"^https?://([^/]+)", 1)
    links = pages.select(host.alias("host"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]+)"'), 1)).alias("target"))
    return links.groupBy("host", "target").agg(F.count(F.lit(1)).alias("n"))


def random_edges(spark: SparkSession, sf_dir: str, n: int, per_node: int = 2, seed: int = RNG_SEED) -> DataFrame:
    """``per_node`` hashed edges from each of ``n`` nodes, which have the numbers of
    customers, and go on behind the last of these."""
    own = load(spark, sf_dir, "customer").select((F.col("c_custkey") - 1).alias("src")).filter((F.col("src") >= 0) & (F.col("src") < n))
    nodes = own.union(spark.range(n).select(F.col("id").alias("src"))).distinct()
    pairs = nodes.select("src", F.explode(F.sequence(F.lit(1), F.lit(per_node))).alias("i"))
    drawn = pairs.select("src", F.pmod(u32(seed, "rd", F.col("src"), F.col("i")), F.lit(n)).alias("dst"), (F.pmod(u32(seed, "rw", F.col("src"), F.col("i")), F.lit(10)) + 1).alias("w"))
    return drawn.filter("src <> dst").groupBy("src", "dst").agg(F.sum("w").alias("w"))


#: Vectors of a block in ``knn_edges``.
KNN_BLOCK = 2_048


def knn_edges(spark: SparkSession, sf_dir: str, k: int = 5) -> DataFrame:
    """Each vector's ``k`` most similar ones, weighted by similarity in thousandths.
    Vectors are dealt to blocks, every pair of blocks is a matrix product of its own,
    and only ``k`` rows a vector leave it."""
    v = load(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    v = cut(v)
    blocks = max(1, -(-v.count() // KNN_BLOCK))
    own = v.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int"))
    each = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    left, right = own.withColumn("c", each), own.withColumnRenamed("b", "c").withColumn("b", each)

    def best(a: pa.Table, b: pa.Table) -> pa.Table:
        src, dst = a.column("vec_id").to_numpy(), b.column("vec_id").to_numpy()
        x, y = (np.array(t.column("e").to_pylist(), float).reshape(t.num_rows, -1) for t in (a, b))
        out: list[list] = [[], [], []]
        for i in range(0, len(src) if len(dst) else 0, 256):
            # summed component by component, as the expression of one pair would be
            dot = np.zeros((len(x[i : i + 256]), len(y)))
            for c in range(x.shape[1]):
                dot += x[i : i + 256, c, None] * y[None, :, c]
            weight = np.sign(dot) * np.floor(np.abs(dot) * 1000 + 0.5)
            for row, w in zip(src[i : i + 256].tolist(), weight, strict=True):
                pick = np.flatnonzero((dst != row) & (w > 0))
                pick = pick[np.lexsort((dst[pick], -w[pick]))[:k]]
                out[0] += [row] * len(pick)
                out[1] += dst[pick].tolist()
                out[2] += w[pick].astype(np.int64).tolist()
        return pa.table({n: pa.array(c, pa.int64()) for n, c in zip(("src", "dst", "w"), out, strict=True)})

    sims = left.groupBy("b", "c").cogroup(right.groupBy("b", "c")).applyInArrow(best, "src long, dst long, w long")
    return sims.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("w"), "dst"))).filter(F.col("r") <= k).drop("r")
