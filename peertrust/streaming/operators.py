"""Operators on streams: windows with watermarks, duplicates, joins, and a runner that
drains a stream of files into a table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType

from peertrust.sources.tables import scratch


def drain(stream: DataFrame, mode: str = "append", checkpoint: str | None = None, keys: list[str] | None = None, every: bool = False) -> DataFrame:
    """All that is there now, through Parquet files in the shared folder.  Rows of mode
    ``append`` are kept as they come; of ``complete`` the last micro-batch is the result;
    of ``update`` the last row of each of the ``keys`` (with ``every`` all rows, and the
    ``number`` of their micro-batch)."""
    spark = stream.sparkSession
    path = scratch(spark, "drained")
    writer = stream.writeStream.option("checkpointLocation", checkpoint or f"{path}-state").outputMode(mode).trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", path).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    last = []

    def feed(batch: DataFrame, number: int) -> None:
        if mode == "complete":
            batch.write.mode("overwrite").parquet(f"{path}/number={number:09d}")
            last[:] = [number]
        else:
            batch.write.mode("overwrite").parquet(f"{path}/number={number:09d}")

    writer.foreachBatch(feed).start().awaitTermination()
    rows = spark.read.schema(StructType([*stream.schema.fields, StructField("number", LongType())])).parquet(path)
    if mode == "complete":
        return rows.filter(F.col("number") == (last[0] if last else -1)).drop("number")
    if every:
        return rows
    rest = [c for c in stream.columns if c not in keys]
    newest = rows.groupBy(*keys).agg(F.max(F.struct("number", *rest)).alias("v"))
    return newest.select(*keys, *[F.col(f"v.{c}").alias(c) for c in rest]).select(*stream.columns)


def daily_counts(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """``day, event_type, n`` of days that the watermark has passed."""
    rows = events.withWatermark("ts", delay).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return rows.select(F.to_date("window.start").alias("day"), "event_type", "n")


def without_duplicates(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Each ``event_id`` once, its state dropped behind the watermark."""
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def with_static(events: DataFrame, table: DataFrame, key: str) -> DataFrame:
    return events.join(table, key)


def halves(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """``a, b``: purchases of a user within ten minutes after one of its clicks; both
    sides have watermarks, and the time bound lets state go."""
    clicks = events.filter("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", delay)
    buys = events.filter("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", delay)
    return clicks.join(buys, F.expr("ua = ub AND tb >= ta AND tb <= ta + INTERVAL 10 MINUTES")).select("a", "b")
