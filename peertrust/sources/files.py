"""File formats, partitioned and bucketed tables, databases, and streams of files."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from peertrust.sources.tables import scratch

FORMATS = ("csv", "json", "orc", "parquet")


def write_read(df: DataFrame, kind: str, path: str | None = None) -> DataFrame:
    """``df`` written in a format and read back with its own schema (never inferred)."""
    if kind not in FORMATS:
        raise ValueError(f"unknown format {kind}")
    path = path or scratch(df.sparkSession, kind)
    options = {"header": "true"} if kind == "csv" else {}
    df.write.format(kind).options(**options).mode("overwrite").save(path)
    return df.sparkSession.read.format(kind).options(**options).schema(df.schema).load(path)


def write_by_day(df: DataFrame, time: str, path: str) -> None:
    """One folder a day, each written by few tasks."""
    df.withColumn("day", F.to_date(time)).repartition("day").write.mode("overwrite").partitionBy("day").parquet(path)


def write_in_order(df: DataFrame, column: str, path: str) -> None:
    """A file for each value of ``column``, whose times of change follow the values, a
    second apart: so a stream of the folder takes them in this order."""
    spark = df.sparkSession
    df.repartition(column).sortWithinPartitions(column).write.partitionBy(column).parquet(f"{path}-parts")
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    at = jvm.org.apache.hadoop.fs.Path
    source, target = at(f"{path}-parts"), at(path)
    fs = source.getFileSystem(conf)
    fs.mkdirs(target)
    begin = int(time.time()) - 1_000_000
    for folder in fs.listStatus(source):  # as many as there are values
        name = folder.getPath().getName()
        if "=" not in name:
            continue
        value = int(name.partition("=")[2])
        for k, part in enumerate(fs.listStatus(folder.getPath())):
            to = at(target, f"{value:09d}-{k}.parquet")
            fs.rename(part.getPath(), to)
            fs.setTimes(to, (begin + value) * 1000, -1)
    fs.delete(source, True)


def read_days(spark: SparkSession, path: str, first: str, last: str) -> DataFrame:
    """Only the folders of the days asked for are read."""
    return spark.read.parquet(path).filter(F.col("day").between(F.lit(first).cast("date"), F.lit(last).cast("date")))


def save_bucketed(edges: DataFrame, table: str, buckets: int = 16) -> DataFrame:
    """Edges bucketed by source, so that joins on it need no shuffle of theirs."""
    edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)
    return edges.sparkSession.table(table)


def scan_jdbc(spark: SparkSession, url: str, table: str, column: str, low: int, high: int, parts: int) -> DataFrame:
    """A ledger in a database, read in ``parts`` ranges of a numeric column; needs the
    database's driver on the class path."""
    options = {"url": url, "dbtable": table, "partitionColumn": column, "lowerBound": str(low), "upperBound": str(high), "numPartitions": str(parts)}
    return spark.read.format("jdbc").options(**options).load()


def stream_files(spark: SparkSession, path: str, schema, pattern: str = "*.parquet", per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("pathGlobFilter", pattern).option("maxFilesPerTrigger", per_trigger).parquet(path)
