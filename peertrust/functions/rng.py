"""Counter-based randomness: a draw is a hash of its coordinates.

``u32(seed, tag, walk, gen, step)`` is the number of the first eight hexadecimal
digits of the MD5 of the coordinates joined by ``|``.  Draws need no state, so they
don't depend on partitions, retries or engines: the SQL form below gives the same
numbers in any database that has MD5.
"""

from __future__ import annotations

import hashlib

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

RNG_SEED = 42
TWO32 = 1 << 32


def _col(x) -> Column:
    return x if isinstance(x, Column) else F.lit(x)


def u32(seed, tag: str, *parts) -> Column:
    """The draw as a column expression, inside whole-stage code generation."""
    key = F.concat_ws("|", *[_col(p).cast("string") for p in (seed, tag, *parts)])
    return F.conv(F.substring(F.md5(key), 1, 8), 16, 10).cast("long")


def u32_py(seed: int, tag: str, *parts) -> int:
    """The same draw on one machine."""
    return int(hashlib.md5("|".join(map(str, (seed, tag, *parts))).encode()).hexdigest()[:8], 16)


def u32_sql(seed: int, tag: str, *parts: str) -> str:
    """The same draw as DuckDB SQL over column expressions."""
    key = " || '|' || ".join([f"'{seed}|{tag}'", *(f"CAST({p} AS VARCHAR)" for p in parts)])
    return f"CAST('0x' || substr(md5({key}), 1, 8) AS BIGINT)"


def stop_limit(alpha: float) -> int:
    """Draws below it stop a walk."""
    return int(alpha * TWO32)


def register(spark: SparkSession) -> None:
    """SQL functions ``u32(key)`` and ``u01(key)`` of a joined key; Spark inlines them."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION u32(k STRING) RETURNS BIGINT RETURN CAST(conv(substring(md5(k), 1, 8), 16, 10) AS BIGINT)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION u01(k STRING) RETURNS DOUBLE RETURN CAST(conv(substring(md5(k), 1, 8), 16, 10) AS BIGINT) / {float(TWO32)}")
