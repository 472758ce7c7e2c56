"""Canonical row types."""

from pyspark.sql import types as T

TX = T.StructType([T.StructField(n, T.LongType()) for n in ("up", "down", "total_up", "total_down")])
BLOCK = T.StructType(
    [
        T.StructField("type", T.StringType()),
        T.StructField("tx", TX),
        T.StructField("public_key", T.LongType()),
        T.StructField("sequence_number", T.LongType()),
        T.StructField("link_public_key", T.LongType()),
        T.StructField("link_sequence_number", T.LongType()),
        T.StructField("previous_hash", T.StringType()),
        T.StructField("signature", T.StringType()),
        T.StructField("block_timestamp", T.TimestampType()),
        T.StructField("insert_time", T.TimestampType()),
        T.StructField("block_hash", T.StringType()),
    ]
)
INTERACTION = "id long, p long, q long, up long, down long, ts timestamp, kind string"
EDGE = "src long, dst long, w long"
WALK = "walk_id long, seed long, gen int, step int, node long"
SCORE = "node long, score double"
CHANGE = "op string, src long, dst long, w_old long, w_new long"
REGION = "node long, is_honest boolean"
#: ``props`` of ``events``.
PROPS = T.StructType([T.StructField("k", T.LongType())])
