"""Sequence packing by large-item matching over a histogram of lengths.

A bin holds ``capacity`` tokens.  Pieces above a third of it are large: at most
two of them fit, so they are paired greedily (the longest one takes the longest
partner that still fits).  Smaller pieces, longest first, go to the tightest gap
that holds them, and open bins of their own only when no gap does.

The packing depends on lengths alone, and there are at most ``capacity`` of them.
So Spark only counts the pieces of each length; the plan is made over the counts
(bins of one make are handled together, with a multiplicity), and its size follows
the number of lengths, not of documents.  Each piece then finds its place from its
rank among the pieces of its length.  Ranks are counted inside hashed shares of a
length and offset by the shares before, so a length that a third of all pieces
have is spread over many tasks.

Defined results: null and empty texts have one piece that holds only the closing
id; documents longer than ``capacity`` are cut, all others stay whole; repeated
rows are packed as often as they stand there; every sequence is gapless from 0.
"""

from __future__ import annotations

import bisect
import zlib
from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import LongType, StructField, StructType

from .bpe_transducer import CHUNK_BYTES, build_lexicon, default_tokenizer, encoder
from .common import id_and_text, saved, slices

CAPACITY = 2048
CLOSING_ID = 0
#: Pieces that one task ranks among the pieces of one length.
SHARE_ROWS = 50_000


def plan_bins(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """``(lengths, how many bins)`` for counts of pieces by length.

    A length fills bins of one gap in bulk: as many bins as the pieces need, each
    with as many pieces as it holds, which is what placing them one by one would
    do, because a gap just made smaller is the tightest one.
    """
    left = {n: c for n, c in counts.items() if c > 0}
    if any(n < 1 or n > capacity for n in left):
        raise ValueError("lengths must be between 1 and the capacity")
    gaps: list[int] = []  # sorted gaps that have bins
    bins: dict[int, list[list]] = defaultdict(list)  # gap: [lengths, count]

    def put(lengths: tuple[int, ...], gap: int, n: int) -> None:
        if gap not in bins:
            bisect.insort(gaps, gap)
        bins[gap].append([lengths, n])

    large = sorted((n for n in left if 3 * n > capacity), reverse=True)
    for n in large:
        while left.get(n, 0):
            partner = next((m for m in large if m <= min(n, capacity - n) and left.get(m, 0)), None)
            if partner is None:
                put((n,), capacity - n, left[n])
                left[n] = 0
            elif partner == n:
                if left[n] // 2:
                    put((n, n), capacity - 2 * n, left[n] // 2)
                left[n] %= 2
                if left[n]:
                    rest = next((m for m in large if m < n and m <= capacity - n and left.get(m, 0)), None)
                    put((n,) if rest is None else (n, rest), capacity - n - (rest or 0), 1)
                    left[n] = 0
                    if rest is not None:
                        left[rest] -= 1
            else:
                k = min(left[n], left[partner])
                put((n, partner), capacity - n - partner, k)
                left[n] -= k
                left[partner] -= k
    for n in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        todo = left[n]
        while todo:
            i = bisect.bisect_left(gaps, n)
            if i == len(gaps):
                each = capacity // n
                if todo // each:
                    put((n,) * each, capacity - each * n, todo // each)
                if todo % each:
                    put((n,) * (todo % each), capacity - todo % each * n, 1)
                break
            gap = gaps[i]
            each = gap // n
            group = bins[gap]
            lengths, have = group[-1]
            use = min(have, -(-todo // each))
            full = min(use, todo // each)
            if use == have:
                group.pop()
                if not group:
                    del bins[gap]
                    gaps.pop(i)
            else:
                group[-1][1] -= use
            if full:
                put((*lengths, *(n,) * each), gap - each * n, full)
                todo -= full * each
            if use > full:
                put((*lengths, *(n,) * todo), gap - todo * n, use - full)
                todo = 0
    return [(lengths, n) for gap in sorted(bins) for lengths, n in bins[gap]]


def token_pieces(docs: DataFrame, path: str | None = None, lexicon: bytes | None = None, capacity: int = CAPACITY) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32``: the pieces of each document."""
    path = path or default_tokenizer()
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)
    closing = np.array([CLOSING_ID], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, shared.value)
        for batch in batches:
            for part in slices(batch, "text", CHUNK_BYTES):
                flat, edge = enc.encode_all(part.column(1).to_pylist())
                data_of, edge = memoryview(flat.astype("<u4", copy=False)).cast("B"), (4 * edge).tolist()
                ids, piece, start, length, crc = [], [], [], [], []
                for doc_id, a, b in zip(part.column(0).to_pylist(), edge, edge[1:], strict=False):
                    data = bytes(data_of[a:b]) + closing
                    for k, at in enumerate(range(0, len(data), 4 * capacity)):
                        chunk = data[at : at + 4 * capacity]
                        ids.append(doc_id)
                        piece.append(k)
                        start.append(at // 4)
                        length.append(len(chunk) // 4)
                        crc.append(zlib.crc32(chunk))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(ids, pa.int64()), pa.array(piece, pa.int32()), *(pa.array(x, pa.int64()) for x in (start, length, crc))],
                    names=["doc_id", "piece", "start", "length", "ids_crc32"],
                )

    return id_and_text(docs).mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long")


def _slots(plan: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int, int]]:
    """``length, first rank, how many, first bin, offset, places of a bin``: which
    ranks of a length go to which bins, and where in them."""
    used: dict[int, int] = defaultdict(int)
    out, first_bin = [], 0
    for lengths, n in plan:
        at = 0
        while at < len(lengths):
            size, same = lengths[at], 1
            while at + same < len(lengths) and lengths[at + same] == size:
                same += 1
            out.append((size, used[size], same * n, first_bin, sum(lengths[:at]), same))
            used[size] += same * n
            at += same
        first_bin += n
    return out


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """``pieces`` (with ``doc_id, piece, length``) plus ``sequence_id`` and
    ``offset``.  The plan has a row for each run of equal lengths in a make of bin;
    its size depends on the capacity, which is why it may be broadcast."""
    spark = pieces.sparkSession
    pieces = saved(pieces)
    n_rows = pieces.count()
    shares = max(1, n_rows // SHARE_ROWS * 4)
    share = F.pmod(F.xxhash64("doc_id", "piece"), F.lit(shares))
    rows = pieces.withColumn("_share", share)
    by_share = rows.groupBy("length", "_share").agg(F.count(F.lit(1)).alias("_n"))
    counts = {r.length: r.n for r in pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most ``capacity`` rows
    before = F.sum("_n").over(Window.partitionBy("length").orderBy("_share")) - F.col("_n")
    starts = by_share.select(F.col("length").alias("_length"), F.col("_share").alias("_of"), before.alias("_before"))
    local = F.row_number().over(Window.partitionBy("length", "_share").orderBy("doc_id", "piece", *[c for c in ("ids_crc32",) if c in pieces.columns])) - 1
    ranked = (
        rows.withColumn("_local", local)
        .join(starts, (F.col("length") == F.col("_length")) & (F.col("_share") == F.col("_of")))
        .withColumn("_rank", F.col("_before") + F.col("_local"))
    )
    by_length: dict[int, list] = defaultdict(list)
    for size, first, n, first_bin, offset, same in _slots(plan_bins(counts, capacity)):
        by_length[size].append((first, n, first_bin, offset, same))
    shared = spark.sparkContext.broadcast({k: tuple(np.array(c, np.int64) for c in zip(*v, strict=True)) for k, v in by_length.items()})

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        slots = shared.value
        for batch in batches:
            size = batch.column(batch.schema.get_field_index("length")).to_numpy()
            rank = batch.column(batch.schema.get_field_index("_rank")).to_numpy()
            bin_, off = np.empty(len(size), np.int64), np.empty(len(size), np.int64)
            order = np.argsort(size, kind="stable")
            for chunk in np.split(order, np.flatnonzero(np.diff(size[order])) + 1) if len(order) else []:
                n = int(size[chunk[0]])
                first, _, first_bin, offset, same = slots[n]
                k = np.searchsorted(first, rank[chunk], side="right") - 1
                inside = rank[chunk] - first[k]
                bin_[chunk] = first_bin[k] + inside // same[k]
                off[chunk] = offset[k] + inside % same[k] * n
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(batch.num_columns - 1)), pa.array(bin_), pa.array(off)], schema=schema)

    names = pieces.columns
    out = ranked.select(*names, F.col("_rank").cast("long").alias("_rank"))
    result = StructType([*pieces.schema.fields, StructField("sequence_id", LongType()), StructField("offset", LongType())])
    schema = to_arrow_schema(result)
    return out.mapInArrow(place, result)


def lower_bound(counts: dict[int, int], capacity: int = CAPACITY) -> int:
    """Bins that no packing can do without: the tokens, or the pieces above half a
    bin and those that no gap beside them holds."""
    total = -(-sum(n * c for n, c in counts.items()) // capacity)
    best = total
    for t in range(1, capacity // 2 + 1):
        big = sum(c for n, c in counts.items() if n > capacity - t)
        mid_n = sum(c for n, c in counts.items() if capacity / 2 < n <= capacity - t)
        mid = sum(n * c for n, c in counts.items() if capacity / 2 < n <= capacity - t)
        low = sum(n * c for n, c in counts.items() if t <= n <= capacity / 2)
        best = max(best, big + mid_n + max(0, -(-(low - (mid_n * capacity - mid)) // capacity)))
    return best


def pack_documents(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY) -> DataFrame:
    path = path or default_tokenizer()
    return pack(token_pieces(docs, path, build_lexicon(None, path), capacity), capacity)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op10``: all documents packed into sequences of 2048 tokens."""
    return pack_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
