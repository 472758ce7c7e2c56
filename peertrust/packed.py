"""Large graphs as blocks of arrays: a row of a table holds many pairs, as bytes.

A block has whole pairs ``a, b`` with their net before (``was``) and after (``net``)
the last change.  A pair's hash says which block it is in, so a change is split like
the blocks and meets them there; no task sees all pairs, and what is shuffled and
written are a few large rows.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from peertrust.sources.tables import cut

#: Pairs of a block, about.
BLOCK = 500_000
PAIRS = ("a", "b", "was", "net")
SCHEMA = "part int, n int, a binary, b binary, was binary, net binary"


def small(column: np.ndarray) -> np.ndarray:
    """Whole numbers in as few bytes as they fit."""
    low, high = (column.min(), column.max()) if len(column) else (0, 0)
    return column.astype(next(t for t in (np.int8, np.int16, np.int32, np.int64) if np.iinfo(t).min <= low and high <= np.iinfo(t).max))


def row(part: int, *columns: np.ndarray) -> tuple:
    return (part, len(columns[0]), *(small(c).tobytes() for c in columns))


def table(rows: list[tuple], names: tuple[str, ...]) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.int32(), *[pa.binary()] * len(names)]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], ["part", "n", *names])


def read(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    """``part`` and the arrays of each block."""
    for batch in batches:
        for part, n, *columns in zip(*batch.columns, strict=True):
            n = n.as_py()
            yield part.as_py(), *(np.frombuffer(c.as_buffer(), f"i{c.as_buffer().size // n}") for c in columns)


def split(part: np.ndarray, parts: int, *columns: np.ndarray) -> list[tuple]:
    """A row for each number in ``part``."""
    order = np.argsort(part, kind="stable")
    ends = np.searchsorted(part[order], np.arange(parts + 1))
    return [row(k, *(c[order[i:j]] for c in columns)) for k, (i, j) in enumerate(zip(ends[:-1], ends[1:], strict=True)) if i < j]


def hashed(parts: int, *columns: np.ndarray) -> np.ndarray:
    key = np.zeros(len(columns[0]), np.uint64)
    for c in columns:
        key = (key ^ c.astype(np.int64).view(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        key ^= key >> np.uint64(29)
    return ((key * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(33)).astype(np.int64) % parts


def by_two(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    """The order by two columns; rows that are equal in both may come in any."""
    if len(first) and min(first.min(), second.min()) >= 0 and max(first.max(), second.max()) < 1 << 31:
        return np.argsort(first.astype(np.int64) << 32 | second.astype(np.int64))
    return np.lexsort((second, first))


def packed(nets: DataFrame) -> DataFrame:
    """Rows ``a, b, net`` as blocks in no order (``part`` -1)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        have, n = [], 0

        def out() -> pa.RecordBatch:
            a, b, net = (np.concatenate([x.column(c).to_numpy() for x in have]) for c in ("a", "b", "net"))
            return table([row(-1, a, b, np.zeros(len(a), np.int8), net)], PAIRS)

        for batch in batches:
            if batch.num_rows:
                have, n = [*have, batch], n + batch.num_rows
            if n >= BLOCK:
                yield out()
                have, n = [], 0
        if n:
            yield out()

    return nets.select("a", "b", "net").mapInArrow(run, SCHEMA)


def pairs(blocks: DataFrame) -> int:
    return blocks.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]


def merged(old: DataFrame, fresh: DataFrame, n: int) -> DataFrame:
    """The blocks after the changes ``fresh``; ``n``: pairs in both.  What was the net is
    ``was`` now."""
    parts = max(1, -(-n // BLOCK))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, a, b, _, net in read(batches):
            was = net if part >= 0 else np.zeros(len(a), np.int8)
            yield table(split(hashed(parts, a, b), parts, a, b, was, net), PAIRS)

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[int, list] = {}
        for part, *columns in read(batches):
            found.setdefault(part, []).append(columns)
        for part in sorted(found):
            a, b, was, net = (np.concatenate(c) for c in zip(*found.pop(part), strict=True))
            order = by_two(a, b)
            a, b = a[order], b[order]
            first = np.flatnonzero(np.append(True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])))
            was, net = (np.add.reduceat(c[order].astype(np.int64), first) for c in (was, net))
            keep = (was != 0) | (net != 0)  # a pair that is even has no edge, and adds nothing to what comes
            if keep.any():
                yield table([row(part, *(c[keep] for c in (a[first], b[first], was, net)))], PAIRS)

    return cut(old.union(fresh).mapInArrow(deal, SCHEMA).repartitionById(parts, "part").mapInArrow(merge, SCHEMA))


def directed(a: np.ndarray, b: np.ndarray, net: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``src, dst, w`` of pairs that are not even: from the net receiver to the net giver."""
    keep = net != 0
    a, b, net = a[keep], b[keep], net[keep].astype(np.int64)
    giver = net > 0
    return np.where(giver, b, a), np.where(giver, a, b), np.abs(net)


def _rows(*columns: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in columns], ["src", "dst", "w"])


def edges_of(blocks: DataFrame, before: bool = False, among: np.ndarray | None = None) -> DataFrame:
    """``src, dst, w`` of the graph after (or before) the last change; ``among``: of these
    sources alone."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, a, b, was, net in read(batches):
            edges = directed(a, b, was if before else net)
            yield _rows(*(edges if among is None else (c[np.isin(edges[0], among)] for c in edges)))

    return blocks.mapInArrow(run, "src long, dst long, w long")


def gathered(blocks: DataFrame, work: Callable[..., pd.DataFrame], schema: str) -> pd.DataFrame:
    """The few rows of ``work`` on all pairs, done in one task of an executor."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = sorted(read(batches), key=lambda x: x[0])
        columns = [np.concatenate([x[i] for x in found]) if found else np.empty(0, np.int64) for i in range(1, 5)]
        del found
        yield from pa.Table.from_pandas(work(*columns), preserve_index=False).to_batches(10_000)

    return blocks.repartition(1).mapInArrow(run, schema).toArrow().to_pandas()


ARC_SCHEMA = "part int, n int, src binary, dst binary, w binary"
#: Edges of a block of arcs, about.
ARCS = 2_000_000


def arcs(edges: DataFrame, by: str = "src") -> DataFrame:
    """Edges as blocks that hold all edges of their sources (or ``by`` ``dst``), in the
    order of these, made once a frame of counted edges."""
    made = edges.__dict__.setdefault("_peertrust_arcs", {})
    if by in made:
        return made[by]
    parts, key = max(1, -(-edges._peertrust_rows // ARCS)), 0 if by == "src" else 1
    blocks = getattr(edges, "_peertrust_blocks", None)
    plain, before = blocks is None, getattr(edges, "_peertrust_before", False)

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for e in ([b.column(c).to_numpy() for c in ("src", "dst", "w")] for b in batches) if plain else (directed(a, b, was if before else net) for _, a, b, was, net in read(batches)):
            if len(e[0]):
                yield table(split(hashed(parts, e[key]), parts, *e), ("src", "dst", "w"))

    def order(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dealt: dict[int, list] = {}
        for part, *columns in read(batches):
            dealt.setdefault(part, []).append(columns)
        for part in sorted(dealt):
            e = [np.concatenate(c) for c in zip(*dealt.pop(part), strict=True)]
            at = by_two(e[key], e[1 - key])
            yield table([row(part, *(c[at] for c in e))], ("src", "dst", "w"))

    given = edges.select("src", "dst", "w") if plain else blocks
    made[by] = cut(given.mapInArrow(deal, ARC_SCHEMA).repartitionById(parts, "part").mapInArrow(order, ARC_SCHEMA))
    return made[by]


def hops(edges: DataFrame, node: np.ndarray, draw: np.ndarray) -> np.ndarray:
    """Where walkers at ``node`` go (-1: no way out).  A source's edges meet the draws
    where they are."""
    blocks = arcs(edges)
    parts = max(1, -(-edges._peertrust_rows // ARCS))
    wanted = np.unique(hashed(parts, node)).tolist()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, src, dst, w in read(batches):
            low, high = np.searchsorted(src, node, "left"), np.searchsorted(src, node, "right")
            i = np.flatnonzero(low < high)
            low, high = low[i], high[i]
            ends = np.cumsum(w, dtype=np.int64)
            base = ends[low] - w[low]
            total = ends[high - 1] - base
            if len(i) and int(total.max()) >= 1 << 31:
                raise ValueError("weights of a source must sum to less than 2**31")
            to = dst[np.searchsorted(ends, base + (draw[i] * total >> 32), side="right")] if len(i) else dst[:0]
            yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int64)), pa.array(to.astype(np.int64))], ["i", "to"])

    found = blocks.filter(F.col("part").isin(wanted)).mapInArrow(run, "i long, to long").toArrow()
    out = np.full(len(node), -1, np.int64)
    out[found.column("i").to_numpy()] = found.column("to").to_numpy()
    return out


def out_weights(edges: DataFrame, weighting: str = "weight") -> DataFrame:
    """``node, out``: the weight (or number) of each source's edges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, src, _, w in read(batches):
            first = np.flatnonzero(np.append(True, src[1:] != src[:-1]))
            out = np.add.reduceat(w.astype(float) if weighting == "weight" else np.ones(len(w)), first)
            yield pa.RecordBatch.from_arrays([pa.array(src[first].astype(np.int64)), pa.array(out)], ["node", "out"])

    return arcs(edges).mapInArrow(run, "node long, out double")


def targets(edges: DataFrame) -> DataFrame:
    """``node`` of each target of edges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, dst, _ in read(batches):
            yield pa.RecordBatch.from_arrays([pa.array(dst[np.append(True, dst[1:] != dst[:-1])].astype(np.int64))], ["node"])

    return arcs(edges, "dst").mapInArrow(run, "node long")


def placed(edges: DataFrame, node: np.ndarray) -> DataFrame:
    """The blocks by target, with places among the sorted nodes for their numbers."""
    shared = edges.sparkSession.sparkContext.broadcast(node)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, src, dst, w in read(batches):
            yield table([row(part, np.searchsorted(shared.value, src), np.searchsorted(shared.value, dst), w)], ("src", "dst", "w"))

    return cut(arcs(edges, "dst").mapInArrow(run, ARC_SCHEMA))


def flows(blocks: DataFrame, x: np.ndarray, weighting: str = "weight") -> np.ndarray:
    """What flows to each node from sources that give ``x`` (rows: one vector each) for a
    unit of weight."""
    shared = blocks.sparkSession.sparkContext.broadcast(x)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, src, dst, w in read(batches):
            first = np.flatnonzero(np.append(True, dst[1:] != dst[:-1]))
            for i, v in enumerate(shared.value):
                y = np.add.reduceat(v[src] * w if weighting == "weight" else v[src], first)
                yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([dst[first].astype(np.int64).tobytes()]), pa.array([y.tobytes()])], ["i", "node", "y"])

    out = np.zeros(x.shape)
    for batch in blocks.mapInArrow(run, "i int, node binary, y binary").toArrow().to_batches():
        for i, node, y in zip(*batch.columns, strict=True):
            out[i.as_py(), np.frombuffer(node.as_buffer(), np.int64)] = np.frombuffer(y.as_buffer(), float)
    shared.destroy()
    return out
