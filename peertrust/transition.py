"""Hop laws: transition probabilities, integer cumulative intervals, bins, aliases."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from peertrust.graph import nodes as graph_nodes
from peertrust.sources.tables import cut

#: Entries of the dense matrix that one task makes, about.
DENSE_PART = 4_000_000


def transitions(edges: DataFrame, weighting: str = "weight") -> DataFrame:
    """``src, dst, p``: proportional to weight, or equal among out-edges."""
    by = Window.partitionBy("src")
    p = F.col("w") / F.sum("w").over(by) if weighting == "weight" else F.lit(1.0) / F.count(F.lit(1)).over(by)
    return edges.select("src", "dst", p.alias("p"))


def dangling(edges: DataFrame) -> DataFrame:
    return graph_nodes(edges).join(edges.select(F.col("src").alias("node")).distinct(), "node", "left_anti")


def dense_transition(edges: DataFrame, alpha: float, seed: int | None = None) -> DataFrame:
    """Every entry of the teleporting matrix: reset mass to the seed or to all nodes;
    dangling rows behave as a reset.  A task makes whole rows from the laws of their
    sources; the nodes' numbers go to all tasks, and no entry is shuffled."""
    node = cut(graph_nodes(edges))
    names = np.sort(node.toArrow().column("node").to_numpy())
    shared = edges.sparkSession.sparkContext.broadcast(names)
    law = transitions(edges).groupBy("src").agg(F.collect_list("dst").alias("dst"), F.collect_list("p").alias("p"))
    parts = max(1, min(len(names), -(-(len(names) ** 2) // DENSE_PART)))
    rows = node.withColumnRenamed("node", "src").join(law, "src", "left").repartition(parts, "src")

    def fill(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = shared.value
        t = np.full(len(names), 1.0 / len(names)) if seed is None else (names == seed).astype(float)
        for batch in batches:
            for src, dst, p in zip(*(batch.column(c) for c in ("src", "dst", "p")), strict=True):
                entry = t
                if dst.is_valid:
                    entry = np.zeros(len(names))
                    entry[np.searchsorted(names, dst.values.to_numpy())] = p.values.to_numpy()
                    entry = (1 - alpha) * entry + alpha * t
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(names), src.as_py())), pa.array(names), pa.array(entry)], ["src", "dst", "p"])

    return rows.select("src", "dst", "p").mapInArrow(fill, "src long, dst long, p double")


def cdf(edges: DataFrame) -> DataFrame:
    """``src, dst, w, lo, hi, tot``: whole-number intervals that tile ``[0, tot)``."""
    order = Window.partitionBy("src").orderBy("dst").rowsBetween(Window.unboundedPreceding, 0)
    hi = F.sum("w").over(order)
    return edges.select("src", "dst", "w", (hi - F.col("w")).alias("lo"), hi.alias("hi"), F.sum("w").over(Window.partitionBy("src")).alias("tot"))


def binned_cdf(table: DataFrame, target: int = 16) -> DataFrame:
    """``cdf`` with a copy of an interval for each bin that it overlaps.  A source
    has about one bin for ``target`` edges, so a hop at a hub joins by ``(src, bin)``
    and meets about ``target`` rows whatever the degree."""
    degree = F.count(F.lit(1)).over(Window.partitionBy("src"))
    n = table.withColumn("bins", F.ceil(degree / F.lit(target)).cast("long"))
    low = F.floor(F.col("lo") * F.col("bins") / F.col("tot")).cast("long")
    high = F.floor((F.col("hi") - 1) * F.col("bins") / F.col("tot")).cast("long")
    # one bin more to either side covers rounding
    spread = F.sequence(F.greatest(low - 1, F.lit(0).cast("long")), F.least(high + 1, F.col("bins") - 1))
    return n.select("*", F.explode(spread).alias("bin"))


def alias_table(edges: DataFrame) -> DataFrame:
    """``src, slot, n, keep, dst, other``: Walker's alias method, so that a hop is an
    equality join on ``(src, slot)``.  A source's edges meet in one task."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("dst")
        n, dst = len(pdf), pdf["dst"].to_numpy()
        scaled = pdf["w"].to_numpy(float) * n / pdf["w"].sum()
        keep, other = np.ones(n), dst.copy()
        small, large = [i for i in range(n) if scaled[i] < 1], [i for i in range(n) if scaled[i] >= 1]
        while small and large:
            s, b = small.pop(), large[-1]
            keep[s], other[s] = scaled[s], dst[b]
            scaled[b] -= 1 - scaled[s]
            if scaled[b] < 1:
                small.append(large.pop())
        return pd.DataFrame({"src": pdf["src"].iloc[0], "slot": np.arange(n), "n": n, "keep": keep, "dst": dst, "other": other})

    return edges.groupBy("src").applyInPandas(build, "src long, slot long, n long, keep double, dst long, other long")
