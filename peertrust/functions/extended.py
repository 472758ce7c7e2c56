"""Functions in Python where SQL has none: vectorised scalars, aggregates, and table
functions.  Each has a built-in twin that the tests compare it with."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf

from peertrust.functions.rng import RNG_SEED
from peertrust.walks import Adjacency, local_edges, run_walks, shared_edges, step_cap


@F.pandas_udf(T.LongType())
def u32_udf(key: pd.Series) -> pd.Series:
    """The draw of a joined key; ``functions.rng.u32`` is the built-in form."""
    return key.map(lambda k: int(hashlib.md5(k.encode()).hexdigest()[:8], 16))


@F.pandas_udf(T.DoubleType())
def auroc_udaf(score: pd.Series, honest: pd.Series) -> float:
    """Area under the curve of one group, with midranks; NaN for one class."""
    ranks, n1 = score.rank(), int(honest.sum())
    n0 = len(honest) - n1
    return float((ranks[honest].sum() - n1 * (n1 + 1) / 2) / (n1 * n0)) if n1 and n0 else float("nan")


@F.pandas_udf(T.DoubleType())
def kendall_udaf(a: pd.Series, b: pd.Series) -> float:
    """Kendall's tau-b of one group, its pairs a block of rows at a time."""
    x, y = a.to_numpy(float), b.to_numpy(float)
    both = nx = ny = 0.0
    for i in range(0, len(x), 512):
        p, q = (np.sign(v[i : i + 512, None] - v[None, :]) for v in (x, y))
        both, nx, ny = both + (p * q).sum(), nx + (p * p).sum(), ny + (q * q).sum()
    norm = np.sqrt(nx * ny)
    return float(both / norm) if norm else float("nan")


@udtf(returnType=T.StructType([T.StructField("cut", T.LongType()), T.StructField("node", T.LongType()), T.StructField("fpr", T.DoubleType()), T.StructField("tpr", T.DoubleType())]))
class RocPoints:
    """Points of the curve of one partition of a table of ``node, is_honest, score``."""

    def __init__(self):
        self.rows = []

    def eval(self, row):
        self.rows.append((-row["score"], row["node"], row["is_honest"]))

    def terminate(self) -> Iterator[tuple]:
        self.rows.sort()
        honest = sum(h for *_, h in self.rows)
        other, tp, fp = len(self.rows) - honest, 0, 0
        for i, (_, node, h) in enumerate(self.rows, 1):
            tp, fp = tp + h, fp + (not h)
            yield i, node, fp / other if other else None, tp / honest if honest else None


def register_walk(spark: SparkSession, edges: DataFrame, name: str = "walk") -> None:
    """A table function ``walk(seed, walk_id, alpha)`` on a graph that is small enough
    to be broadcast: its rows are ``step, node``."""
    found, kept = local_edges(edges)
    if found is None:
        raise ValueError("the graph is too large for a table function")
    shared = shared_edges(spark, found, kept)

    @udtf(returnType="step: int, node: long")
    class Walk:
        def __init__(self):
            self.graph = Adjacency(*shared.value)

        def eval(self, seed: int, walk_id: int, alpha: float):
            task = pd.DataFrame({"walk_id": [walk_id], "seed": [seed], "gen": [0], "step": [0], "node": [seed]})
            yield 0, seed
            rest = run_walks(self.graph, task, np.array([alpha]), RNG_SEED, step_cap(alpha))
            yield from zip(rest["step"].tolist(), rest["node"].tolist(), strict=True)

    spark.udtf.register(name, Walk)
