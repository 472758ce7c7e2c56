"""Nearest neighbours by shifted Hilbert orderings of projected vectors.

Every curve projects the vectors on a few random orthogonal directions, shifts the
box they are cut in, and orders them by their place on a Hilbert curve through its
cells.  Spark range-partitions each ordering, so a curve is a row of blocks.  A
query looks at the window of ``window`` neighbours to either side of its own place
on each curve; windows of all curves are merged, and the candidates are ranked by
their exact distance on the original vectors.

Equal vectors are one point: only the eleven smallest ids of each are kept (no
query can need more of them: its ten, and itself), which a limited window does
before the shuffle.  So a vector that a third of the table repeats neither fills a
window nor hides the ids that ties prefer.

A window has ``WINDOW`` points to either side, whatever the size of the table, unless
that finds too few neighbours.  Before the search, ``SAMPLE`` queries are compared with
all points, in blocks; how far apart they and their true neighbours lie on the curves
tells the window that finds ``TARGET`` of these, and the wider of the two is taken.  So
vectors with structure are searched in time that follows their number, and vectors
without any (at 64 independent dimensions neighbours hardly lie nearer than others, and
any order keeps few of them together) still get their neighbours, in windows that grow
with the table.  ``recall`` measures against brute force.

Defined results: vectors that are null, zero, or hold null or non-finite components
take no part, as queries or as candidates, nor do those that have another length than
most (of lengths as frequent, the longest counts); a query with fewer candidates than
asked for gets them all; rows that repeat an id are one vector, the smallest by its
components.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import saved

NEIGHBOURS, QUERY_STEP = 10, 100
CURVES, DIMENSIONS, BITS = 16, 4, 10
WINDOW, BLOCK_ROWS = 256, 4_096
#: Queries that say how wide windows must be, and the share of their neighbours to find.
SAMPLE, TARGET = 64, 0.95
SEED = 11


def hilbert_index(cells: np.ndarray, bits: int) -> np.ndarray:
    """The place of each row of cell coordinates on the Hilbert curve.

    From the coarsest bit on, each level undoes the reflection and the exchange of
    axes that the curve makes in the cell chosen so far; what is left is a Gray
    code over the axes, whose prefix parity is the place.
    """
    x = cells.astype(np.int64).T.copy()
    dims = len(x)
    for level in range(bits - 1, 0, -1):
        bit, below = 1 << level, (1 << level) - 1
        for axis in range(dims):
            inside = (x[axis] & bit) != 0
            swap = np.where(inside, 0, (x[0] ^ x[axis]) & below)
            x[0] ^= np.where(inside, below, swap)
            x[axis] ^= swap
    for axis in range(1, dims):
        x[axis] ^= x[axis - 1]
    flip = np.zeros_like(x[0])
    for level in range(bits - 1, 0, -1):
        flip ^= np.where((x[-1] & (1 << level)) != 0, (1 << level) - 1, 0)
    x ^= flip
    out = np.zeros_like(x[0])
    for level in range(bits - 1, -1, -1):
        for axis in range(dims):
            out = out << 1 | (x[axis] >> level & 1)
    return out


def curve_frames(size: int, curves: int, dims: int, seed: int = SEED) -> list[tuple[np.ndarray, np.ndarray]]:
    """Random orthogonal directions and a shift, for each curve.  Curves share
    bases as long as these have directions left, so they look different ways."""
    rng = np.random.default_rng(seed)
    out, basis, used = [], np.empty((0, size)), 0
    take = min(dims, size)
    for _ in range(curves):
        if used + take > len(basis):
            basis, used = np.linalg.qr(rng.standard_normal((size, size)))[0], 0
        out.append((basis[used : used + take], rng.random(take)))
        used += take
    return out


def curve_keys(vectors: np.ndarray, frame: tuple[np.ndarray, np.ndarray], center: np.ndarray, spread: float, bits: int = BITS) -> np.ndarray:
    """Hilbert keys of the vectors on one curve.  The box covers six spreads and is
    shifted by up to half its size; what lies outside sticks to its faces."""
    directions, shift = frame
    unit = ((vectors - center) @ directions.T) / (12 * spread) + 0.25 + shift / 2
    cells = np.clip((unit * (1 << bits)).astype(np.int64), 0, (1 << bits) - 1)
    return hilbert_index(cells, bits)


def _plain(vectors: DataFrame) -> Column:
    """The vectors in their own precision, without negative zeros."""
    kind = "double" if dict(vectors.dtypes)["embedding"] == "array<double>" else "float"
    return F.transform(F.col("embedding").cast(f"array<{kind}>"), lambda x: F.when(x == 0, F.lit(0.0).cast(kind)).otherwise(x))


def points(vectors: DataFrame, keep: int = NEIGHBOURS + 1) -> DataFrame:
    """``point`` (smallest id), ``vector``, ``ids``: distinct usable vectors, with
    at most ``keep`` of their smallest ids."""
    v = _plain(vectors)
    usable = v.isNotNull() & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))) & F.exists(v, lambda x: x != 0)
    rows = vectors.select(F.col("vec_id").cast("long").alias("id"), v.alias("vector")).filter(F.col("id").isNotNull() & usable)
    lengths = rows.groupBy(F.size("vector").alias("size")).agg(F.count(F.lit(1)).alias("n"))
    usual = lengths.orderBy(F.desc("n"), F.desc("size")).first()
    rows = rows.filter(F.size("vector") == (usual.size if usual else 0)).groupBy("id").agg(F.min("vector").alias("vector"))
    ranked = rows.withColumn("n", F.row_number().over(Window.partitionBy("vector").orderBy("id"))).filter(F.col("n") <= keep)
    return ranked.groupBy("vector").agg(F.sort_array(F.collect_list("id")).alias("ids")).select(F.col("ids")[0].alias("point"), "vector", "ids")


def _ordered(pts: DataFrame, curves: int, dims: int, blocks: int, seed: int) -> DataFrame:
    """``curve, place, point, vector``: the points on every curve, places from 0."""
    first = pts.select("vector").first()
    if first is None:
        return pts.select(F.lit(0).alias("curve"), F.lit(0).cast("long").alias("place"), "point", "vector")
    size = len(first.vector)
    moments = pts.select(*[F.avg(F.col("vector")[i].cast("double")).alias(f"m{i}") for i in range(size)], F.avg(F.aggregate("vector", F.lit(0.0), lambda a, x: a + x.cast("double") * x)).alias("square")).first()
    center = np.array(moments[:size])
    spread = max(float(np.sqrt(max(moments["square"] - center @ center, 0) / size)), 1e-300)
    frames = curve_frames(size, curves, dims, seed)

    def keys(batches):
        for batch in batches:
            x = np.array(batch.column(1).to_pylist(), np.float64).reshape(batch.num_rows, -1)
            for c, frame in enumerate(frames):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), c, np.int32)), pa.array(curve_keys(x, frame, center, spread)), batch.column(0), batch.column(1)], names=["curve", "key", "point", "vector"])

    keyed = pts.select("point", "vector").mapInArrow(keys, f"curve int, key long, point long, vector {dict(pts.dtypes)['vector']}")
    ordered = keyed.repartitionByRange(blocks, "curve", "key", "point").sortWithinPartitions("curve", "key", "point")
    row = F.monotonically_increasing_id()
    ordered = saved(ordered.select("curve", "point", "vector", F.shiftright(row, 33).alias("part"), row.bitwiseAND(F.lit((1 << 33) - 1)).alias("row")))
    sizes = ordered.groupBy("curve", "part").agg(F.count(F.lit(1)).alias("n"), F.min("row").alias("low"))
    before = sizes.withColumn("before", F.sum("n").over(Window.partitionBy("curve").orderBy("part")) - F.col("n"))
    return ordered.join(before.select("curve", "part", "low", "before"), ["curve", "part"]).select("curve", (F.col("before") + F.col("row") - F.col("low")).alias("place"), "point", "vector")


def _exact(query: np.ndarray, candidates: np.ndarray) -> np.ndarray:
    """Distances in double precision, summed component by component."""
    total = np.zeros(len(candidates))
    for j in range(candidates.shape[1]):
        d = candidates[:, j] - query[j]
        total += d * d
    return np.sqrt(total)


def _block_nearest(k: int, window: int):
    def run(block: pa.Table, queries: pa.Table) -> pa.Table:
        out: list[tuple[int, int, float]] = []
        if block.num_rows and queries.num_rows:
            place = block.column("place").to_numpy()
            point = block.column("point").to_numpy()
            x = np.array(block.column("vector").to_pylist(), np.float64)
            q_place = queries.column("q_place").to_numpy()
            q = np.array(queries.column("q_vector").to_pylist(), np.float64)
            norm = (x * x).sum(axis=1)
            for i in range(0, len(q), 256):
                part = q[i : i + 256]
                near = norm[None, :] - 2 * part @ x.T
                near[np.abs(place[None, :] - q_place[i : i + 256, None]) > window] = np.inf
                for j, row in enumerate(near):
                    inside = int(np.isfinite(row).sum())
                    if not inside:
                        continue
                    pick = np.flatnonzero(np.isfinite(row))
                    if inside > k:
                        limit = np.partition(row, k - 1)[k - 1]
                        # a little room for rounding; ties are settled on exact distances
                        pick = np.flatnonzero(row <= limit + 1e-9 * (abs(limit) + 1))
                    d = _exact(part[j], x[pick])
                    best = np.lexsort((point[pick], d))[:k]
                    query = int(queries.column("q_point")[i + j].as_py())
                    out += [(query, int(point[pick[b]]), float(d[b])) for b in best]
        return pa.table({"query": pa.array([r[0] for r in out], pa.int64()), "point": pa.array([r[1] for r in out], pa.int64()), "score": pa.array([r[2] for r in out], pa.float64())})

    return run


def _sample_nearest(pts: DataFrame, queries: dict[int, list[float]], k: int) -> DataFrame:
    """``query, point, n_ids``: the ``k`` nearest points of a few queries, by comparison
    with all points."""
    names, q = np.array(list(queries), np.int64), np.array(list(queries.values()), np.float64)

    def run(batches):
        for batch in batches:
            x = np.array(batch.column(1).to_pylist(), np.float64).reshape(batch.num_rows, -1)
            for name, vector in zip(names.tolist(), q, strict=True):
                d = _exact(vector, x)
                best = np.lexsort((batch.column(0).to_numpy(), d))[:k]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(best), name)), batch.column(0).take(pa.array(best)), batch.column(2).take(pa.array(best)), pa.array(d[best])], names=["query", "point", "n_ids", "score"])

    found = pts.select("point", "vector", F.size("ids").alias("n_ids")).mapInArrow(run, "query long, point long, n_ids int, score double")
    return found.withColumn("n", F.row_number().over(Window.partitionBy("query").orderBy("score", "point"))).filter(F.col("n") <= k)


def needed_window(pts: DataFrame, asked: DataFrame, ordered: DataFrame, k: int, target: float = TARGET, sample: int = SAMPLE) -> int:
    """The window that finds ``target`` of the neighbours of ``sample`` queries.  All that
    is collected follows ``sample``, ``k`` and the number of curves."""
    some = asked.select("query").distinct().orderBy(F.xxhash64("query"), "query").limit(sample)
    queries = {r.point: r.vector for r in pts.join(F.broadcast(some), F.col("point") == F.col("query"), "left_semi").select("point", "vector").collect()}
    if not queries:
        return 0
    near: dict[int, list] = {}
    for r in sorted(_sample_nearest(pts, queries, k + 1).collect(), key=lambda r: (r["query"], r.n)):
        near.setdefault(r["query"], []).append(r)
    pairs = []
    for query, rows in near.items():
        have = -1  # the query's own id
        for r in rows:
            if have >= k:
                break
            pairs.append((query, r.point))
            have += r.n_ids
    spark = pts.sparkSession
    wanted = spark.createDataFrame(sorted({(p,) for pair in pairs for p in pair}), "wanted long")
    places = ordered.join(F.broadcast(wanted), F.col("point") == F.col("wanted"), "left_semi").select("curve", "point", "place").collect()
    curves = sorted({r.curve for r in places})
    at = {p: np.zeros(len(curves), np.int64) for (p,) in wanted.collect()}
    for r in places:
        at[r.point][curves.index(r.curve)] = r.place
    apart = np.sort([np.abs(at[a] - at[b]).min() for a, b in pairs])
    return int(apart[min(len(apart), int(np.ceil(target * len(apart)))) - 1])


def nearest(vectors: DataFrame, step: int = QUERY_STEP, k: int = NEIGHBOURS, curves: int = CURVES, dims: int = DIMENSIONS, window: int = WINDOW, target: float = TARGET, seed: int = SEED) -> DataFrame:
    """``query_id, rank, vec_id, score`` for the ids divisible by ``step``.  ``target``
    0: windows of ``window``, whatever they find."""
    pts = saved(points(vectors, k + 1))
    n = pts.count()
    blocks = max(1, -(-n * curves // BLOCK_ROWS))
    block = F.floor(F.col("place") / F.lit(BLOCK_ROWS)).cast("long")
    ordered = _ordered(pts, curves, dims, blocks, seed).withColumn("block", block)
    # ids beyond the kept ones of a vector ask too, so queries find their points by vector
    all_ids = vectors.select(F.col("vec_id").cast("long").alias("query_id"), _plain(vectors).alias("v")).filter(F.pmod("query_id", F.lit(step)) == 0)
    all_ids = all_ids.groupBy("query_id").agg(F.min("v").alias("v"))
    asked = all_ids.join(pts.select(F.col("vector").alias("v"), F.col("point").alias("query")), "v").select("query_id", "query")
    asked = saved(asked)
    if target > 0:
        window = max(window, needed_window(pts, asked, ordered, k, target))
    here = ordered.join(asked.select(F.col("query").alias("point")).distinct(), "point", "left_semi")
    reach = here.withColumn("block", F.explode(F.sequence(F.greatest(F.floor((F.col("place") - window) / BLOCK_ROWS), F.lit(0)), F.floor((F.col("place") + window) / BLOCK_ROWS)).cast("array<long>")))
    reach = reach.select(*[F.col(c).alias(f"q_{c}") for c in ("curve", "block", "place", "point", "vector")])
    found = ordered.groupBy("curve", "block").cogroup(reach.groupBy("q_curve", "q_block")).applyInArrow(_block_nearest(k + 1, window), "query long, point long, score double")
    best = found.distinct().withColumn("n", F.row_number().over(Window.partitionBy("query").orderBy("score", "point"))).filter(F.col("n") <= k + 1).drop("n")
    pairs = asked.join(best, "query").join(pts.select("point", "ids"), "point").select("query_id", "score", F.explode("ids").alias("vec_id")).filter("vec_id <> query_id")
    ranked = pairs.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id"))).filter(F.col("rank") <= k)
    return ranked.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op2``: ten nearest of every hundredth vector."""
    return nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet"))


def recall(found: DataFrame, exact: DataFrame) -> float:
    """Share of the exact neighbours that were found."""
    return found.join(exact, ["query_id", "vec_id"], "left_semi").count() / max(1, exact.count())


#: Brute force.  In a table of some hundred vectors the windows of all curves together
#: miss none; larger ones are tested for their recall.
ORACLE_SQL = f"""
WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0 AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
d AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, sqrt(list_reduce(list_prepend(0.0::DOUBLE, list_transform(list_zip(q.e, c.e), lambda p: (p[1] - p[2]) * (p[1] - p[2]))), lambda a, b: a + b)) AS score FROM v q, v c WHERE q.vec_id % {QUERY_STEP} = 0 AND c.vec_id <> q.vec_id),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score, vec_id) AS INTEGER) AS rank FROM d)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= {NEIGHBOURS}
"""
