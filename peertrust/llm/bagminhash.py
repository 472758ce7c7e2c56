"""Near-duplicate classes by weighted minwise hashing of word shingles.

A document is the multiset of its five-word shingles; its likeness to another is
the weighted Jaccard index of the two.

Signatures.  A shingle of weight ``w`` owns the levels ``0 .. w-1``; every level of
every shingle is a Poisson process of rate one whose points fall on random
signature places, and a place keeps its earliest point.  The levels of a heavy
shingle are not walked one by one: a block of levels has one process, whose first
point is split down the halves of the block, and a half whose first point comes
after all that the signature can still use is dropped whole.  Two documents agree
on a place exactly with the probability of their weighted Jaccard index.  All
documents of a chunk advance together, array by array.

Classes.
1.  Documents with equal shingle multisets are one; the smallest id stands for them.
2.  Signatures are cut into bands; equal bands make a bucket.  (At a likeness of
    0.8, 32 bands of 4 miss a pair once in 20 million.)
3.  Every bucket is a star around its smallest member: links to it are verified on
    the exact multisets.  So a group of thousands of copies costs a few links a
    member, never all pairs.
4.  What then still shares a bucket without having a hub in common is compared by
    signature; members that might reach the threshold with one of another hub are
    compared exactly, as products of incidence matrices.  A large bucket is dealt out
    to blocks of bounded size, and every pair of blocks is a piece of work of its own,
    so a bucket of thousands of unlike documents takes many tasks, none of them large.
    Only links that join components leave a task.

A class is a component of documents linked at ``SIMILARITY`` or above, named by its
smallest id.

Defined results: null texts are empty; a text of fewer than five words is one
shingle; texts without words, and rows without id, are classes of their own; rows
that repeat an id are one document, with the greatest of their texts, and repeat its
class.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import MapType

from .bytehash import mix
from .common import fresh, id_and_text, saved, shared_dir, slices, text_or_empty, utf8
from .wordhash import runs, tokens

SHINGLE, SIMILARITY = 5, 0.8
BANDS, ROWS = 32, 4
PLACES = BANDS * ROWS
#: Estimated likeness from which a pair is verified in the last step: five standard
#: errors below the threshold.
_MIGHT = SIMILARITY - 5 * (SIMILARITY * (1 - SIMILARITY) / PLACES) ** 0.5
_BLOCK = 1024
#: Rows and bytes of a block of a bucket, and of the work of one task, in the last step.
_BLOCK_ROWS, _BLOCK_BYTES = 4_096, 4 << 20
_GROUP_ROWS, _GROUP_BYTES = 10_000, 8 << 20
#: Shingles whose occurrences are told apart together, of at most so many sets.
_OVERLAP_SHINGLES, _OVERLAP_SETS = 1 << 18, 512


def shingle_multisets(buf: np.ndarray, offsets: np.ndarray, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """``text number, shingle hash, weight``, ordered by text and hash."""
    text, shingle = runs(*tokens(buf, offsets, "fields"), k)
    edge = np.searchsorted(text, np.arange(len(offsets)))
    shingle = shingle.copy()
    for a, b in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        shingle[a:b].sort()
    if not len(text):
        return text, shingle, np.empty(0, np.int64)
    new = np.flatnonzero(np.concatenate([[True], (text[1:] != text[:-1]) | (shingle[1:] != shingle[:-1])]))
    return text[new], shingle[new], np.diff(np.concatenate([new, [len(text)]]))


def _exponential(bits: np.ndarray) -> np.ndarray:
    return -np.log(((bits >> np.uint64(11)).astype(np.float64) + 0.5) / float(1 << 53))


def signatures(text: np.ndarray, shingle: np.ndarray, weight: np.ndarray, n_texts: int, places: int = PLACES) -> np.ndarray:
    """``n_texts x places`` earliest points (their bits; all ones: no shingle)."""
    out = np.full((n_texts, places), np.inf)
    total = np.bincount(text, weights=weight, minlength=n_texts)
    horizon = places / np.maximum(total, 1) * (np.log(places) + 3)
    todo = total > 0
    while todo.any():
        pick = todo[text]
        _points(text[pick], shingle[pick], weight[pick], horizon, out)
        todo &= ~(out.max(axis=1) < horizon)  # a place without a point before the horizon: look further
        horizon = np.where(todo, horizon * 2, horizon)
        out[todo] = np.inf
    return np.where(np.isinf(out), np.uint64(0xFFFFFFFFFFFFFFFF), out.view(np.uint64))


def _points(text: np.ndarray, shingle: np.ndarray, weight: np.ndarray, horizon: np.ndarray, out: np.ndarray) -> None:
    """All points before the horizon, into ``out``."""
    # blocks of levels: 0, 1, 2-3, 4-7, ...
    levels = np.ceil(np.log2(np.maximum(weight, 1))).astype(np.int64) + 1
    owner = np.repeat(np.arange(len(text)), levels)
    block = np.arange(len(owner)) - np.repeat(np.cumsum(levels) - levels, levels)
    low = np.where(block == 0, 0, 1 << np.maximum(block - 1, 0))
    size = np.where(block == 0, 1, low)
    state = mix(shingle[owner] ^ mix(low.astype(np.uint64) * np.uint64(2) + np.uint64(1)))
    x = _exponential(state) / size
    while True:
        live = np.flatnonzero((x < horizon[text[owner]]) & (low < weight[owner]))
        if not len(live):
            return
        owner, low, size, state, x = owner[live], low[live], size[live], state[live], x[live]
        leaf = size == 1
        one = np.flatnonzero(leaf)
        place = (mix(state[one] + np.uint64(0xC2B2AE3D27D4EB4F)) % np.uint64(out.shape[1])).astype(np.int64)
        np.minimum.at(out.reshape(-1), text[owner[one]] * out.shape[1] + place, x[one])
        later = mix(state[one] * np.uint64(0x9E3779B97F4A7C15) + np.uint64(1))
        two = np.flatnonzero(~leaf)
        if len(two):
            half = size[two] // 2
            right = (mix(state[two] + np.uint64(0x165667B19E3779F9)) >> np.uint64(63)).astype(np.int64)  # the half with the first point
            kept = mix(state[two] + np.uint64(0x27D4EB2F165667C5))
            fresh = mix(state[two] + np.uint64(0x85EBCA77C2B2AE63))
            owner = np.concatenate([owner[one], owner[two], owner[two]])
            new_low = np.concatenate([low[one], low[two] + right * half, low[two] + (1 - right) * half])
            x = np.concatenate([x[one] + _exponential(later), x[two], x[two] + _exponential(fresh) / half])
            state = np.concatenate([later, kept, fresh])
            size = np.concatenate([size[one], half, half])
            low = new_low
        else:
            owner, low, size = owner[one], low[one], size[one]
            x, state = x[one] + _exponential(later), later


def weighted_jaccard(a: np.ndarray, b: np.ndarray) -> float:
    """Of two multisets, as ordered hashes that stand as often as they weigh."""
    if not len(a) or not len(b):
        return 0.0
    both = np.concatenate([a, b])
    order = np.argsort(both, kind="stable")
    run = both[order]
    edge = np.flatnonzero(np.concatenate([[True], run[1:] != run[:-1], [True]]))
    ours = np.concatenate([[0], np.cumsum(order < len(a))])[edge]
    ours = np.diff(ours)
    least = int(np.minimum(ours, np.diff(edge) - ours).sum())
    return least / (len(both) - least)


# --- Spark ---------------------------------------------------------------------------


def bands() -> Column:
    """A hash for each band: four places of the signature, and the band's number."""
    width = 4 * ROWS
    return F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), lambda j: F.xxhash64(F.substr("signature", j * width + 1, F.lit(width)), j))


def signature_table(docs: DataFrame, k: int = SHINGLE) -> DataFrame:
    """``doc_id, n_shingles, d1, d2`` (digest of the multiset), ``signature`` (32 bits
    of each place)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text", 1 << 20):
                n = part.num_rows
                text, shingle, weight = shingle_multisets(*utf8(part.column(1)), k)
                sig = signatures(text, shingle, weight, n)
                total = np.bincount(text, weights=weight, minlength=n).astype(np.int64)
                item = mix(shingle ^ mix(weight.astype(np.uint64)))
                other = mix(item + np.uint64(0x2545F4914F6CDD1D))
                d1, d2 = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
                np.add.at(d1, text, item)
                np.add.at(d2, text, other)
                short = (mix(sig) >> np.uint64(32)).astype(np.uint32)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), pa.array(total), pa.array(d1.view(np.int64)), pa.array(d2.view(np.int64)),
                     pa.array([s.tobytes() for s in short], pa.binary())],
                    names=["doc_id", "n_shingles", "d1", "d2", "signature"],
                )

    return id_and_text(docs).filter(F.col("doc_id").isNotNull()).mapInArrow(run, "doc_id long, n_shingles long, d1 long, d2 long, signature binary")


def _multisets(docs: DataFrame, k: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text", 1 << 20):
                text, shingle, weight = shingle_multisets(*utf8(part.column(1)), k)
                text, shingle = np.repeat(text, weight), np.repeat(shingle, weight)
                edge = np.searchsorted(text, np.arange(part.num_rows + 1)).tolist()
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([shingle[a:b].tobytes() for a, b in zip(edge, edge[1:], strict=False)], pa.binary())], names=["id", "multiset"])

    return docs.mapInArrow(run, "id long, multiset binary")


def _verified(pairs: DataFrame, sets: DataFrame, similarity: float) -> DataFrame:
    """The pairs ``a, b`` whose exact likeness reaches the threshold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = [weighted_jaccard(np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)) >= similarity for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True)]
            mask = pa.array(ok, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(mask), batch.column(1).filter(mask)], names=["a", "b"])

    left = sets.select(F.col("id").alias("_a"), F.col("multiset").alias("x"))
    right = sets.select(F.col("id").alias("_b"), F.col("multiset").alias("y"))
    both = pairs.join(right, pairs.b == right._b).join(left, pairs.a == left._a).select("a", "b", "x", "y")
    return both.mapInArrow(run, "a long, b long")


def components(links: DataFrame) -> DataFrame:
    """``id, label`` for every end of a link: the smallest id of its component.

    Every id points to the smallest one it knows of; a round takes the least label
    of its neighbours, then the label's own label, so chains halve."""
    both = links.select(F.col("a").alias("id"), F.col("b").alias("near")).union(links.select(F.col("b").alias("id"), F.col("a").alias("near"))).distinct().checkpoint()
    labels = both.groupBy("id").agg(F.least(F.col("id"), F.min("near")).alias("label")).checkpoint()
    while True:
        near = labels.select(F.col("id").alias("near"), F.col("label").alias("near_label"))
        least = both.join(near, "near").groupBy("id").agg(F.min("near_label").alias("least"))
        joined = labels.join(least, "id").select("id", "label", F.least("label", "least").alias("next"))
        jump = labels.select(F.col("id").alias("next"), F.col("label").alias("jumped"))
        step = joined.join(jump, "next", "left").select("id", "label", F.least("next", F.coalesce("jumped", "next")).alias("next")).checkpoint()
        changed = step.filter("next < label").limit(1).count()
        labels = step.select("id", F.col("next").alias("label"))
        if not changed:
            return labels


def _dealt(rows: DataFrame, weight: Column, most_rows: int, most_weight: int) -> DataFrame:
    """``rows`` of buckets (``key``, ``rep``, ...) once for each pair of blocks that
    their block is in: ``x <= y`` name the pair, ``mine`` the row's own block.  A
    bucket has as many blocks as its rows or their weight ask for."""
    sizes = rows.groupBy("key").agg(F.count(F.lit(1)).alias("_n"), F.sum(weight).alias("_w"))
    blocks = F.greatest(F.ceil(F.col("_n") / most_rows), F.ceil(F.col("_w") / most_weight), F.lit(1))
    many = sizes.select(F.col("key").alias("_key"), blocks.cast("int").alias("_blocks")).filter("_blocks > 1")
    both = rows.join(many, rows.key == F.col("_key"), "left").drop("_key").withColumn("_blocks", F.coalesce("_blocks", F.lit(1)))
    own = both.withColumn("mine", F.pmod(F.xxhash64("rep", F.lit(7)), F.col("_blocks")).cast("int"))
    each = own.withColumn("_other", F.explode(F.sequence(F.lit(0), F.col("_blocks") - 1)))
    return each.withColumn("x", F.least("mine", "_other")).withColumn("y", F.greatest("mine", "_other")).drop("_other", "_blocks")


def _task(dealt: DataFrame, weight: Column, most_rows: int, most_weight: int) -> Column:
    """Which of as many tasks as rows or weight ask for has a pair of blocks."""
    total = dealt.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(weight), F.lit(0)).alias("w")).first()
    groups = max(1, -(-total.n // most_rows), -(-int(total.w) // most_weight))
    return F.pmod(F.xxhash64("key", "x", "y"), F.lit(groups)).alias("group")


def _pairs(table: pa.Table) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """``bucket, rows of one block, rows of the other`` for each pair of blocks of a
    group, by id; the same rows twice where a block meets itself."""
    key, x, y, mine, ids = (table.column(c).to_numpy() for c in ("key", "x", "y", "mine", "rep"))
    order = np.lexsort((ids, mine, y, x, key))
    same = (key[order][1:] == key[order][:-1]) & (x[order][1:] == x[order][:-1]) & (y[order][1:] == y[order][:-1])
    edge = np.flatnonzero(np.concatenate([[True], ~same, [True]]))
    for a, b in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        rows = order[a:b]
        if x[rows[0]] == y[rows[0]]:
            yield int(key[rows[0]]), rows, rows
        else:
            first = mine[rows] == x[rows[0]]
            yield int(key[rows[0]]), rows[first], rows[~first]


def _apart(labels: np.ndarray, n: np.ndarray, x: np.ndarray, y: np.ndarray, similarity: float) -> np.ndarray:
    """Which pairs of two sets of rows are of unlike components and like sizes."""
    ok = labels[x][:, None] != labels[y][None, :]
    return ok & (n[x][:, None] >= similarity * n[y][None, :]) & (n[y][None, :] >= similarity * n[x][:, None])


def _suspects(similarity: float):
    """``key, rep, label, n`` of members that, by signature, may reach the threshold
    with a member of another component: one row a member, however many partners."""

    def run(table: pa.Table) -> pa.Table:
        ids, labels, n = (table.column(c).to_numpy() for c in ("rep", "label", "n"))
        sig = np.frombuffer(b"".join(table.column("signature").to_pylist()), np.uint32).reshape(len(ids), -1)
        least = (_MIGHT + similarity - SIMILARITY) * sig.shape[1]
        keys, found = [], []
        hit = np.zeros(len(ids), bool)
        for key, left, right in _pairs(table):
            for i in range(0, len(left), _BLOCK):
                for j in range(i if left is right else 0, len(right), _BLOCK):
                    x, y = left[i : i + _BLOCK], right[j : j + _BLOCK]
                    u, v = np.nonzero(_apart(labels, n, x, y, similarity))
                    for p in range(0, len(u), 1 << 14):
                        q = slice(p, p + (1 << 14))
                        like = (sig[x[u[q]]] == sig[y[v[q]]]).sum(axis=1) >= least
                        hit[x[u[q][like]]] = True
                        hit[y[v[q][like]]] = True
            rows = left if left is right else np.concatenate([left, right])
            rows = rows[hit[rows]]
            keys.append(np.full(len(rows), key, np.int64))
            found.append(rows)
        pick = np.concatenate([*found, np.empty(0, np.int64)]).astype(np.int64)
        return pa.table({"key": np.concatenate([*keys, np.empty(0, np.int64)]), "rep": ids[pick], "label": labels[pick], "n": n[pick]})

    return run


def overlaps(sets: list[np.ndarray], x: slice, y: slice) -> np.ndarray:
    """Exact overlaps of all multisets of two blocks (ordered hashes that stand as
    often as they weigh): a product of matrices whose columns are the occurrences
    that more than one set has."""
    part = [*sets[x], *sets[y]]
    owner = np.repeat(np.arange(len(part)), [len(t) for t in part])
    item = np.concatenate(part)
    again = np.concatenate([[False], (item[1:] == item[:-1]) & (owner[1:] == owner[:-1])])
    at = np.arange(len(item))
    rank = at - np.maximum.accumulate(np.where(again, 0, at))  # the how-manieth of its hash in its set
    item = mix(item ^ mix(rank.astype(np.uint64)))
    kinds, column, count = np.unique(item, return_inverse=True, return_counts=True)
    place = np.cumsum(count > 1) - 1
    keep = count[column] > 1
    owner, column = owner[keep], place[column[keep]]
    n_x = len(sets[x])
    out = np.zeros((n_x, len(part) - n_x), np.float32)
    for c in range(0, int(place[-1]) + 1 if len(place) else 0, 4096):
        here = (column >= c) & (column < c + 4096)
        m = np.zeros((len(part), 4096), np.float32)
        m[owner[here], column[here] - c] = 1
        out += m[:n_x] @ m[n_x:].T
    return np.rint(out)


def _parts(rows: np.ndarray, n: np.ndarray) -> list[np.ndarray]:
    """The rows in runs of at most ``_OVERLAP_SETS``, whose multisets have some
    ``_OVERLAP_SHINGLES`` elements together."""
    heavy, many = np.cumsum(n[rows]) // _OVERLAP_SHINGLES, np.arange(len(rows)) // _OVERLAP_SETS
    return np.split(rows, np.flatnonzero((np.diff(heavy) > 0) | (np.diff(many) > 0)) + 1)


def _exact_links(similarity: float):
    """Links between unlike components of each bucket, verified on the multisets;
    of links that join the same components, one."""

    def run(table: pa.Table) -> pa.Table:
        ids, n = (table.column(c).to_numpy() for c in ("rep", "n"))
        blobs = table.column("multiset")
        a, b = [], []
        for _, left, right in _pairs(table):
            labels = table.column("label").to_numpy().copy()
            ends = _parts(left, n), _parts(right, n)
            for i, x in enumerate(ends[0]):
                for y in ends[1][i:] if left is right else ends[1]:
                    ok = _apart(labels, n, x, y, similarity)
                    x_some, y_some = x[ok.any(axis=1)], y[ok.any(axis=0)]
                    if not len(x_some):
                        continue
                    sets = [np.frombuffer(blobs[int(r)].as_py(), np.uint64) for r in (*x_some, *y_some)]
                    both = overlaps(sets, slice(0, len(x_some)), slice(len(x_some), None))
                    ok = _apart(labels, n, x_some, y_some, similarity)
                    ok &= both >= similarity * (n[x_some][:, None] + n[y_some][None, :] - both)
                    for u, v in zip(*np.nonzero(ok), strict=True):
                        lu, lv = labels[x_some[u]], labels[y_some[v]]
                        if lu != lv:
                            a.append(int(ids[x_some[u]]))
                            b.append(int(ids[y_some[v]]))
                            labels[labels == max(lu, lv)] = min(lu, lv)
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return run


def near_duplicate_classes(docs: DataFrame, similarity: float = SIMILARITY, k: int = SHINGLE) -> DataFrame:
    """``doc_id, class_id, n_shingles`` for every row of ``docs``."""
    shared_dir(docs.sparkSession)
    rows = id_and_text(docs)
    table = signature_table(docs, k).checkpoint()
    digest = F.struct("d1", "d2")
    unlike = table.groupBy("doc_id").agg(F.min(digest).alias("lo"), F.max(digest).alias("hi")).filter("lo <> hi").select("doc_id").checkpoint()
    if not unlike.isEmpty():
        clash = rows.join(unlike, "doc_id", "left_semi")
        once = rows.join(unlike, "doc_id", "left_anti").unionByName(clash.groupBy("doc_id").agg(F.max("text").alias("text")))
        classes = near_duplicate_classes(saved(once), similarity, k)
        again = clash.select("doc_id").join(classes.join(unlike, "doc_id", "left_semi"), "doc_id").select(*classes.columns)
        return classes.join(unlike, "doc_id", "left_anti").unionByName(again)
    some = table.filter("n_shingles > 0")
    # equal multisets: one representative each
    reps = some.groupBy("d1", "d2").agg(F.min("doc_id").alias("rep"), F.first(F.struct("signature", "n_shingles")).alias("s")).select("rep", "s.signature", F.col("s.n_shingles").alias("n")).checkpoint()
    bucket = reps.select("rep", "n", F.explode(bands()).alias("bucket"))
    shared = bucket.groupBy("bucket").agg(F.min(F.struct("rep", "n")).alias("center"), F.max("rep").alias("last")).filter("center.rep < last")
    rekeyed = shared.select(F.col("bucket").bitwiseXOR(F.lit(0x5DEECE66D)).alias("key"), F.col("center.rep").alias("center"), F.col("center.n").alias("center_n"))
    members = bucket.select("rep", "n", F.col("bucket").bitwiseXOR(F.lit(0x5DEECE66D)).alias("key")).join(rekeyed.hint("merge"), "key").select("key", "rep", "n", "center", "center_n").checkpoint()
    involved = members.select(F.col("rep").alias("_rep")).distinct()
    sets = _multisets(rows.join(involved, rows.doc_id == involved._rep, "left_semi").dropDuplicates(["doc_id"]), k).checkpoint()

    pairs = members.filter("rep <> center").filter(_near_sizes("n", "center_n", similarity)).select(F.col("center").alias("a"), F.col("rep").alias("b")).distinct()
    links = _verified(pairs, sets, similarity).checkpoint()
    open_rows = _open(members, _hubs(links)).checkpoint()
    dealt = _dealt(open_rows, F.lit(0), _BLOCK_ROWS, 1)
    signed = dealt.join(reps.select("rep", "signature"), "rep")
    suspects = signed.groupBy(_task(dealt, F.lit(0), _GROUP_ROWS, 1)).applyInArrow(_suspects(similarity), "key long, rep long, label long, n long").distinct().checkpoint()
    weight = 8 * F.col("n")
    dealt = _dealt(suspects, weight, _BLOCK_ROWS, _BLOCK_BYTES)
    rest = dealt.join(sets.withColumnRenamed("id", "rep"), "rep").select("key", "x", "y", "mine", "rep", "label", "n", "multiset")
    links = links.union(rest.groupBy(_task(dealt, weight, _GROUP_ROWS, _GROUP_BYTES)).applyInArrow(_exact_links(similarity), "a long, b long")).distinct().checkpoint()
    labels = components(links)

    # back to all rows: digests of representatives, in an exchange of their own
    named = reps.select(F.col("rep").alias("id")).join(labels, "id", "left").select(F.col("id").alias("rep"), F.coalesce("label", "id").alias("class_id"))
    digests = some.select(F.col("doc_id").alias("rep"), "d1", "d2").join(named, "rep").dropDuplicates(["d1", "d2"])
    salt = F.lit(0x9E3779B9)
    digests = digests.select(F.col("d1").bitwiseXOR(salt).alias("k1"), F.col("d2").bitwiseXOR(salt).alias("k2"), "class_id")
    keyed = some.select("doc_id", F.col("d1").bitwiseXOR(salt).alias("k1"), F.col("d2").bitwiseXOR(salt).alias("k2"), "n_shingles")
    known = keyed.join(digests.hint("merge"), ["k1", "k2"]).select("doc_id", "class_id", "n_shingles")
    alone = table.filter("n_shingles = 0").select("doc_id", F.col("doc_id").alias("class_id"), "n_shingles")
    nameless = rows.filter("doc_id IS NULL").select("doc_id", F.col("doc_id").alias("class_id"), F.lit(None).cast("long").alias("n_shingles"))
    return known.unionByName(alone).unionByName(nameless)


def _hubs(links: DataFrame) -> DataFrame:
    """``id, label``: the smallest neighbour, or its own smallest one.  Equal labels
    mean one component; unlike ones may, which costs the last step a comparison."""
    ends = links.select(F.col("a").alias("id"), F.col("b").alias("near")).union(links.select(F.col("b").alias("id"), F.col("a").alias("near")))
    one = ends.groupBy("id").agg(F.least(F.col("id"), F.min("near")).alias("label"))
    jump = one.select(F.col("id").alias("label"), F.col("label").alias("next"))
    return one.join(jump, "label", "left").select("id", F.coalesce("next", "label").alias("label"))


def _near_sizes(a: str, b: str, similarity: float) -> Column:
    """Multisets of other sizes cannot be that alike."""
    return (F.col(a) >= F.lit(similarity) * F.col(b)) & (F.col(b) >= F.lit(similarity) * F.col(a))


def _open(members: DataFrame, labels: DataFrame) -> DataFrame:
    """Members of buckets that hold more than one component."""
    rows = members.select("key", "rep", "n").join(labels.select(F.col("id").alias("rep"), "label"), "rep", "left").select("key", "rep", "n", F.coalesce("label", "rep").alias("label"))
    mixed = rows.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).filter("lo < hi").select(F.col("key").bitwiseXOR(F.lit(77)).alias("k1"))
    return rows.withColumn("k1", F.col("key").bitwiseXOR(F.lit(77))).join(mixed, "k1", "left_semi").drop("k1")


def keep_representatives(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """The rows of ``docs`` that name their class; of rows with one id, the one with
    the greatest text (then, the greatest other columns)."""
    key, place = fresh(docs, "_kept"), fresh(docs, "_place")
    classes = near_duplicate_classes(docs, similarity).filter("class_id = doc_id").select(F.col("doc_id").alias(key)).distinct()
    named = docs.join(classes, F.col("doc_id") == F.col(key), "left_semi")
    order = [F.col(f"`{f.name}`").desc() for f in docs.schema.fields if f.name not in ("doc_id", "text") and not isinstance(f.dataType, MapType)]
    one = Window.partitionBy("doc_id").orderBy(text_or_empty().desc(), *order)
    named = named.withColumn(place, F.row_number().over(one)).filter(F.col(place) == 1).drop(place)
    return named.unionByName(docs.filter(F.col("doc_id").isNull()))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op5``: the near-duplicate class of every document."""
    return near_duplicate_classes(spark.read.parquet(f"{sf_dir}/documents.parquet"))
