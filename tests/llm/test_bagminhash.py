from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from peertrust.llm import bagminhash as bag


def multiset(text):
    words = text.lower().split()
    if not words:
        return Counter()
    return Counter(tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4)))


def jaccard(a, b):
    low, high = sum((a & b).values()), sum((a | b).values())
    return low / high if high else 0


def classes(docs, similarity=0.8):
    """All pairs that share a shingle."""
    sets = {i: multiset(t or "") for i, t in docs}
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    where = {}
    for i, s in sets.items():
        for g in s:
            where.setdefault(g, []).append(i)
    for i, s in sets.items():
        for j in {j for g in s for j in where[g] if j < i}:
            if find(i) != find(j) and jaccard(s, sets[j]) >= similarity:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return {i: find(i) for i in sets}


def test_signatures_estimate_weighted_jaccard():
    rng = np.random.default_rng(1)
    for _ in range(4):
        n = 60
        shingle = rng.integers(0, 1 << 63, n).astype(np.uint64)
        wa, wb = rng.integers(0, 40, n), rng.integers(0, 40, n)
        wb = np.where(rng.random(n) < 0.5, wa, wb)
        exact = np.minimum(wa, wb).sum() / np.maximum(wa, wb).sum()
        text = np.concatenate([np.zeros((wa > 0).sum(), int), np.ones((wb > 0).sum(), int)])
        sig = bag.signatures(text, np.concatenate([shingle[wa > 0], shingle[wb > 0]]), np.concatenate([wa[wa > 0], wb[wb > 0]]), 2, places=4096)
        assert abs((sig[0] == sig[1]).mean() - exact) < 0.035
    assert (bag.signatures(np.empty(0, int), np.empty(0, np.uint64), np.empty(0, int), 1) == np.uint64(0xFFFFFFFFFFFFFFFF)).all()


def test_tables_match_brute_force(spark):
    for sf in ("/root/testdata/sf0.001", "/root/testdata/sf0.01"):
        docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
        got = {r.doc_id: r.class_id for r in bag.query(spark, sf).collect()}
        assert got == classes(docs)


def test_chains_edges_and_repeats(spark):
    rng = np.random.default_rng(3)
    words = [f"w{i}" for i in rng.integers(0, 5000, 120)]
    docs = [(i, " ".join([*(f"x{i}_{j}" if j < i else w for j, w in enumerate(words))])) for i in range(0, 60, 4)]
    docs += [(100, docs[3][1]), (101, None), (102, ""), (103, "one two"), (104, "ONE  two"), (105, "a a a a a a a a a a"), (106, "a a a a a a a a a a a")]
    df = spark.createDataFrame([(i, t, "x") for i, t in docs], "doc_id long, text string, class_id string")
    rows = bag.near_duplicate_classes(df.union(df.filter("doc_id = 103")).union(spark.createDataFrame([(None, "one two", "x")], df.schema))).collect()
    want = classes(docs)
    assert {r.doc_id: r.class_id for r in rows if r.doc_id is not None} == want
    assert len(rows) == len(docs) + 2
    kept = {r.doc_id for r in bag.keep_representatives(df).collect()}
    assert kept == {i for i, c in want.items() if i == c}
    assert bag.near_duplicate_classes(df.limit(0)).count() == 0


def test_overlaps_of_blocks():
    rng = np.random.default_rng(5)
    sets = [np.sort(rng.integers(0, 30, rng.integers(1, 40)).astype(np.uint64)) for _ in range(9)]
    got = bag.overlaps(sets, slice(0, 4), slice(2, 9))
    for i, a in enumerate(sets[0:4]):
        for j, b in enumerate(sets[2:9]):
            assert got[i, j] == sum((Counter(a.tolist()) & Counter(b.tolist())).values())
            union = len(a) + len(b) - got[i, j]
            assert abs(bag.weighted_jaccard(a, b) - got[i, j] / union) < 1e-12


def test_large_group_of_near_copies(spark):
    rng = np.random.default_rng(8)
    base = [f"w{i}" for i in range(100)]
    docs = []
    for i in range(300):
        words = list(base)
        for j in rng.choice(100, rng.integers(1, 7), replace=False):
            words[j] = f"z{rng.integers(1 << 30)}"
        docs.append((i, " ".join(words)))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    assert {r.doc_id: r.class_id for r in bag.near_duplicate_classes(df).collect()} == classes(docs)


def test_rows_of_one_id_with_unlike_texts(spark):
    a, b = " ".join(f"a{i}" for i in range(40)), " ".join(f"b{i}" for i in range(40))
    rows = [(1, a, "x"), (2, b, "x"), (3, a, "x"), (3, b, "y"), (3, b, "z"), (4, a + " more", "x"), (None, a, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    want = {1: 1, 2: 2, 3: 2, 4: 1}  # the greatest text of 3 is b
    for some in (df, df.repartition(5), df.orderBy(F.desc("lang"))):
        got = bag.near_duplicate_classes(some).collect()
        assert len(got) == len(rows) and {r.doc_id: r.class_id for r in got if r.doc_id} == want
    kept = bag.keep_representatives(df.union(df.filter("doc_id = 2"))).collect()
    assert sorted((r.doc_id or 0, r.text) for r in kept) == [(0, a), (1, a), (2, b)]


def test_a_bucket_of_unlike_documents_in_many_blocks(spark, monkeypatch):
    """Documents that share half of their words: equal bands, but no links."""
    for name, value in {"_BLOCK_ROWS": 40, "_BLOCK_BYTES": 20_000, "_GROUP_ROWS": 50, "_GROUP_BYTES": 40_000, "_OVERLAP_SHINGLES": 1_000, "_BLOCK": 16}.items():
        monkeypatch.setattr(bag, name, value)
    base = [f"w{i}" for i in range(150)]
    rng = np.random.default_rng(4)
    docs = []
    for i in range(400):
        own = [f"x{i}_{j}" for j in range(60)]
        docs.append((i, " ".join([*base, *own])))
        if rng.random() < 0.15:
            docs.append((1000 + i, " ".join([*base, *own[:-3], "z", "y", "x"])))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    assert {r.doc_id: r.class_id for r in bag.near_duplicate_classes(df).collect()} == classes(docs)


def test_parts_are_bounded_by_sets_and_by_shingles():
    n = np.concatenate([np.full(3_000, 2), np.full(5, 200_000), [1 << 20], np.full(700, 1)])
    parts = bag._parts(np.arange(len(n)), n)
    assert np.concatenate(parts).tolist() == list(range(len(n)))
    assert max(map(len, parts)) <= bag._OVERLAP_SETS
    assert all(n[p].sum() - n[p].max() <= 2 * bag._OVERLAP_SHINGLES for p in parts)  # besides a single large one


def test_memory_of_many_short_sets():
    """Thousands of short, unlike members of one bucket: no matrix over all of them."""
    import tracemalloc

    import pyarrow as pa

    rng = np.random.default_rng(1)
    n, size = 6_000, 12
    sets = [np.sort(np.concatenate([np.arange(4), rng.integers(10, 1 << 60, size - 4)]).astype(np.uint64)) for _ in range(n)]
    zero = np.zeros(n, np.int64)
    table = pa.table({"key": zero, "x": zero.astype(np.int32), "y": zero.astype(np.int32), "mine": zero.astype(np.int32), "rep": np.arange(n), "label": np.arange(n), "n": np.full(n, size), "multiset": pa.array([s.tobytes() for s in sets], pa.binary())})
    tracemalloc.start()
    assert bag._exact_links(0.8)(table).num_rows == 0
    assert tracemalloc.get_traced_memory()[1] < 150 << 20
    tracemalloc.stop()
