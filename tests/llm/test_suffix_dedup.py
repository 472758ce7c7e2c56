import hashlib
import random

import numpy as np
import pytest

from peertrust.llm import suffix_dedup as sd
from peertrust.llm.bytehash import HashedBytes, merge_sorted_suffixes


def brute(docs, length):
    """Byte by byte, with every string of the smaller documents in a set."""
    seen, out = {}, {}
    for doc_id, text in docs:
        data = (text or "").encode()
        for i in range(len(data) - length + 1):
            s = data[i : i + length]
            seen[s] = min(seen.get(s, doc_id), doc_id)
    for doc_id, text in docs:
        data = (text or "").encode()
        gone = np.zeros(len(data), bool)
        for i in range(len(data) - length + 1):
            if seen[data[i : i + length]] < doc_id:
                gone[i : i + length] = True
        kept = bytes(b for b, g in zip(data, gone) if not g)
        spans = int(np.sum(np.diff(np.concatenate([[0], gone.astype(int)])) == 1))
        out[doc_id] = (len(data), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest())
    return out


def corpus(seed, n, alphabet="ab c", sizes=400):
    rng = random.Random(seed)
    docs = []
    for i in range(n):
        text = "".join(rng.choice(alphabet) for _ in range(rng.randrange(sizes)))
        for _ in range(rng.randrange(4)):
            if docs:
                other = rng.choice(docs)[1]
                a = rng.randrange(len(other) + 1)
                cut = rng.randrange(len(text) + 1)
                text = text[:cut] + other[a : a + rng.randrange(150)] + text[cut:]
        docs.append((i * 7 % 1009, text))
    return docs


@pytest.mark.parametrize("seed,alphabet", [(1, "abcdefgh é"), (2, "ab"), (3, "a")])
def test_matches_brute_force(spark, seed, alphabet):
    docs = corpus(seed, 60, alphabet)
    docs += [(2000, docs[0][1]), (2001, ""), (2002, None), (2003, "x" * 49), (2004, "x" * 50), (2005, "x" * 300)]
    want = brute(docs, 50)
    df = spark.createDataFrame([(i, t, "k") for i, t in docs], "doc_id long, text string, kind string").repartition(5)
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.remove_shared_substrings(df).collect()}
    assert got == want


def test_tables(spark, sf):
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.query(spark, sf).collect()}
    assert got == brute(docs, 50)


def test_null_ids_repeated_rows_and_empty_tables(spark):
    long = "abcdefghij" * 9
    df = spark.createDataFrame([(1, long), (1, long), (2, "x" + long), (None, long)], "doc_id long, text string")
    rows = sd.remove_shared_substrings(df).collect()
    assert sorted((r.doc_id or 0, r.n_removed, bytes(r.text_bytes)[:1]) for r in rows) == [(0, 0, b"a"), (1, 0, b"a"), (1, 0, b"a"), (2, 90, b"x")]
    assert sd.remove_shared_substrings(df.limit(0)).count() == 0


def test_suffix_mergesort():
    rng = np.random.default_rng(4)
    for limit in (1, 7, 30):
        buf = rng.integers(97, 99, 400).astype(np.uint8)
        buf[200:300] = buf[50:150]
        text, suffix = HashedBytes(buf), np.arange(len(buf) - limit + 1)
        order, shared = merge_sorted_suffixes(text, suffix, limit)
        keys = [buf[i : i + limit].tobytes() for i in suffix]
        assert order.tolist() == sorted(range(len(keys)), key=lambda i: (keys[i], i))
        for k in range(1, len(order)):
            a, b = keys[order[k - 1]], keys[order[k]]
            n = next((i for i in range(limit) if a[i] != b[i]), limit)
            assert shared[k] == n


def results(df, **more):
    return sorted((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in sd.remove_shared_substrings(df, **more).collect())


def test_hot_grams_and_pieces_of_long_texts(spark):
    rng = random.Random(9)
    core = "the gram that all of them have, "
    docs = [(i, "".join(rng.choice("abc ") for _ in range(80)) + rng.choice(["xy", "z", "qq"]) + core[rng.randrange(8) :] + "".join(rng.choice("ab") for _ in range(90))) for i in range(80)]
    docs += [(100 + i, "".join(docs[rng.randrange(80)][1][20:180] for _ in range(30))) for i in range(6)]
    want = sorted((i, *v) for i, v in brute(docs, 50).items())
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(4)
    assert results(df, hot=3, chunk=700, seed=5) == want == results(df, hot=1)


def test_rows_of_one_id_with_unlike_texts(spark):
    a, b, c = ("".join(random.Random(k).choice("abcdefgh ") for _ in range(200)) for k in range(3))
    rows = [(5, a), (5, b + "é"), (5, a), (7, b + c), (8, c + a), (3, c[50:])]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    seen = {}
    for i, t in rows:
        for k in range(len(t.encode()) - 49):
            s = t.encode()[k : k + 50]
            seen[s] = min(seen.get(s, i), i)
    want = []
    for i, t in rows:
        data, gone = t.encode(), np.zeros(len(t.encode()), bool)
        for k in range(len(data) - 49):
            if seen[data[k : k + 50]] < i:
                gone[k : k + 50] = True
        kept = bytes(x for x, g in zip(data, gone) if not g)
        want.append((i, len(data), int(gone.sum()), int((np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    for some in (df, df.repartition(6), df.coalesce(1)):
        assert results(some) == sorted(want)


def test_equal_hashes_of_unlike_strings_are_noticed(spark):
    """With a hash that says nothing, the comparison of bytes speaks up."""
    rng = random.Random(2)
    docs = [(i, "".join(rng.choice("abcdefgh") for _ in range(60)) + "one and the same passage of some forty" + "".join(rng.choice("abcdefgh") for _ in range(60))) for i in range(6)]
    df = spark.createDataFrame(docs, "doc_id long, text string").repartition(6)
    with pytest.raises(Exception, match="two unlike strings have one hash"):
        results(df, bits=0, chunk=10)


def test_rows_found_by_id_and_variant():
    rng = np.random.default_rng(3)
    for _ in range(50):
        n = int(rng.integers(1, 30))
        ids, variants = rng.integers(0, 4, n), rng.integers(0, 6, n)
        order = np.lexsort((variants, ids))
        ids, variants = ids[order], variants[order]
        want = [min(j for j in range(n) if (ids[j], variants[j]) == (ids[i], variants[i])) for i in range(n)]
        assert sd._row_of(ids, variants, ids, variants).tolist() == want


def test_parents_make_a_tree():
    root = np.array([0, 0, 0, 0, 0, 5, 5, 7, 7, 7])
    covered = np.array([1, 2, 3, 4, 6, 8, 9])
    assert sd._parents(covered, root).tolist() == [0, 0, 1, 1, 5, 7, 7]
