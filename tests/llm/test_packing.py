import random
import zlib
from collections import Counter, defaultdict

import numpy as np
from tokenizers import Tokenizer

from peertrust.llm import lim_packing as lim
from peertrust.llm.bpe_transducer import default_tokenizer


def one_by_one(sizes, capacity):
    """The same rules, a piece at a time."""
    large = sorted((n for n in sizes if 3 * n > capacity), reverse=True)
    bins = []
    while large:
        n = large.pop(0)
        i = next((i for i, m in enumerate(large) if m <= capacity - n), None)
        bins.append([n] if i is None else [n, large.pop(i)])
    for n in sorted((n for n in sizes if 3 * n <= capacity), reverse=True):
        fit = [b for b in bins if sum(b) + n <= capacity]
        if fit:
            max(fit, key=sum).append(n)
        else:
            bins.append([n])
    return len(bins)


def test_plan_is_a_packing_and_matches_single_placement():
    rng = random.Random(1)
    for _ in range(200):
        cap = rng.choice([10, 30, 97, 200])
        sizes = [rng.randint(1, cap) for _ in range(rng.randint(0, 120))]
        plan = lim.plan_bins(dict(Counter(sizes)), cap)
        got = Counter()
        for lengths, n in plan:
            assert n > 0 and sum(lengths) <= cap and sum(3 * x > cap for x in lengths) <= 2
            for x in lengths:
                got[x] += n
        assert got == Counter(sizes)
        n_bins = sum(n for _, n in plan)
        assert n_bins == one_by_one(sizes, cap)
        assert lim.lower_bound(dict(Counter(sizes)), cap) <= n_bins


def test_pack_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = lim.pack_documents(docs).collect()
    lib = Tokenizer.from_file(default_tokenizer())
    ids = {r.doc_id: [*lib.encode(r.text, add_special_tokens=False).ids, 0] for r in docs.collect()}
    seqs, pieces = defaultdict(list), defaultdict(list)
    for r in rows:
        seqs[r.sequence_id].append((r.offset, r.length))
        pieces[r.doc_id].append((r.piece, r.start, r.length, r.ids_crc32))
    for s in seqs.values():
        at = 0
        for offset, length in sorted(s):
            assert offset == at
            at += length
        assert at <= 2048
    assert pieces.keys() == ids.keys()
    for doc_id, ps in pieces.items():
        at = 0
        for k, (piece, start, length, crc) in enumerate(sorted(ps)):
            assert (piece, start) == (k, at) and length == min(2048, len(ids[doc_id]) - at)
            assert crc == zlib.crc32(np.array(ids[doc_id][at : at + length], "<u4").tobytes())
            at += length
        assert at == len(ids[doc_id])
    counts = Counter(r.length for r in rows)
    assert len(seqs) <= 1.02 * lim.lower_bound(counts) + 1


def test_edge_cases(spark):
    docs = spark.createDataFrame([(1, None, 5), (2, "", 5), (2, "", 5), (None, "word", 5), (4, "x " * 5000, 5)], "doc_id long, text string, offset int")
    rows = lim.pack_documents(docs).collect()
    assert len(rows) == 4 + 3 and sum(r.length for r in rows) == 3 + 2 + 5001
    assert len({(r.sequence_id, r.offset) for r in rows}) == len(rows)
    assert lim.pack_documents(docs.limit(0)).count() == 0
