"""A small case of each finding of the third round."""

import pytest
from pyspark.sql import functions as F

from peertrust import incremental, packed, power, walks
from peertrust.queries import workloads
from peertrust.sources.tables import cut, interactions, peer_edges
from peertrust.streaming import trust


def stores(spark, sf, limit, monkeypatch, broadcast=walks.BROADCAST_EDGES):
    monkeypatch.setattr(trust.TrustStore, "LOCAL_PAIRS", limit)
    monkeypatch.setattr(walks, "BROADCAST_EDGES", broadcast)
    out = [trust.TrustStore(spark, 0, 40, policy=p, refresh=incremental.RefreshPolicy(k, 9.0)) for p, k in (("coupling", None), ("source_visit", 3), ("coupling", 2))]
    parts = cut(trust.batches(interactions(spark, sf), "volume", 350))
    for k in range(3):
        trust.TrustStore.update_together(out, parts.filter(F.col("batch") == k))
    return out


def rows(store):
    return sorted(tuple(r) for r in store.walks.collect()), sorted(tuple(r) for r in store.edges.collect())


def test_one_task_moves_all_stores_of_a_stream(spark, sf, monkeypatch):
    own, calls = stores(spark, sf, 10**6, monkeypatch), []
    monkeypatch.setattr(packed, "BLOCK", 100)  # many blocks
    monkeypatch.setattr(packed, "gathered", lambda *a, f=packed.gathered: calls.append(1) or f(*a))
    monkeypatch.setattr(trust, "apply_changes", lambda *a, **b: pytest.fail("joins for each store"))
    together = stores(spark, sf, 0, monkeypatch)
    assert len(calls) == 3 and not any(s.local for s in together)
    for a, b in zip(own, together, strict=True):
        assert rows(a) == rows(b) and (a.hops, a.rebuilds) == (b.hops, b.rebuilds)
        assert b.errors == pytest.approx(a.errors) and b.measured_error()["linf"] == pytest.approx(a.measured_error()["linf"])


def test_larger_stores_hop_in_blocks(spark, sf, monkeypatch):
    own = stores(spark, sf, 10**6, monkeypatch)
    monkeypatch.setattr(packed, "BLOCK", 100)
    monkeypatch.setattr(packed, "ARCS", 100)
    monkeypatch.setattr(walks, "binned_cdf", lambda *a: pytest.fail("intervals of the whole graph"))
    large = stores(spark, sf, 0, monkeypatch, broadcast=-1)
    for a, b in zip(own, large, strict=True):
        assert rows(a) == rows(b) and (a.hops, a.rebuilds) == (b.hops, b.rebuilds)
        assert b.errors == pytest.approx(a.errors)


def test_power_in_blocks(spark, sf, monkeypatch):
    e, key = cut(peer_edges(spark, sf)), lambda df: {(r.seed, r.alpha, r.node): r.score for r in df.collect()}
    monkeypatch.setattr(walks, "BROADCAST_EDGES", -1)
    for options in ({}, {"dangling": "drop"}, {"dangling": "uniform", "init": "uniform"}, {"weighting": "degree"}):
        e._peertrust_rows = None
        want, trace = power.distributed_power(e, [(0, 0.3), (None, 0.2)], **{"dangling": "seed", "rounds": 8, **options})
        e._peertrust_rows = e.count()
        got, same = power.distributed_power(e, [(0, 0.3), (None, 0.2)], **{"dangling": "seed", "rounds": 8, **options})
        assert key(got) == pytest.approx(key(want)) and all(same[i] == pytest.approx(trace[i]) for i in (0, 1))


def test_pairs_held_out_need_no_sorting(spark):
    keys = spark.range(3_000).select(F.concat(F.lit("k"), F.pmod("id", F.lit(900))).alias("k"))
    want = [r.k for r in keys.distinct().orderBy(F.md5("k")).limit(20).collect()]
    assert workloads._first_hashed(keys, 3_000, 20) == want and len(workloads._first_hashed(keys.limit(5), 3_000, 20)) == 5
