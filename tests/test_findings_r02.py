"""A small case of each finding of the second round."""

import datetime
import tracemalloc

import duckdb
import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from peertrust import metrics, power, registry, transition, walks
from peertrust.functions import extended as fx
from peertrust.sources.tables import cut, interactions, load, peer_edges
from peertrust.streaming import trust

RING = 120


@pytest.fixture(scope="module")
def ring(tmp_path_factory):
    """Each user gives to the next one, so trust comes one peer farther a round, and not
    to all peers in forty."""
    path, day = tmp_path_factory.mktemp("ring"), datetime.datetime(2024, 1, 1)
    i = np.arange(RING)
    rows = {"event_id": i, "ts": pa.array([day + datetime.timedelta(minutes=int(k)) for k in i], pa.timestamp("us")), "user_id": i, "event_type": ["view"] * RING, "value": np.full(RING, 100.0), "props": ['{"k": 0}'] * RING}
    pq.write_table(pa.table(rows), path / "events.parquet")
    return str(path)


def like_sql(spark, d, name):
    """The query's rows are those of its SQL on ``events`` alone."""
    con = duckdb.connect()
    con.execute(f"SET TimeZone = 'UTC'; CREATE VIEW events AS SELECT * FROM '{d}/events.parquet'")
    found = con.execute(registry.ORACLE_SQL[name])
    names = [c[0] for c in found.description]
    want = sorted(map(repr, found.fetchall()))
    assert sorted(repr(tuple(r)) for r in registry.QUERIES[name](spark, d).select(*names).collect()) == want
    assert len(want) < RING * (3 if name == "power_many_seeds" else 1)


def test_power_personal(spark, ring):
    like_sql(spark, ring, "power_personal")


def test_power_outdegree(spark, ring):
    like_sql(spark, ring, "power_outdegree")


def test_power_distributed(spark, ring):
    like_sql(spark, ring, "power_distributed")


def test_power_neumann(spark, ring):
    like_sql(spark, ring, "power_neumann")


def test_power_many_seeds(spark, ring):
    like_sql(spark, ring, "power_many_seeds")


def test_locality_mass_by_hop(spark, ring):
    like_sql(spark, ring, "locality_mass_by_hop")


def test_metric_score_spread(spark, ring):
    like_sql(spark, ring, "metric_score_spread")


def test_w15_relay_effect(spark, ring):
    like_sql(spark, ring, "w15_relay_effect")


def test_table_function_on_a_larger_graph(spark):
    e = spark.range(200_001).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).cast("long").alias("w"))
    fx.register_walk(spark, e, "peertrust_long")
    rows = spark.sql("SELECT r.id, w.step, w.node FROM range(5) r, LATERAL peertrust_long(CAST(7 AS BIGINT), r.id, CAST(0.3 AS DOUBLE)) w").collect()
    assert {r.node - r.step for r in rows} == {7} and len(rows) >= 5


def test_edges_are_collected_without_objects(spark):
    e = cut(spark.range(200_000).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), F.lit(1).cast("long").alias("w")))
    tracemalloc.start()
    found, _ = walks.local_edges(e)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert found["src"].dtype == np.int32 and peak < 60 * 200_000  # bytes


@pytest.mark.parametrize("name", ["update_source_visit_joins", "update_coupling_joins"])
def test_joins_beyond_a_broadcast(spark, sf, monkeypatch, name):
    want = sorted(tuple(r) for r in registry.QUERIES[name](spark, sf).collect())
    monkeypatch.setattr(walks, "BROADCAST_EDGES", -1)
    assert sorted(tuple(r) for r in registry.QUERIES[name](spark, sf).collect()) == want


@pytest.mark.parametrize("name, table", [("baseline_random_auroc", "customer"), ("sybil_attack_edges", "orders"), ("walks_needed", "lineitem")])
def test_reads_a_table(spark, sf, name, table):
    assert any(f"/{table}.parquet" in f for f in registry.QUERIES[name](spark, sf).inputFiles())


@pytest.mark.parametrize("seed", [None, 0])
def test_dense_matrix_of_many_nodes(spark, seed):
    n = 2_001
    e = spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst"), F.lit(1).cast("long").alias("w"))
    one = transition.dense_transition(e, 0.3, seed).agg(F.count(F.lit(1)).alias("n"), F.sum("p").alias("p"), F.max("p").alias("top")).first()
    assert one.n == n * n and one.p == pytest.approx(n) and one.top == pytest.approx(0.7 + 0.3 / n if seed is None else 1.0)


def test_large_graphs_are_not_iterated_on_the_driver(spark, sf, monkeypatch):
    from peertrust import power

    e = cut(peer_edges(spark, sf))
    near = {r.node: r.score for r in power.neumann_scores(e, 0, 0.3, 12).collect()}
    monkeypatch.setattr(power, "LOCAL_EDGES", 0)
    monkeypatch.setattr(power, "_neumann_distributed", lambda *a, f=power._neumann_distributed: calls.append(1) or f(*a))
    calls = []
    assert {r.node: r.score for r in power.neumann_scores(e, 0, 0.3, 12).collect()} == pytest.approx(near) and calls


@pytest.fixture
def tables_store(spark, sf, monkeypatch):
    monkeypatch.setattr(trust.TrustStore, "LOCAL_PAIRS", 0)
    store = trust.TrustStore(spark, 0, 40, policy="source_visit")
    parts = cut(trust.batches(interactions(spark, sf), "volume", 500))
    for k in (0, 1):
        store.update(parts.filter(F.col("batch") == k))
    return store


def test_a_store_of_tables_measures_itself(tables_store):
    error = tables_store.measured_error()
    assert 0 < error["linf"] <= error["l2"] < 1 and tables_store.hops > 0


def test_nets_of_pairs_without_python(spark, tmp_path):
    for k, up in enumerate((5, -9, 3)):
        spark.createDataFrame([(1, 2, up, 0), (3, 4, 1, 0)][: 2 - k % 2], "p long, q long, up long, down long").coalesce(1).write.parquet(f"{tmp_path}/{k}")
    rows = spark.readStream.schema("p long, q long, up long, down long").option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/*")
    got = sorted((r.a, r.b, r.net, r.flipped) for r in trust.pair_nets_by_batch(rows).collect())
    assert got == [(1, 2, -4, True), (1, 2, -1, False), (1, 2, 5, False), (3, 4, 1, False), (3, 4, 2, False)]


def test_a_graph_without_attacks_is_taken_as_it_is(monkeypatch):
    import pandas as pd

    from peertrust import sybil

    base = pd.DataFrame({"src": [0, 1], "dst": [1, 0], "w": [2, 3]})
    monkeypatch.setattr(pd.DataFrame, "groupby", lambda *a, **b: pytest.fail("grouped"))
    assert sybil._attacked(base, pd.DataFrame({"i": [1], "src": [0], "dst": [9], "w": [1]}), 0).total.tolist() == [2, 3]


def test_walks_of_a_store_of_tables(tables_store, spark, sf, monkeypatch):
    monkeypatch.setattr(trust.TrustStore, "LOCAL_PAIRS", 10**6)
    own = trust.TrustStore(spark, 0, 40, policy="source_visit")
    parts = cut(trust.batches(interactions(spark, sf), "volume", 500))
    for k in (0, 1):
        own.update(parts.filter(F.col("batch") == k))
    rows = lambda s: sorted(tuple(r) for r in s.walks.collect())
    assert own.local and not tables_store.local and rows(own) == rows(tables_store)


def test_stores_of_one_stream_share_tables(spark, sf, monkeypatch):
    monkeypatch.setattr(trust.TrustStore, "LOCAL_PAIRS", 0)
    a, b = (trust.TrustStore(spark, 0, 20, refresh=trust.RefreshPolicy(max_error=9.0)) for _ in range(2))
    x = cut(interactions(spark, sf))
    a.update(x)
    b.update(x, a)
    assert b.edges is a.edges and b._exact is a._exact and b.errors == a.errors


def test_larger_graphs_do_not_pass_the_driver(spark, sf, monkeypatch):
    name = "update_source_visit_joins"
    want = sorted(tuple(r) for r in registry.QUERIES[name](spark, sf).collect())
    monkeypatch.setattr(walks, "LOCAL_EDGES", 0)
    monkeypatch.setattr(walks, "shared_edges", lambda *a: pytest.fail("edges on the driver"))
    assert sorted(tuple(r) for r in registry.QUERIES[name](spark, sf).collect()) == want and want


@pytest.mark.parametrize("limit", [10**6, 0])
def test_runs_share_the_adjacency(spark, sf, monkeypatch, limit):
    e = cut(peer_edges(spark, sf))
    exact = power.power_iteration(e, 0, 0.3)
    one = {i: walks.simulate_walks(e, 0, 40, 0.3, 7 + i) for i in range(3)}
    want = sorted((i, *r) for i, w in one.items() for r in w.collect())
    errors = {(i, r.n_walks): r.l2 for i, w in one.items() for r in metrics.error_by_walks(w, exact, [10, 40]).collect()}
    monkeypatch.setattr(walks, "LOCAL_EDGES", limit)
    monkeypatch.setattr(walks, "simulate_walks", lambda *a, **b: pytest.fail("a run of its own"))
    runs = walks.simulate_runs(e, 0, [7, 8, 9], 40, 0.3)
    assert sorted(tuple(r) for r in runs.collect()) == want
    assert {(r.run, r.n_walks): r.l2 for r in metrics.run_errors(runs, exact, [10, 40]).collect()} == pytest.approx(errors)
    assert -0.7 < registry.QUERIES["metric_error_slope"](spark, sf).first().slope < -0.3


def test_scores_of_a_gathered_graph(spark, sf, monkeypatch):
    e, key = cut(peer_edges(spark, sf)), lambda df: {(r.seed, r.node): r.score for r in df.collect()}
    want = key(power.power_iteration_many(e, [0, None], [0.3], rounds=8))
    monkeypatch.setattr(power, "LOCAL_EDGES", 0)
    monkeypatch.setattr(power, "local_edges", lambda e, limit, f=walks.local_edges: f(e, limit) if limit == 0 else pytest.fail("edges on the driver"))
    assert key(power.power_iteration_many(e, [0, None], [0.3], rounds=8)) == pytest.approx(want)


def test_sizes_do_not_grow_in_a_loop(spark):
    x = cut(spark.range(5))
    for _ in range(9):
        x = cut(x.join(x.withColumnRenamed("id", "other"), F.col("id") == F.col("other")).select("id"))
    assert x._jdf.queryExecution().optimizedPlan().stats().sizeInBytes() <= 1 << 256 and sorted(r.id for r in x.collect()) == list(range(5))
