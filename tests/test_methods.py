"""Hand-worked graphs, laws and bounds."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from peertrust import estimate as est
from peertrust import graph, incremental, ledger, metrics, power, sybil, transition, walks
from peertrust.functions.rng import u32, u32_py
from peertrust.plans import planner
from peertrust.sources.tables import cut, peer_edges
from peertrust.streaming import trust

EDGE = "src long, dst long, w long"


def edges(spark, *rows):
    return spark.createDataFrame(list(rows), EDGE)


def scores(df):
    return {r.node: r.score for r in df.collect()}


def test_draws_agree(spark):
    got = spark.range(50).select(u32(42, "x", F.col("id"), F.lit(3)).alias("d")).collect()
    assert [r.d for r in got] == [u32_py(42, "x", i, 3) for i in range(50)]


@pytest.mark.parametrize("a", [0.1, 0.3, 0.5])
def test_two_nodes_and_chain(spark, a):
    for e in (edges(spark, (1, 2, 1), (2, 1, 1)), edges(spark, (1, 2, 5))):
        for distributed in (False, True):
            if distributed and a != 0.3:
                continue
            s = scores(power.power_iteration(e, 1, a, rounds=200 if not distributed else 60, distributed=distributed))
            assert s[1] == pytest.approx(1 / (2 - a), abs=1e-6) and s[2] == pytest.approx((1 - a) / (2 - a), abs=1e-6)


def test_star_and_weights(spark):
    a = 0.3
    s = scores(power.power_iteration(edges(spark, *((0, i, 7) for i in range(1, 6))), 0, a, rounds=200))
    assert s[0] == pytest.approx(1 / (2 - a)) and s[3] == pytest.approx((1 - a) / (5 * (2 - a)))
    s = scores(power.power_iteration(edges(spark, (0, 1, 3), (0, 2, 1)), 0, a, rounds=200))
    assert s[1] / s[2] == pytest.approx(3)


def test_isolated_seed(spark):
    e = edges(spark, (1, 2, 1))
    w = walks.simulate_walks(e, 9, 30)
    assert scores(est.estimate(w)) == {9: 1.0} and w.count() == 30
    assert scores(power.power_iteration(e, 9))[9] == 1.0
    with pytest.raises(ValueError):
        incremental.drop_seed_check(e, 9)


def test_even_pairs_and_flips(spark):
    t = "p long, q long, up long, down long, ts long, id long, kind string"
    even = spark.createDataFrame([(1, 2, 5, 0, 1, 1, "x"), (2, 1, 5, 0, 2, 2, "x")], t)
    assert graph.net_edges(even).count() == 0
    flip = spark.createDataFrame([(1, 2, 3, 0, 1, 1, "x"), (2, 1, 5, 0, 2, 2, "x")], t)
    assert [tuple(r) for r in graph.net_edges(flip).collect()] == [(1, 2, 2)]
    assert [r.flipped for r in graph.net_flip_history(flip).orderBy("id").collect()] == [False, True]
    diff = graph.diff_edges(graph.net_edges(flip.filter("id = 1")), graph.net_edges(flip)).collect()
    assert {(r.op, r.src, r.dst) for r in diff} == {("remove", 2, 1), ("add", 1, 2)}


def test_chain_audit_finds_what_was_tampered(spark):
    t = spark.createDataFrame([(1, 2, 5, 0, 1, 1, "x"), (1, 3, 5, 0, 2, 2, "x"), (1, 4, 5, 0, 3, 3, "x")], "p long, q long, up long, down long, ts long, id long, kind string")
    linked = ledger.link_blocks(ledger.agent_chains(t))
    assert ledger.audit_chain(linked).count() == 0 and ledger.find_double_spends(linked).count() == 0
    bad = ledger.audit_chain(linked.withColumn("hash", F.when((F.col("id") == 2) & (F.col("agent") == 1), F.lit("0")).otherwise(F.col("hash")))).collect()
    assert [(r.agent, r.seq, r.broken) for r in bad] == [(1, 3, True)]
    twice = linked.unionByName(linked.filter("agent = 1 AND seq = 2").withColumn("hash", F.lit("z")))
    assert [(r.agent, r.seq, r.n) for r in ledger.find_double_spends(twice).collect()] == [(1, 2, 2)]


def test_ranking_areas(spark):
    rows = spark.createDataFrame([(1, True, 0.4), (2, False, 0.3), (3, True, 0.2), (4, False, 0.1)], "node long, is_honest boolean, score double")
    assert metrics.auroc(rows).first()[0] == 0.75
    curve = metrics.roc(rows)
    assert [(r.fpr, r.tpr) for r in curve.orderBy("cut").collect()] == [(0, 0.5), (0.5, 0.5), (0.5, 1), (1, 1)]
    assert metrics.auroc_trapezoid(curve).first()[0] == 0.75
    assert metrics.auroc(rows.withColumn("score", F.lit(1.0))).first()[0] == 0.5
    assert metrics.auroc(rows.filter("is_honest")).first()[0] is None


def test_roc_identity(spark, sf):
    edges_, extra, labels, h = sybil.build(spark, sf, 5, sizes=(50, 200, 100))
    with pytest.raises(ValueError, match="smaller sizes"):
        sybil.build(spark, sf, 5)
    rows = metrics.labelled(est.estimate(walks.simulate_walks(edges_, 0, 50)), labels)
    n = labels.count()
    total = metrics.roc(rows).agg(F.sum("tpr").alias("t"), F.sum("fpr").alias("f")).first()
    assert h * total.t + (n - h) * total.f == pytest.approx(n * (n + 1) / 2)


def test_strategies_and_partitions_agree(spark, sf):
    e = spark.createDataFrame(peer_edges(spark, sf).collect(), EDGE)
    key = lambda df: sorted(tuple(r) for r in df.collect())
    want = key(walks.simulate_walks(e, 0, 30, 0.4))
    for strategy in ("frontier", "binned", "recursive"):
        assert key(walks.simulate_walks(e, 0, 30, 0.4, strategy=strategy)) == want
    assert key(walks.simulate_walks(e.repartition(7), 0, 30, 0.4)) == want


def test_walk_law_is_the_seed_rule(spark):
    rng = np.random.default_rng(2)
    rows = {(int(a), int(b)): int(w) for a, b, w in zip(rng.integers(0, 9, 25), rng.integers(0, 12, 25), rng.integers(1, 9, 25)) if a != b}
    e = edges(spark, *((a, b, w) for (a, b), w in rows.items()))
    seed = min(a for a, _ in rows)
    exact = power.power_iteration(e, seed, 0.3, rounds=300)
    assert metrics.linf(est.estimate(walks.simulate_walks(e, seed, 20_000)), exact) < 0.01
    neumann = scores(power.neumann_scores(e, seed, 0.3, 300))
    total = sum(neumann.values())
    assert all(v / total == pytest.approx(scores(exact)[k], abs=1e-9) for k, v in neumann.items())


@pytest.mark.parametrize("policy", ["source_visit", "coupling"])
def test_updates_have_the_law_of_the_new_graph(spark, policy):
    old = edges(spark, (0, 1, 2), (1, 2, 3), (2, 0, 1), (1, 3, 1), (4, 0, 2), (0, 4, 1))
    # 3 was dangling and now hops; 1 -> 2 goes; 2 is reweighted; 4 loses all
    new = edges(spark, (0, 1, 5), (2, 0, 1), (2, 1, 4), (1, 3, 1), (3, 4, 2), (3, 0, 1), (0, 4, 1))
    before = cut(walks.simulate_walks(old, 0, 20_000))
    after = incremental.apply_changes(before, old, new, 1, policy=policy)
    assert metrics.linf(est.estimate(after), power.power_iteration(new, 0, 0.3, rounds=300)) < 0.012
    have = {(r.src, r.dst) for r in new.collect()}
    paths = {}
    for r in after.filter("walk_id < 300").orderBy("walk_id", "step").collect():
        paths.setdefault(r.walk_id, []).append((r.step, r.node))
    for p in paths.values():
        assert [s for s, _ in p] == list(range(len(p)))
        assert all((a, b) in have for (_, a), (_, b) in zip(p, p[1:]))


def test_coupling_touches_fewer_walks(spark, sf):
    from peertrust.queries.updates import updated

    cost = {}
    for policy in ("source_visit", "coupling"):
        before, after, old, new = updated(spark, sf, policy)
        cost[policy] = incremental.update_cost(before, after, 1).first().redone
        moved = before.join(after, ["walk_id", "seed", "gen", "step", "node"], "left_anti").select("walk_id").distinct()
        assert moved.join(incremental.affected(before, incremental.changed_sources(old, new)), "walk_id", "left_anti").count() == 0
    assert cost["coupling"] < cost["source_visit"]


def test_bounds():
    assert incremental.bound_arrival(10, 500) == 50
    assert incremental.bound_total(3, 0.5, 60) == pytest.approx(60 / 0.5 * (1 + 1 / 2 + 1 / 3))
    assert incremental.bound_removal(0.5, 60) == 120 and incremental.bound_removal(0.5, 60, 6) == 20
    assert est.walks_for_error(0.01, 0.05, 0.3) == math.ceil(math.log(40) / 2e-4 * 0.3)


def test_alias_and_bins_keep_the_law(spark):
    e = edges(spark, *((0, i, i * i) for i in range(1, 70)))
    table = transition.binned_cdf(transition.cdf(e), 16)
    assert table.count() <= 3 * 69 and table.agg(F.max("bins")).first()[0] == 5
    a = transition.alias_table(e)
    law = a.select("dst", (F.col("keep") / F.col("n")).alias("p")).union(a.select("other", (1 - F.col("keep")) / F.col("n"))).groupBy("dst").agg(F.sum("p").alias("p"))
    total = sum(i * i for i in range(1, 70))
    assert all(r.p == pytest.approx(r.dst**2 / total, abs=1e-9) for r in law.collect())


def test_workload_shapes(spark):
    from peertrust.queries import workloads as w

    sf = "/root/testdata/sf0.01"
    assert all(r.ok for r in w.random_agreement(spark, sf).collect())
    assert all(abs(r.l2) < 0.2 for r in w.batch_replay(spark, sf, 3).select(F.col("incremental_error").alias("l2")).collect())
    assert all(r.ok for r in w.update_agreement(spark, sf).collect())
    assert -0.8 < w.error_slope(spark, sf).first().slope < -0.3
    r = w.ledger_initial(spark, sf).first()
    assert r.l2 <= 0.05 and r.linf <= 0.03
    assert all(r.l2 <= 0.06 for r in w.ledger_update(spark, sf).collect())
    rows = w.arrival_cost(spark, sf).collect()
    assert np.mean([r.expected_touched for r in rows]) <= 1.5 * np.mean([r.bound for r in rows])


def test_sybil_curves_fall_with_attack_edges(spark):
    got = {(r.attack, r.alpha): r for r in sybil.sybil_experiment(spark, "/root/testdata/sf0.01", [0, 500], [0.1, 0.3]).collect()}
    assert got[0, 0.1].auroc > got[500, 0.1].auroc + 0.1
    visited = {(r.attack, r.alpha): r for r in sybil.sybil_experiment(spark, "/root/testdata/sf0.01", [0], [0.1], drop_unvisited=True).collect()}
    assert visited[0, 0.1].auroc is None


def test_stream_replay_and_state(spark, sf):
    from peertrust.operators.extended import _flips
    from peertrust.queries.workloads import stream_replay

    key = lambda df: sorted(tuple(r) for r in df.select("src", "dst", "w").collect())
    daily, volume = stream_replay(spark, sf)[0], stream_replay(spark, sf, "volume", 4)[0]
    assert daily.batch > 20 and volume.batch == 4  # as many micro-batches as there are days, or parts
    assert key(daily.edges) == key(volume.edges) == key(peer_edges(spark, sf))
    last = _flips(spark, sf).collect()
    assert any(r.flipped for r in last)


def test_store_as_arrays_and_as_tables(spark, sf, monkeypatch):
    from peertrust.sources.tables import interactions

    x = cut(trust.batches(interactions(spark, sf), "volume", 400))
    for policy in ("source_visit", "coupling"):
        stores = []
        for pairs in (10**6, 0):
            monkeypatch.setattr(trust.TrustStore, "LOCAL_PAIRS", pairs)
            store = trust.TrustStore(spark, 0, 40, policy=policy, refresh=incremental.RefreshPolicy(max_error=10.0))
            for k in range(3):
                store.update(x.filter(F.col("batch") == k))
            assert store.local == bool(pairs) and len(store.errors) == 3
            stores.append(store)
        a, b = ([tuple(r) for r in s.walks.orderBy("walk_id", "step").collect()] for s in stores)
        assert a == b and stores[0].errors == pytest.approx(stores[1].errors, abs=1e-9)


def test_refresh_by_measured_error(spark, sf):
    from peertrust.sources.tables import interactions

    x = cut(trust.batches(interactions(spark, sf), "volume", 100))
    store = trust.TrustStore(spark, 0, 30, refresh=incremental.RefreshPolicy(max_error=0.0))
    for k in range(3):
        store.update(x.filter(F.col("batch") == k))
    assert store.rebuilds == 3 and all(e > 0 for e in store.errors)  # every error is too large
    with pytest.raises(ValueError, match="no longer"):
        trust.TrustStore(spark, -5, 3, seed_must_stay=True).update(x)


def test_one_machine_and_many_give_the_same(spark, sf, monkeypatch):
    """Forms for graphs that can be sent to every task, and for those that cannot."""
    from peertrust.queries.ranking import _linked_graph

    e = cut(spark.createDataFrame(_linked_graph(spark, sf).collect(), EDGE))  # all targets dangle
    plain = cut(spark.createDataFrame(peer_edges(spark, sf).collect(), EDGE))
    node_table = graph.nodes(e)
    begin = walks.starts_everywhere(node_table, 1)
    host = e.agg(F.min("src")).first()[0]

    def rows():
        out = [sorted(tuple(r) for r in walks.advance(e, begin, 0.5, jump=node_table).collect())]
        out.append(sorted(tuple(r) for r in walks.simulate_walks(plain, [0, 3], 10, 0.5).collect()))
        many = power.power_iteration_many(plain, [0, 3, None], [0.3, 0.5], rounds=10)
        scores_ = [{(r.seed, r.alpha, r.node): r.score for r in many.collect()}]
        for df in (power.power_iteration(plain, 0, 0.3, tol=0.03), power.neumann_scores(plain, 0, 0.3, 12), power.power_iteration(e, host, 0.3, "drop", 8), power.power_iteration(e, None, 0.3, rounds=8)):
            scores_.append({r.node: r.score for r in df.collect()})
        base, extra, labels, h = sybil.build(spark, sf, 6, sizes=(50, 200, 100))
        m = sybil.scenario_measures(base, extra, labels, [(0, 0.5), (6, 0.5)], h, 30)
        scores_.append({(r.attack, c): r[c] for r in m.collect() for c in ("auroc", "fp_mean", "fn_mean", "fp_at", "fn_at") if r[c] is not None})
        return out, scores_

    near, near_scores = rows()
    for module in (walks, sybil):
        monkeypatch.setattr(module, "BROADCAST_EDGES", -1)
    monkeypatch.setattr(power, "BROADCAST_SCORES", 0)
    for df in (e, plain):
        df._peertrust_local = None
    far, far_scores = rows()
    assert near == far and any(s > 0 for *_, s, _ in near[0])
    for a, b in zip(near_scores, far_scores, strict=True):
        assert a == pytest.approx(b, abs=1e-12)


def test_numbers_and_running_sums(spark):
    from peertrust.sources.tables import numbered, running_sums

    df = spark.range(1000).select((F.col("id") * 7919 % 1009).alias("k")).distinct()
    got = numbered(df.repartition(6), "k").orderBy("k").collect()
    assert [r.place for r in got] == list(range(1000))
    sums = running_sums(numbered(df, "k").withColumn("place", F.col("place") + 1), "place", ["k"], block=37).orderBy("place").collect()
    assert [r.k for r in sums] == np.cumsum(sorted(r.k for r in df.collect())).tolist()
    assert numbered(df.limit(0), "k").count() == 0


def test_long_walks_need_another_strategy(spark):
    with pytest.raises(ValueError, match="another strategy"):
        walks.simulate_walks(edges(spark, (1, 2, 1)), 1, 3, 0.1, strategy="recursive")
    assert walks.simulate_walks(edges(spark, (1, 2, 1)), 1, 3, 0.1, strategy="recursive", max_steps=20).count() >= 3


@pytest.mark.parametrize("strategy", ["local", "broadcast"])
def test_coins_and_crossings(spark, strategy):
    old = edges(spark, (0, 1, 2), (1, 2, 3), (2, 0, 1), (4, 0, 2), (0, 4, 1))
    more = edges(spark, (0, 1, 5), (1, 2, 3), (1, 3, 2), (2, 0, 1), (4, 0, 2), (0, 4, 1), (3, 0, 1), (3, 4, 1), (5, 0, 1))
    apply = lambda w, a, b, policy: incremental.apply_changes(w, a, b, 1, policy=policy, strategy=strategy)
    for a, b, policy in ((old, more, "coin"), (more, edges(spark, (0, 4, 1), (1, 2, 3), (4, 0, 2), (3, 0, 1)), None), (more, edges(spark, (0, 1, 5), (1, 3, 2), (2, 0, 1), (4, 0, 2), (3, 4, 1)), "crossing")):
        before = cut(walks.simulate_walks(a, 0, 20_000))
        if policy is None:  # weights of no other edge change, so this is a departure, too
            policy = "crossing"
        after = cut(apply(before, a, b, policy))
        assert metrics.linf(est.estimate(after), power.power_iteration(b, 0, 0.3, rounds=300)) < 0.012
        moved = {r.walk_id for r in after.filter("gen = 1").collect()}
        full = {r.walk_id for r in incremental.affected(before, incremental.changed_sources(a, b)).collect()}
        assert moved < full
        wrong = "crossing" if policy == "coin" else "coin"
        with pytest.raises(ValueError, match=f"{wrong} is for"):
            apply(before, a, b, wrong)


def test_nodes_that_come(spark):
    e = edges(spark, (1, 2, 3), (2, 1, 1))
    ops = spark.createDataFrame([("add_node", 9, None, None, None), ("add_node", 8, None, None, None), ("add", 1, 9, None, 4), ("drop_node", 2, None, None, None)], "op string, src long, dst long, w_old long, w_new long")
    rows = incremental.expand_changes(ops, e)
    assert sorted((r.op, r.src) for r in rows.collect()) == [("add", 1), ("add_node", 8), ("add_node", 9), ("remove", 1), ("remove", 2)]
    assert [tuple(r) for r in incremental.apply_to_edges(e, rows).collect()] == [(1, 9, 4)]
    assert sorted(r.node for r in incremental.apply_to_nodes(graph.nodes(e), ops).collect()) == [1, 8, 9]


def test_suspects_without_labels(spark):
    """Two communities with few links between them: the sweep finds the seed's own."""
    rng = np.random.default_rng(3)
    rows = {}
    for k in (0, 40):
        for a in range(40):
            for b in rng.choice(40, 6, replace=False):
                if a != b:
                    rows[k + a, k + int(b)] = 5
    true = [(3, 50, 4), (50, 3, 4), (20, 70, 4), (70, 20, 4)]
    e = edges(spark, *((a, b, w) for (a, b), w in rows.items()), *true)
    own = {r.node for r in sybil.community(power.power_iteration(sybil.both_ways(e), 0, 0.02, rounds=100), e, share=0.6).collect()}
    assert own == set(range(40))
    w = cut(walks.simulate_walks(e, 0, 2_000, 0.1))
    found = cut(sybil.suspect_edges(w, spark.createDataFrame([(n,) for n in own], "node long")))
    assert {(r.src, r.dst) for r in found.collect()} == {(a, b) for a, b, _ in true}
    quality = sybil.detection_quality(found, w, e, edges(spark, *true)).first()
    assert (quality.attack_edges, quality.suspects, quality.hits, quality.auroc) == (4, 4, 4, 1.0)


def test_attack_edges_are_found_in_the_experiment(spark):
    from peertrust.queries.detection import QUERIES

    r = QUERIES["sybil_suspect_quality"](spark, "/root/testdata/sf0.01").first()
    assert r.hits >= 0.8 * r.attack_edges and r.hits >= 0.8 * r.suspects and r.auroc > 0.9


def test_scenario_measures_are_those_of_tables(spark, sf):
    base, extra, labels, h = sybil.build(spark, sf, 10, sizes=(50, 200, 100))
    grid = [(0, 0.1), (10, 0.1), (10, 0.7)]
    for drop in (False, True):
        a = sybil.scenario_measures(base, extra, labels, grid, h, 60, drop_unvisited=drop).orderBy("attack", "alpha").collect()
        b = sybil.evaluate(cut(sybil.scenario_walks(base, extra, grid, 60)), labels, h, drop).orderBy("attack", "alpha").collect()
        for x, y in zip(a, b, strict=True):
            assert all((x[c] is None and y[c] is None) or x[c] == pytest.approx(y[c], abs=1e-12) for c in y.asDict())


def test_updates_are_cheaper_than_new_runs(spark):
    from peertrust.queries.workloads import update_speed

    rows = {r.way: r for r in update_speed(spark, "/root/testdata/sf0.01", "trades").collect()}
    first, scratch = rows["first"], rows["scratch"]
    for policy in ("source_visit", "coupling"):
        assert rows[f"update by {policy}"].hops < scratch.hops / (2.7 if policy == "coupling" else 1) and rows[f"update by {policy}"].seconds < scratch.seconds
        assert rows[f"update by {policy}"].l2 <= 2 * max(first.l2, scratch.l2)


def test_store_spreads_its_load(spark, sf):
    from peertrust.sources.tables import interactions

    x = cut(interactions(spark, sf))
    store = trust.TrustStore(spark, 0, 20, max_pairs=40)
    empty, sizes = x.limit(0), []
    store.update(x)
    while store.waiting.count():
        sizes.append(store.edges.count())
        store.update(empty)
    assert sizes and max(np.diff([0, *sizes])) <= 40
    key = lambda df: sorted(tuple(r) for r in df.select("src", "dst", "w").collect())
    assert key(store.edges) == key(peer_edges(spark, sf))
    hops = {(r.src, r.dst) for r in store.edges.collect()}
    rows = store.walks.orderBy("walk_id", "step").collect()
    assert all((a.node, b.node) in hops for a, b in zip(rows, rows[1:]) if a.walk_id == b.walk_id)


def test_doubling_has_the_law_of_walks(spark):
    from peertrust.doubling import doubling_walks

    e = edges(spark, (0, 1, 2), (1, 2, 3), (2, 0, 1), (1, 3, 1), (4, 0, 2), (0, 4, 1))
    got = est.estimate(doubling_walks(e, 300, 0.4), ["seed"])
    for seed in (0, 1):
        mine = got.filter(F.col("seed") == seed).select("node", "score")
        assert metrics.linf(mine, power.power_iteration(e, seed, 0.4, rounds=200)) < 0.05


def test_stream_goes_on_where_it_stopped(spark, sf, tmp_path):
    from peertrust.sources.files import stream_files
    from peertrust.streaming.trust import EVENTS

    events = spark.read.parquet(f"{sf}/events.parquet").repartition(4)
    events.filter("event_id % 2 = 0").write.parquet(str(tmp_path / "in"))
    run = lambda: stream_files(spark, str(tmp_path / "in"), EVENTS).writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start().awaitTermination()
    run()
    assert spark.read.parquet(str(tmp_path / "out")).count() == events.filter("event_id % 2 = 0").count()
    events.filter("event_id % 2 = 1").write.mode("append").parquet(str(tmp_path / "in"))
    run()
    run()
    assert spark.read.parquet(str(tmp_path / "out")).count() == events.count()


def test_refresh_policy():
    p = incremental.RefreshPolicy(k=3, max_error=0.1)
    assert [p.due(i) for i in range(5)] == [False, False, False, True, False] and p.due(1, 0.2)


def test_plans(spark, sf):
    df = spark.read.parquet(f"{sf}/events.parquet").filter("value > 10").select("event_id")
    planner.assert_plan(df, has=("PushedFilters: [IsNotNull(value), GreaterThan(value,10.0)]",))
    planner.assert_plan(graph.net_edges(spark.createDataFrame([(1, 2, 3, 0, "x")], "p long, q long, up long, down long, kind string")))
    assert planner.choose_walk_strategy(10, 5, 10) == "broadcast" and planner.choose_walk_strategy(10**9, 10**6, 300) == "binned"
    assert planner.choose_iteration(10**8, 10**9) == "shuffle"
    with pytest.raises(AssertionError):
        planner.assert_plan(df, has=("BroadcastHashJoin",))
