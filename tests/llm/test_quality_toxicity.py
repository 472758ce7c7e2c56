import math
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import functions as F

from peertrust.llm import quality_resampling as q
from peertrust.llm import toxicity_ordinal as tox


def test_held_out_quality(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    train, test = labels.filter("doc_id % 2 = 0"), labels.filter("doc_id % 2 = 1")
    rows = q.resample(docs, train)[0].join(test, "doc_id").collect()
    good = [r.keep for r in rows if r.quality == 1]
    bad = [r.keep for r in rows if r.quality == 0]
    assert np.mean(good) > 0.97 and np.mean(bad) < 0.05
    kept = {r.doc_id for r in q.resample(docs, train)[0].filter("keep").collect()}
    stage = q.select_documents(docs, train)
    assert stage.columns == docs.columns and {r.doc_id for r in stage.collect()} == kept


def test_top_k_is_exact_and_follows_the_importance(spark):
    keys = spark.range(30_000).select((F.xxhash64("id") % 1000 / 7.0).alias("x"))
    values = sorted((r.x for r in keys.collect()), reverse=True)
    for k in (1, 17, 5000, 30_000):
        assert q.kth_largest(keys, "x", k) == values[k - 1]
    assert q.kth_largest(keys, "x", 30_001) is None and q.kth_largest(keys, "x", 0) == float("inf")
    # Gumbel top-1 draws in proportion to the weights
    w = np.log(np.array([1.0, 2.0, 5.0]))
    wins = np.bincount([(w + q.gumbel(np.arange(3), s)).argmax() for s in range(4000)], minlength=3) / 4000
    assert np.abs(wins - np.array([1, 2, 5]) / 8).max() < 0.03


def plain_ngrams(text):
    """Hashed unigrams and bigrams of one text, counted one by one."""
    words = [int(w) for w in q.tokens(*q.utf8(pa.array([text or ""])), "wordpunct")[1]]
    out = Counter(w % q.BUCKETS for w in words)
    for a, b in zip(words, words[1:], strict=False):
        pair = int(q._REPEAT) if a == b else int(q.mix(np.array([(a * 0x9E3779B97F4A7C15 + (b ^ 0xD6E8FEB86659FD93)) % (1 << 64)], np.uint64))[0])
        out[pair % q.BUCKETS] += 1
    return out


def test_query_against_a_plain_version(spark, sf):
    docs = {r.doc_id: plain_ngrams(r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    sample = {r.label_id: r for r in q.labelled_sample(spark.read.parquet(f"{sf}/labels.parquet")).collect()}
    raw, target = Counter(), Counter()
    for i, grams in docs.items():
        raw += grams
        if i in sample and sample[i].half == 0 and sample[i].good == 1:
            target += grams
    scale = sum(target.values()) / sum(raw.values())
    ratio = {b: math.log((target[b] + q.PRIOR) / (n * scale + q.PRIOR)) for b, n in raw.items()}
    weight = {i: q.SPAN * sum(n * ratio[b] for b, n in g.items()) / max(1, sum(g.values())) for i, g in docs.items()}
    held = [(weight[i], s.good) for i, s in sample.items() if s.half == 1 and i in docs]
    values = sorted({w for w, _ in held})
    places = [values[0] - 1, *((a + b) / 2 for a, b in zip(values, values[1:], strict=False)), values[-1] + 1]
    good, bad = [w for w, g in held if g], [w for w, g in held if not g]
    cost = {p: sum(w < p for w in good) / len(good) + sum(w >= p for w in bad) / len(bad) for p in places}
    k = {sum(w >= p for w in weight.values()) for p in places if cost[p] <= min(cost.values()) + 1e-12}
    noise = dict(zip(docs, q.gumbel(np.array(list(docs)), q.SEED), strict=True))
    rows = q.query(spark, sf).collect()
    assert len(rows) == len(docs)
    for r in rows:
        assert math.isclose(r.log_importance, weight[r.doc_id], rel_tol=1e-9, abs_tol=1e-9) and math.isclose(r.sample_key, weight[r.doc_id] + noise[r.doc_id], rel_tol=1e-9)
    kept = {r.doc_id for r in rows if r.keep}
    assert len(kept) in k
    assert kept == set(sorted(docs, key=lambda i: -(weight[i] + noise[i]))[: len(kept)])


def test_draws_follow_the_importance(spark):
    """Two of five documents, drawn with many seeds, against the exact chances."""
    n = 5
    docs = spark.createDataFrame([(i, " ".join(["good"] * i + ["bad"] * (n - 1 - i))) for i in range(n)], "doc_id long, text string")
    grams = Counter()
    model = q.Model(np.zeros(q.BUCKETS), np.zeros(q.BUCKETS), 0.5)
    for word, value in (("good", 0.2), ("bad", -0.2)):
        model.ratio[int(q.tokens(*q.utf8(pa.array([word])), "wordpunct")[1][0]) % q.BUCKETS] = value
    w = {r.doc_id: math.exp(r.log_importance) for r in q.scored(docs, model, span=4.0).collect()}
    for seed in range(2500):
        keys = np.log([w[i] for i in range(n)]) + q.gumbel(np.arange(n), seed)
        grams.update(np.argsort(-keys)[:2].tolist())
    total = sum(w.values())
    for i in range(n):
        exact = w[i] / total + sum(w[j] / total * w[i] / (total - w[j]) for j in range(n) if j != i)
        assert abs(grams[i] / 2500 - exact) < 0.04


def test_parting_value():
    assert q.parting_value(np.array([1.0, 2, 8, 9]), np.array([0, 0, 1, 1]), 0) == 5
    assert q.parting_value(np.array([1.0, 2]), np.array([1, 1]), 7) == 7


def test_long_clean_documents_of_a_minority_language_stay(spark):
    rng = np.random.default_rng(5)
    text = lambda kind, n: " ".join(f"{kind}{i}" for i in rng.integers(0, 20, n))
    docs = [(i, text("a", 40)) for i in range(300)] + [(i, text("b", 40)) for i in range(300, 500)] + [(i, text("junk", 40)) for i in range(500, 600)]
    docs += [(600, text("b", 2000)), (601, text("b", 1)), (602, text("junk", 2000))]
    labels = [(i, 1, 0) for i in [*range(200), *range(300, 400)]] + [(i, 0, 0) for i in range(500, 580)]
    df, marks = spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    kept = {r.doc_id for r in q.resample(df, marks, span=1e3)[0].filter("keep").collect()}
    assert kept == {*range(500), 600, 601}
    assert {r.doc_id for r in q.select_documents(df, marks, span=1e3).collect()} == kept


def test_quality_edge_cases(spark):
    docs = spark.createDataFrame([(1, None, 0.5), (2, "", 0.5), (3, "good words here", 0.5), (3, "good words here", 0.5), (None, "x" * 100_000, 0.5)], "doc_id long, text string, log_importance double")
    labels = spark.createDataFrame([*((i, 1, 0) for i in range(3, 12)), (99, None, None)], "doc_id long, quality int, toxic int")
    rows = q.resample(docs, labels)[0].collect()
    assert len(rows) == 5 and all(r.log_importance == 0 for r in rows if r.doc_id in (1, 2))
    assert q.resample(docs, labels.limit(0))[0].filter("keep").count() == 5
    assert q.resample(docs.filter("doc_id = 3"), labels, k=1)[0].count() == 2


def test_held_out_toxicity(spark):
    sf = "/root/testdata/sf0.1"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    model = tox.fit(docs, tox.labelled_sample(labels.filter("doc_id % 2 = 0")))
    assert len(model.thresholds) == 2 and model.thresholds[0] < model.thresholds[1]
    rows = tox.score(docs, model).join(labels.filter("doc_id % 2 = 1").select("doc_id", F.col("toxic").alias("y")), "doc_id").collect()
    y, hit = np.array([r.y for r in rows]) == 1, np.array([r.toxic for r in rows])
    assert hit[y].mean() > 0.8 and hit[~y].mean() < 0.05
    severity = np.array([r.expected_severity for r in rows])
    assert severity[y].mean() > 10 * severity[~y].mean()


def test_ordinal_fit_recovers_a_known_model():
    rng = np.random.default_rng(0)
    n, theta, w = 6000, np.array([-0.5, 1.5]), np.array([2.0, -1.5, 0, 0, 0])
    x = rng.random((n, 5)) < 0.4
    u = rng.logistic(size=n) + x @ w
    grade = (u[:, None] > theta).sum(axis=1)
    row, word = np.nonzero(x)
    model = tox.train(row, word, grade, buckets=8)
    assert np.abs(model.weights[:2] - w[:2]).max() < 0.25 and np.abs(model.weights[2:]).max() < 0.1
    assert np.abs(model.thresholds - theta).max() < 0.2
    p = model.probabilities(x @ model.weights[:5])
    assert np.allclose(p.sum(axis=1), 1) and abs((p @ np.arange(3)).mean() - grade.mean()) < 0.05


def test_toxicity_edge_cases(spark):
    model = tox.OrdinalModel(np.zeros(tox.BUCKETS), np.array([2.0, 4.0]))
    docs = spark.createDataFrame([(1, None, 1), (2, "", 1), (None, "a b", 1)], "doc_id long, text string, toxic int")
    assert [round(r.p_toxic, 6) for r in tox.score(docs, model).collect()] == [0.119203] * 3
    assert tox.score(docs.limit(0), model).count() == 0
    for grade, toxic in (([0, 0, 0], 0), ([1, 1, 1], 3), ([], 0)):
        flat = tox.train(np.empty(0, int), np.empty(0, int), np.array(grade, int))
        assert tox.score(docs, flat).filter("toxic").count() == toxic
    none = tox.labelled_sample(spark.createDataFrame([(None, 1, 1), (1, None, None)], "doc_id long, quality int, toxic int"))
    assert tox.score(docs, tox.fit(docs, none)).filter("toxic").count() == 0


def test_toxicity_does_not_depend_on_the_order_of_rows(spark):
    sf = "/root/testdata/sf0.01"
    docs, labels = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "labels"))
    want = {r.doc_id: (r.expected_severity, r.toxic) for r in tox.query(spark, sf).collect()}
    for d, l in ((docs.repartition(5), labels.repartition(3)), (docs.coalesce(1).orderBy(F.desc("doc_id")), labels.orderBy(F.rand(1)))):
        got = {r.doc_id: (r.expected_severity, r.toxic) for r in tox.score(d, tox.fit(d, tox.labelled_sample(l))).collect()}
        assert got == want
    again = docs.unionByName(docs.join(labels, "doc_id", "left_semi"))
    model = tox.fit(again, tox.labelled_sample(labels))
    assert {r.doc_id: (r.expected_severity, r.toxic) for r in tox.score(docs, model).collect()} == want
