"""Every stage against a plain version of it, on what its predecessor kept."""

from collections import defaultdict

import numpy as np
from tokenizers import Tokenizer

import corpus_pipeline
from peertrust.llm import pii_feistel, quality_resampling, registry
from peertrust.llm.bpe_transducer import default_tokenizer

from .test_bagminhash import classes
from .test_substring_dedup import plain


def test_stages(spark, tmp_path):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, kept = docs.columns, {}
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        stage(spark, docs, sf).write.parquet(str(tmp_path / str(i)))
        before, docs = docs, spark.read.parquet(str(tmp_path / str(i)))
        if i < 4:
            assert docs.columns == columns
            kept[name] = {r.doc_id: r.text for r in docs.collect()}
            assert docs.count() == len(kept[name])
    raw = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    drawn = quality_resampling.resample(spark.read.parquet(f"{sf}/documents.parquet"), labels)[0]
    assert set(kept["quality"]) == {r.doc_id for r in drawn.filter("keep").collect()}
    good = {r.doc_id: r.quality for r in labels.collect()}
    assert np.mean([i in kept["quality"] for i, q in good.items() if q]) > 0.97
    assert np.mean([i in kept["quality"] for i, q in good.items() if not q]) < 0.05
    group = classes(list(kept["quality"].items()))
    assert set(kept["near_duplicates"]) == {i for i, c in group.items() if i == c}
    assert kept["repeated_lines"] == {i: t for i, (t, _) in plain(list(kept["near_duplicates"].items())).items()}
    p = pii_feistel.Pseudonymizer(pii_feistel.DEMO_KEY)
    assert kept["private_data"] == {i: p.replace(t)[0] for i, t in kept["repeated_lines"].items()}
    lib, pieces = Tokenizer.from_file(default_tokenizer()), defaultdict(int)
    places = defaultdict(list)
    for r in docs.collect():
        pieces[r.doc_id] += r.length
        places[r.sequence_id].append((r.offset, r.length))
    assert pieces == {i: len(lib.encode(t, add_special_tokens=False).ids) + 1 for i, t in kept["private_data"].items()}
    for s in places.values():
        assert sum(n for _, n in s) <= 2048 and [o for o, _ in sorted(s)] == np.cumsum([0, *(n for _, n in sorted(s))])[:-1].tolist()
    assert before.count() == len(pieces) and raw.keys() >= pieces.keys()


def test_registry():
    assert sorted(int(n[2:].split("_")[0]) for n in registry.QUERIES) == list(range(1, 11))
    assert set(registry.ORACLE_SQL) <= set(registry.QUERIES)
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality", "near_duplicates", "repeated_lines", "private_data", "packing"]


def test_stages_bear_odd_tables(spark):
    """Null ids and texts, repeated rows, a very long text, extra columns named like
    the operators' own, and no rows at all."""
    names = ["_gone", "_gone_id", "_kept", "rep", "label", "positions", "key", "n", "toxic", "_share"]
    long = " ".join(f"w{i % 977}" for i in range(60_000))
    rows = [(1, None), (2, ""), (3, "a few plain words in one line\nand one more line of words here"), (3, "a few plain words in one line\nand one more line of words here"), (None, "no id but some words in it"), (4, long), (5, long)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{n} int" for n in names)
    docs = spark.createDataFrame([(*r, None, "s", 1, *range(len(names))) for r in rows], schema)
    sf = "/root/testdata/sf0.001"
    for table in (docs, docs.limit(0)):
        at = table
        for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
            if name == "quality" and table is not docs:
                continue  # a model of no documents has nothing to learn from
            out = stage(spark, table, sf)
            assert i == 4 or out.columns == table.columns
            at = out.count()
        assert (at > 0) == (table is docs)
    kept = {r.doc_id for r in corpus_pipeline.near_duplicates(spark, docs, sf).collect()}
    assert kept == {None, 1, 2, 3, 4}
    assert {r.text for r in corpus_pipeline.repeated_lines(spark, docs, sf).filter("doc_id = 5").collect()} == {""}
