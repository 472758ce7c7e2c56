import json
import re

import pytest

from peertrust.llm import substring_dedup as sub


def plain(docs, sep="\n", min_words=sub.MIN_WORDS, min_sentence=sub.MIN_SENTENCE):
    """Unit by unit, in order of ids."""
    norm = lambda u: " ".join(u.lower().split())
    seen, out = {}, {}
    for doc_id, text in sorted(docs, key=lambda d: d[0]):
        left, gone, at = [], [], 0
        for unit in (text or "").split(sep):
            key, size = norm(unit), len(unit.encode())
            whole = len(key.split()) >= min_words and seen.setdefault((0, key), (doc_id, at)) != (doc_id, at)
            if whole:
                gone.append((0, at, at + size))
            rest, inner = [], at
            for piece in re.split(r"(?<=[.!?])(?=\s)", unit):
                # white space goes with the sentence before it
                lead = piece[: len(piece) - len(piece.lstrip())] if rest or inner > at else ""
                if lead:
                    rest[-1] += lead
                    inner += len(lead.encode())
                    piece = piece[len(lead) :]
                rest.append(piece)
                inner += len(piece.encode())
            kept, inner = [], at
            for piece in rest:
                key, end = norm(piece), inner + len(piece.encode())
                if len(key.split()) >= min_sentence and seen.setdefault((1, key), (doc_id, inner)) != (doc_id, inner):
                    if not whole:
                        gone.append((1, inner, end))
                else:
                    kept.append(piece)
                inner = end
            if not whole:
                left.append("".join(kept))
            at += size + len(sep)
        out[doc_id] = (sep.join(left), gone)
    return out


@pytest.mark.parametrize("unit", ["line", "paragraph"])
def test_against_plain_version(spark, unit):
    sep = sub.UNITS[unit]
    a, b = "one two three four five", "six seven eight nine ten  eleven"
    docs = [(1, sep.join([a, b, "x"])), (2, sep.join(["new words in this line", a.upper(), "x", "x"])), (3, None), (4, ""), (5, sep.join([b, b.replace("  ", "\t"), a])), (7, a), (6, sep.join(["", a, ""]))]
    passage = "Here is a first sentence of nine words, so. And here is a second one that has eleven."
    docs += [(20 + i, f"héad {i} goes on {passage} and then {i} more. Ends!{sep}{a}") for i in range(3)] + [(30, passage), (31, f"  {passage}  ")]
    df = spark.createDataFrame([(i, t, 3) for i, t in docs], "doc_id long, text string, positions int").repartition(3)
    got = {r.doc_id: (r.text, [(x.kind, x.start, x.end) for x in r.removed]) for r in sub.remove_repeats(df, unit).collect()}
    assert got == plain(docs, sep)
    out = sub.dedup_documents(df, unit)
    assert out.columns == df.columns
    assert {r.doc_id: r.text or "" for r in out.collect()} == {i: t for i, (t, _) in got.items()}


def test_tables_nulls_and_repeated_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    want = plain([(r.doc_id, r.text) for r in docs.collect()])
    for r in sub.query(spark, sf).collect():
        assert r.text == want[r.doc_id][0] and [(x["kind"], x["start"], x["end"]) for x in json.loads(r.removed)] == want[r.doc_id][1]
    line = "the same five words again"
    df = spark.createDataFrame([(1, line), (1, line), (None, line), (2, line)], "doc_id long, text string")
    assert sorted((r.doc_id or 0, r.text) for r in sub.remove_repeats(df).collect()) == [(0, line), (1, line), (1, line), (2, "")]
    assert sub.remove_repeats(df.limit(0)).count() == 0 and sub.dedup_documents(df.limit(0)).count() == 0


def test_long_units_of_few_words(spark):
    zh = "这一行文字没有空格但是很长所以重复的时候应当去掉。"
    ja = "これは空白のない長い文章です。「次の文もここに続いていきます。」そして最後の文は毎回違います"
    th = "ข้อความนี้ไม่มีช่องว่างแต่ยาวมากจึงควรถูกลบเมื่อซ้ำ"
    code = "QUJD" * 40
    docs = [(1, "\n".join([zh, th, code, "短い"])), (2, "\n".join(["new", zh, "x", th, code, "短い"]))]
    # full-width stops end sentences without white space, with the quotes behind them
    docs += [(3, ja + "一"), (4, "始まりは違う文章です。" + ja.split("そして")[0] + "終わりも違う文章です。")]
    a, b = 'He said "here are nine words in this one sentence."', "(And these are eight more words of it.)"
    docs += [(5, f"First. {a} {b} End"), (6, f"Other start. {a} {b} Other end")]
    # Unicode white space parts words
    docs += [(7, "one two three four five"), (8, "one\u00a0two\u2003three\u3000four five")]
    # a stop at the end of one text says nothing about the next
    docs += [(9, "終わり。"), (10, "」a b")]
    df = spark.createDataFrame(docs, "doc_id long, text string").coalesce(1)
    got = {r.doc_id: r.text for r in sub.remove_repeats(df).collect()}
    assert got == dict(docs) | {2: "new\nx\n短い", 4: "始まりは違う文章です。終わりも違う文章です。", 6: "Other start. Other end", 8: ""}
    assert {r.doc_id: r.text for r in sub.dedup_documents(df).collect()} == got


def test_rows_of_one_id_with_unlike_texts(spark):
    a, b, c = (f"the {w} line has five words" for w in ("first", "sécond", "third"))
    rows = [(1, f"{a}\n{b}"), (2, f"{b}\nx"), (2, f"é\n{c}\n{b} "), (2, f"{b}\nx"), (3, f"y\n{c}")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = sorted([(1, f"{a}\n{b}"), (2, "x"), (2, f"é\n{c}"), (2, "x"), (3, "y")])
    for some in (df, df.repartition(4), df.coalesce(1)):
        assert sorted((r.doc_id, r.text) for r in sub.remove_repeats(some).collect()) == want
        assert sorted((r.doc_id, r.text) for r in sub.dedup_documents(some).collect()) == want
