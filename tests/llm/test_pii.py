import re

import pytest

from peertrust.llm import pii_feistel as pii

KEY = b"k"


@pytest.mark.parametrize("size", [1, 2, 3, 10, 1000, 4097, 10**15])
def test_feistel_is_a_permutation(size):
    f = pii.Feistel(KEY, "t", size)
    xs = range(size) if size < 5000 else range(0, size, size // 500)
    ys = [f.permute(x) for x in xs]
    assert len(set(ys)) == len(ys) and all(0 <= y < size for y in ys)
    assert [f.permute(y, back=True) for y in ys] == list(xs)


VALUES = ["4785380592391139", "+1 (743) 555-3824", "114.203.152.12", "hein.19@mail5.example.com", "2024-02-29", "1/12/2020", "11/12/2020", "31.12.1999", "3.4.2001",
          "1eb9c654e721b4f812088970e66a6345ce33dd61", "123-45-6789", "4111 1111 1111 1111", "a" * 65 + "@x.org", "z9." * 100 + "b@long-host.sub.example.org", "a" * 205 + "@b.io", "q" * 5000 + "@" + "h" * 300 + ".net"]


@pytest.mark.parametrize("value", VALUES)
def test_format_is_kept_and_undone(value):
    text = f"before {value}, after"
    new, spans = pii.Pseudonymizer(KEY).replace(text)
    assert len(spans) == 1 and value not in new
    kind, a, b = spans[0]
    got = new[a:b]
    if kind not in ("ip", "date"):
        assert re.sub("[0-9a-z]", "x", got) == re.sub("[0-9a-z]", "x", value)
    if kind == "card":
        digits = re.sub(r"\D", "", got)
        assert pii.luhn_digit(digits[:-1]) == digits[-1]
    assert pii.Pseudonymizer(KEY, back=True).replace(new)[0] == text
    assert pii.Pseudonymizer(KEY).replace(f"{value} {value}")[0] == f"{got} {got}"
    assert pii.Pseudonymizer(b"other").replace(text)[0] != new


def test_what_is_not_valid_stays():
    for text in ("4785380592391138", "999.1.1.1", "2023-02-29", "01/5/2020", "000-12-3456", "plain words", "v1.2.3", "1234567"):
        assert pii.Pseudonymizer(KEY).replace(text) == (text, [])


def test_frames(spark):
    docs = spark.createDataFrame([(1, None, "a"), (2, "", "a"), (3, "mail a.b@x.org", "b"), (3, "mail a.b@x.org", "b"), (None, "call +49 (151) 555-1234" + " x" * 50000, "c")], "doc_id long, text string, spans string")
    rows = pii.pseudonymize(docs).collect()
    assert [r.text for r in rows if r.doc_id in (1, 2)] == [None, ""]
    assert len({r.text for r in rows if r.doc_id == 3}) == 1
    out = pii.pseudonymize_documents(docs)
    assert out.columns == docs.columns and out.count() == 5
    assert pii.pseudonymize(docs.limit(0)).count() == 0


def test_every_planted_value_goes(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    old = {r.doc_id: r.text for r in docs.collect()}
    for r in pii.pseudonymize(docs).collect():
        for m in re.findall(r"[\w.]+@[\w.]+\w|\b4\d{15}\b|\+1 \(\d{3}\) 555-\d{4}", old[r.doc_id]):
            assert m not in r.text
        if not re.search(r"\d|@", old[r.doc_id]):
            assert r.text == old[r.doc_id]


@pytest.mark.parametrize("n", [1, 2, 3, 63, 64, 65, 190, 198, 199, 300, 1023, 5000])
def test_names_of_any_length(n):
    forth, back = pii.Pseudonymizer(KEY), pii.Pseudonymizer(KEY, back=True)
    seen = set()
    for name in ("a" * n, "b" + "a" * (n - 1), "a" * (n - 1) + "b", "z" * n):
        text = f"to {name}@host.example.org now"
        new, spans = forth.replace(text)
        assert len(spans) == 1 and len(new) == len(text) and back.replace(new)[0] == text
        assert n < 20 or not re.search(r"(.)\1{9}", new)  # nothing of the name is left readable
        seen.add(new)
    assert len(seen) == len({"a" * n, "b" + "a" * (n - 1), "a" * (n - 1) + "b", "z" * n})


def test_short_strings_of_digits_are_permuted():
    import itertools

    import numpy as np

    for n in (1, 2, 3):
        all_ = [pii.permute_digits(KEY, np.array(x), 5).tolist() for x in itertools.product(range(5), repeat=n)]
        assert sorted(all_) == sorted(map(list, itertools.product(range(5), repeat=n)))


def test_tables_against_a_plain_reading(spark, sf):
    """Outside of the spans nothing changes; inside, equal values have equal
    pseudonyms, unlike ones unlike ones, and the key brings all of them back."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    old = {r.doc_id: r.text for r in docs.collect()}
    new = pii.pseudonymize(docs).collect()
    forth, back = {}, {}
    for r in new:
        text, at, gone = old[r.doc_id], 0, 0
        for s in r.spans:
            # the plain text between the spans is that of the original
            plain = r.text[gone : s.start]
            assert text[at : at + len(plain)] == plain
            at += len(plain)
            found = pii.PATTERN.match(text, at)
            kind, was, now = found.lastgroup, found[0].lower(), r.text[s.start : s.end].lower()
            assert kind == s.kind and was != now or kind in ("date", "ip")
            assert forth.setdefault((kind, was), now) == now and back.setdefault((kind, now), was) == was
            at, gone = found.end(), s.end
        assert text[at:] == r.text[gone:]
        assert len(r.spans) == sum(r[f"n_{k}"] for k in pii.KINDS)
    again = pii.pseudonymize(spark.createDataFrame([(r.doc_id, r.text) for r in new], "doc_id long, text string"), back=True)
    assert all(r.text.lower() == old[r.doc_id].lower() for r in again.collect())
