import hashlib
import random

import pytest
from tokenizers import Tokenizer

from peertrust.llm import bpe_transducer as bpe

PATH = bpe.default_tokenizer()


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(PATH)


@pytest.fixture(scope="module")
def blob():
    return bpe.build_lexicon(None, PATH)


def texts(n=400):
    rng = random.Random(5)
    pool = ["the", "The", "Éclair", "naïve", "don't", "we'll", "x's", "''s", "123", "½²", "Ⅷ", "  ", "\n", "\t", "\x85", "\xa0", "　", "\x1c", "​",
            "<|endoftext|>", "<|startoftext|>", "<|", "İstanbul", "ΣΊΣΥΦΟΣ", "é", "日本語", "😀👍🏽", "ß", "ﬁ", "a" * 300, "!?" * 90, "́", "_", "क्षि", "\x00"]
    out = ["", " ", *pool]
    for _ in range(n):
        out.append("".join(rng.choice([*pool, " ", " ", chr(rng.randrange(32, 0x2FFF))]) for _ in range(rng.randrange(1, 40))))
    return out


def test_same_ids_and_decoded_text_as_the_library(library, blob):
    for enc in (bpe.Encoder(PATH, blob), bpe.Encoder(PATH, None)):
        for t in texts():
            want = library.encode(t, add_special_tokens=False).ids
            assert enc.encode(t) == want, repr(t)
            assert enc.decode(want) == library.decode(want, skip_special_tokens=False)


def test_automaton_is_minimal_and_numbers_its_words():
    words = {w: [i, i + 1] for i, w in enumerate([b"tops", b"stops", b"top", b"stop", b"tap", b"taps"])}
    arrays = bpe.compile_lexicon(words)
    assert len(arrays["final"]) == 7
    lex = bpe.Lexicon(bpe.packed(arrays))
    found = lex.find([b"tops", b"stop", b"to", b"stopss", b"", b"taps"])
    assert (found >= 0).tolist() == [True, True, False, False, False, True]
    assert [lex.outputs(found[[i]])[0].tolist() for i in (0, 1, 5)] == [words[b"tops"], words[b"stop"], words[b"taps"]]


def test_long_words_merge_as_short_ones_do():
    table = bpe.MergeTable(PATH)
    for word in ("internationalization", "aaaaaaaaaaaaaaaaaaaa", "thethethethe"):
        data = word.encode()
        symbols = [table.inner[b] for b in data[:-1]] + [table.final[data[-1]]]
        short = table._short(list(symbols))
        assert table._long(list(symbols)) == short
        ids, count = table.words([data, b"a", data])
        assert ids.tolist() == [*short, *table.word("a"), *short] and count.tolist() == [len(short), 1, len(short)]


def test_query_shape_and_edge_cases(spark, library):
    docs = spark.createDataFrame([(1, None, "x"), (2, "", "x"), (3, "Hello Hello wörld", "y"), (3, "Hello Hello wörld", "y"), (None, "a", "z")], "doc_id long, text string, ids string")
    rows = {(r.doc_id, r.n_tokens): r for r in bpe.encoding_digests(docs, PATH, bpe.build_lexicon(docs, PATH)).collect()}
    empty = hashlib.sha256(b"").hexdigest()
    assert rows[1, 0].ids_sha256 == rows[2, 0].decoded_sha256 == empty
    ids = library.encode("Hello Hello wörld", add_special_tokens=False).ids
    assert rows[3, len(ids)].ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
    back = bpe.decode_documents(bpe.encode_documents(docs, PATH)).collect()
    assert {r.text for r in back if r.doc_id == 3} == {library.decode(ids, skip_special_tokens=False)}
    assert bpe.encoding_digests(docs.limit(0), PATH).count() == 0
