"""Substring dedup by line or paragraph hashing, with sentences as the finer unit.

Every text is cut into units: lines (or paragraphs parted by blank lines), and the
sentences in them.  A unit is normalised (white space folded, lower case) and hashed
to 128 bits, as the polynomial of its hashed words.  The earliest occurrence of a
digest by ``(doc_id, offset)`` stays; the others go.  A repeated line goes whole;
from other lines their repeated sentences go, so a passage that was set into the
middle of a line is found too.

Plan.  Digests are counted with map-side combining, so a line that stands in a
third of all documents reaches its reducer as one row per map task.  Only digests
seen more than once go on.  They meet the occurrences in a sort-merge join whose
two sides both have an exchange of their own (the keys are re-encoded after the
count), which lets adaptive execution split the partition of a hot line.  Texts
move once, to meet the ranges that they lose.

White space is that of Unicode.  A sentence ends at a stop, with the quotes and
brackets that close behind it, before white space; after the full-width stops of
scripts that set no spaces it ends without any.

Defined results: null texts are empty and lose nothing; lines of fewer than
``MIN_WORDS`` words and sentences of fewer than ``MIN_SENTENCE`` count as repeats
only if they are long: every two characters of a script without spaces count as a
further word, and ``MIN_BYTES`` bytes besides white space are enough; equal rows (of
``doc_id`` and text) are the same document; unlike texts of one ``doc_id`` are
documents of their own, in the order of a hash of the text (their ``variant``); rows
without ``doc_id`` pass unchanged.  Offsets are those of the UTF-8 bytes of the original.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .bytehash import BASE, INVERSE, HashedBytes, mix, powers_of
from .common import fresh, id_and_text, slices, text_or_empty, utf8
from .wordhash import CLASSES, lowered

#: What parts the units, and what joins the kept ones again.
UNITS = {"line": "\n", "paragraph": "\n\n"}
MIN_WORDS, MIN_SENTENCE = 5, 8
LINE, SENTENCE = 0, 1
#: Bytes from which a unit counts, however few its words.
MIN_BYTES = {LINE: 64, SENTENCE: 128}
_REKEY = 0x5DEECE66D
_SPACES = "\u0085\u00a0\u1680\u2000\u2001\u2002\u2003\u2004\u2005\u2006\u2007\u2008\u2009\u200a\u2028\u2029\u202f\u205f\u3000"
#: Stops before white space, stops that need none, and what may close behind a stop.
_STOPS, _WIDE_STOPS = ".!?\u2026\u061f\u06d4\u0964\u0965\u1362", "\u3002\uff01\uff1f\uff61\uff0e"
_CLOSERS = "\"')]}\u00bb\u203a\u2019\u201d\u300d\u300f\u3011\u300b\u3009\u3015\uff09\uff3d\uff5d\uff63"
#: First and last head (two bytes) of the characters of scripts without spaces: Thai
#: and Lao, Burmese, Khmer, kana, ideographs, half-width kana, further ideographs.
_UNSPACED = ((0xE0B8, 0xE0BB), (0xE180, 0xE182), (0xE19E, 0xE19F), (0xE381, 0xE9BF), (0xEFA4, 0xEFAB), (0xEFBD, 0xEFBE), (0xF0A0, 0xF0B3))
_OUT = "doc_id long, text string, n_units int, n_removed int, removed array<struct<kind:int,start:int,end:int>>"


def _marked(buf: np.ndarray, chars: str) -> tuple[np.ndarray, np.ndarray]:
    """Which bytes belong to one of ``chars``, and which of them are its last."""
    every, last = np.zeros(len(buf), bool), np.zeros(len(buf), bool)
    heads: dict[int, list[bytes]] = {}
    for c in chars:
        heads.setdefault(c.encode()[0], []).append(c.encode())
    for head, codes in heads.items():
        at = np.flatnonzero(buf == head)
        for code in codes if len(at) else ():
            hit = at[at + len(code) <= len(buf)]
            for j, byte in enumerate(code[1:], 1):
                hit = hit[buf[hit + j] == byte]
            last[hit + len(code) - 1] = True
            for j in range(len(code)):
                every[hit + j] = True
    return every, last


def _unspaced(buf: np.ndarray) -> np.ndarray:
    """Where characters of scripts without spaces begin."""
    out = np.zeros(len(buf), bool)
    at = np.flatnonzero(buf[:-1] >= 0xE0)
    pair = buf[at].astype(np.int32) * 256 + buf[at + 1]
    for low, high in _UNSPACED:
        out[at[(pair >= low) & (pair <= high)]] = True
    return out


def _runs(words: np.ndarray, first: np.ndarray, last: np.ndarray, salt: int) -> tuple[np.ndarray, np.ndarray]:
    """Two independent digests of each run ``words[first:last]``, as signed numbers."""
    out = []
    for other in (0x5851F42D4C957F2D, 0x14057B7EF767814F):
        h = mix(words ^ np.uint64(other + salt))
        prefix = np.zeros(len(h) + 1, np.uint64)
        np.cumsum(h * powers_of(BASE, len(h) + 1)[: len(h)], out=prefix[1:])
        out.append(mix((prefix[last] - prefix[first]) * powers_of(INVERSE, len(h) + 1)[first]).view(np.int64))
    return out[0], out[1]


def unit_table(buf: np.ndarray, offsets: np.ndarray, unit: str, min_words: int, min_sentence: int) -> dict[str, np.ndarray]:
    """``text, kind, start, end, h1, h2`` of the units that may be repeats; ``start``
    and ``end`` count from the beginning of their text."""
    n = len(buf)
    low = lowered(buf)
    solid = (CLASSES["fields"][low] > 0) & ~_marked(buf, _SPACES)[0]
    wide_bytes, wide_stop = _marked(buf, _WIDE_STOPS)
    stop = _marked(buf, _STOPS)[1] | wide_stop
    closer = _marked(buf, _CLOSERS)[0]
    # the last byte up to each one that closes nothing
    core = np.maximum.accumulate(np.where(closer, -1, np.arange(n))) if n else np.arange(n)
    breaks = buf == 10
    if unit == "paragraph":
        # of a row of line breaks every second one ends a separator
        index = np.arange(n)
        run = index - np.maximum.accumulate(np.where(breaks, -1, index)) if n else index
        breaks = breaks & (run % 2 == 0)
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    if wide_stop.any():
        # words part behind stops that need no white space
        at = np.flatnonzero(solid[1:] & ~(closer | wide_bytes)[1:] & (core[:-1] >= 0) & wide_stop[core[:-1]]) + 1
        edge[at[np.searchsorted(offsets, at, side="right") == np.searchsorted(offsets, core[at - 1], side="right")]] = True
    begin = np.flatnonzero(solid & (edge[:n] | ~np.concatenate([[False], solid[:-1]])))
    end = np.flatnonzero(solid & (edge[1:] | ~np.concatenate([solid[1:], [False]]))) + 1
    text = np.searchsorted(offsets, begin, side="right") - 1
    words = mix(HashedBytes(low).ranges(begin, end))
    # where lines lie: bounds of texts and separators
    width = len(UNITS[unit])
    line_end = np.concatenate([offsets[1:], np.flatnonzero(breaks) + 1 - width])
    is_text_end = np.arange(len(line_end)) < len(offsets) - 1
    order = np.lexsort((~is_text_end, line_end))  # a text ends before the next one's empty first line
    line_end, is_text_end = line_end[order], is_text_end[order]
    line = np.searchsorted(line_end, begin, side="right")
    line_start = np.concatenate([[0], np.where(is_text_end, line_end, line_end + width)[:-1]]) if len(line_end) else line_end
    new_line = np.concatenate([[True], (line[1:] != line[:-1]) | (text[1:] != text[:-1])]) if len(begin) else np.empty(0, bool)
    new_sentence = new_line | np.concatenate([[False], (core[end[:-1] - 1] >= begin[:-1]) & stop[core[end[:-1] - 1]]]) if len(begin) else new_line
    n_solid, n_unspaced = (np.concatenate([[0], np.cumsum(x)]) for x in (solid, _unspaced(buf)))
    parts = []
    for kind, opens, least in ((LINE, np.flatnonzero(new_line), min_words), (SENTENCE, np.flatnonzero(new_sentence), min_sentence)):
        closes = np.concatenate([opens[1:], [len(begin)]])[: len(opens)]
        a, b = line_start[line[opens]], line_end[line[opens]]
        if kind == SENTENCE:
            inner = ~new_line[opens]
            a = np.where(inner, begin[opens], a)
            follows = np.concatenate([inner[1:], [False]])[: len(opens)]
            b = np.where(follows, np.concatenate([begin[opens][1:], [n]])[: len(opens)], b)
        first, last = begin[opens], end[closes - 1]
        keep = (closes - opens + (n_unspaced[last] - n_unspaced[first]) // 2 >= least) | (n_solid[last] - n_solid[first] >= MIN_BYTES[kind])
        h1, h2 = _runs(words, opens[keep], closes[keep], kind)
        t = text[opens[keep]]
        parts.append((t, np.full(len(t), kind), a[keep] - offsets[t], b[keep] - offsets[t], h1, h2))
    return dict(zip(("text", "kind", "start", "end", "h1", "h2"), (np.concatenate(c) for c in zip(*parts, strict=True)), strict=True))


def _variant():
    """What tells rows of one id and unlike texts apart."""
    return F.xxhash64(text_or_empty()).alias("variant")


def _digests(docs: DataFrame, unit: str, min_words: int, min_sentence: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                t = unit_table(*utf8(part.column(1)), unit, min_words, min_sentence)
                ids, variants = (part.column(i).to_numpy(zero_copy_only=False)[t["text"]] for i in (0, 2))
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(variants, pa.int64()), *(pa.array(t[c].astype(np.int32)) for c in ("kind", "start", "end")), pa.array(t["h1"]), pa.array(t["h2"])], names=["doc_id", "variant", "kind", "start", "end", "h1", "h2"])

    return docs.mapInArrow(run, "doc_id long, variant long, kind int, start int, end int, h1 long, h2 long")


def repeated_units(docs: DataFrame, unit: str = "line", min_words: int = MIN_WORDS, min_sentence: int = MIN_SENTENCE) -> DataFrame:
    """``doc_id, variant`` and ``gone``: the units that an earlier occurrence repeats."""
    units = _digests(id_and_text(docs, _variant()).filter(F.col("doc_id").isNotNull()), unit, min_words, min_sentence)
    first = (
        units.groupBy("h1", "h2")
        .agg(F.min(F.struct("doc_id", "variant", "start")).alias("first"), F.count(F.lit(1)).alias("n"))
        .filter("n > 1")
        .select((F.col("h1").bitwiseXOR(F.lit(_REKEY))).alias("k1"), (F.col("h2").bitwiseXOR(F.lit(_REKEY))).alias("k2"), "first")
    )
    again = units.select("doc_id", "variant", "kind", "start", "end", (F.col("h1").bitwiseXOR(F.lit(_REKEY))).alias("k1"), (F.col("h2").bitwiseXOR(F.lit(_REKEY))).alias("k2"))
    return (
        again.join(first.hint("merge"), ["k1", "k2"])
        .filter(F.struct("doc_id", "variant", "start") != F.col("first"))
        .groupBy("doc_id", "variant")
        .agg(F.sort_array(F.collect_set(F.struct("start", "kind", "end"))).alias("gone"))
    )


def cut_units(text: str, gone: list[tuple[int, int, int]], sep: str) -> tuple[str, list[tuple[int, int, int]]]:
    """The text without its ``(start, kind, end)`` units, and ``kind, start, end`` of
    those cut; sentences of lines that go count with their line."""
    data = text.encode()
    width, at, out, lost, strip = len(sep), 0, [], [], False
    for start, kind, end in sorted(gone):
        if start < at or end > len(data):
            continue  # in a line that is gone
        lost.append((kind, start, end))
        out.append(data[at:start])
        at = end
        if kind == LINE:
            if end < len(data):
                at += width
            else:
                strip = True  # the last line went, so the separator before it goes
    out.append(data[at:])
    left = b"".join(out)
    if strip and left.endswith(sep.encode()):
        left = left[:-width]
    return left.decode(), lost


def _rebuild(unit: str):
    sep = UNITS[unit]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            kept, n_units, spans = [], [], []
            for text, gone in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                left, lost = cut_units(text, [(g["start"], g["kind"], g["end"]) for g in gone], sep) if gone else (text, [])
                kept.append(left)
                n_units.append(text.count(sep) + 1)
                spans.append([{"kind": k, "start": a, "end": b} for k, a, b in lost])
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(kept, pa.string()), pa.array(n_units, pa.int32()), pa.array([len(s) for s in spans], pa.int32()),
                 pa.array(spans, pa.list_(pa.struct([("kind", pa.int32()), ("start", pa.int32()), ("end", pa.int32())])))],
                names=["doc_id", "text", "n_units", "n_removed", "removed"],
            )

    return run


def remove_repeats(docs: DataFrame, unit: str = "line", min_words: int = MIN_WORDS, min_sentence: int = MIN_SENTENCE) -> DataFrame:
    """One row per row of ``docs``: the text without its repeated units, and the
    removed units (``kind`` 0 line, 1 sentence) with their byte offsets in the
    original text."""
    gone = repeated_units(docs, unit, min_words, min_sentence).withColumnsRenamed({"doc_id": "gone_id", "variant": "gone_variant"})
    rows = id_and_text(docs, _variant())
    joined = rows.join(gone, (rows.doc_id == gone.gone_id) & (rows.variant == gone.gone_variant), "left").select("doc_id", "text", "gone")
    return joined.mapInArrow(_rebuild(unit), _OUT)


def dedup_documents(docs: DataFrame, unit: str = "line", min_words: int = MIN_WORDS, min_sentence: int = MIN_SENTENCE) -> DataFrame:
    """``docs`` with its own columns, ``text`` (and ``n_chars``) without repeats.
    Documents that only held repeats stay, with an empty text."""
    key, variant, gone_name = (fresh(docs, x) for x in ("_gone_id", "_gone_variant", "_gone"))
    gone = repeated_units(docs, unit, min_words, min_sentence).select(F.col("doc_id").alias(key), F.col("variant").alias(variant), F.to_json("gone").alias(gone_name))
    none = F.col(gone_name).isNull()
    out = docs.join(gone, (F.col("doc_id").cast("long") == F.col(key)) & (_variant() == F.col(variant)), "left").withColumn("text", F.when(none, F.col("text")).otherwise(_without(unit)(F.col("text"), F.col(gone_name))))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(none, F.col("n_chars")).otherwise(F.length("text").cast("long")))
    return out.select(*docs.columns)


def _without(unit: str):
    sep = UNITS[unit]

    @F.pandas_udf("string")
    def without(text: pd.Series, gone: pd.Series) -> pd.Series:
        def one(t, g):
            if t is None or g is None:
                return t
            return cut_units(t, [(x["start"], x["kind"], x["end"]) for x in json.loads(g)], sep)[0]

        return pd.Series([one(t, g) for t, g in zip(text, gone, strict=True)], dtype=object)

    return without


def query(spark, sf_dir) -> DataFrame:
    """``op1``: line and sentence dedup of all documents."""
    out = remove_repeats(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "n_units", "n_removed", F.length("text").alias("n_kept_chars"), F.md5("text").alias("kept_md5"), "text",
                      F.to_json("removed").alias("removed"))


_NORM = r"trim(lower(regexp_replace({}, '\s+', ' ', 'g')))"
_WORDS = "len({0}) - len(replace({0}, ' ', '')) + 1"
ORACLE_SQL = rf"""
WITH parts AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS unit, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) - 1 AS pos
  FROM documents),
units AS (SELECT doc_id, pos, unit, {_NORM.format('unit')} AS norm, sum(strlen(unit) + 1) OVER (PARTITION BY doc_id ORDER BY pos) - strlen(unit) - 1 AS start FROM parts),
lines AS (SELECT *, norm <> '' AND {_WORDS.format('norm')} >= {MIN_WORDS} AND row_number() OVER (PARTITION BY norm ORDER BY doc_id, pos) > 1 AS gone FROM units),
pieces AS (SELECT doc_id, pos, gone, start AS line_start, string_split(regexp_replace(unit, '([.!?]\s+)', '\1' || chr(1), 'g'), chr(1)) AS list FROM lines),
piece AS (SELECT doc_id, pos, gone, line_start, unnest(list) AS s, generate_subscripts(list, 1) AS i FROM pieces),
sentence AS (SELECT *, {_NORM.format('s')} AS norm, line_start + sum(strlen(s)) OVER (PARTITION BY doc_id, pos ORDER BY i) - strlen(s) AS start FROM piece),
marked AS (SELECT *, norm <> '' AND {_WORDS.format('norm')} >= {MIN_SENTENCE} AND row_number() OVER (PARTITION BY norm ORDER BY doc_id, start) > 1 AS cut FROM sentence),
kept_lines AS (SELECT doc_id, pos, any_value(gone) AS gone, coalesce(string_agg(s, '' ORDER BY i) FILTER (WHERE NOT cut), '') AS line FROM marked GROUP BY doc_id, pos),
lost AS (
  SELECT doc_id, start, 0 AS kind, start + strlen(unit) AS stop FROM lines WHERE gone
  UNION ALL SELECT doc_id, start, 1, start + strlen(s) FROM marked WHERE cut AND NOT gone),
spans AS (SELECT doc_id, count(*) AS n, string_agg('{{"kind":' || kind || ',"start":' || CAST(start AS BIGINT) || ',"end":' || CAST(stop AS BIGINT) || '}}', ',' ORDER BY start) AS removed FROM lost GROUP BY doc_id),
docs AS (SELECT doc_id, CAST(count(*) AS INTEGER) AS n_units, coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '') AS text FROM kept_lines GROUP BY doc_id)
SELECT doc_id, n_units, CAST(coalesce(n, 0) AS INTEGER) AS n_removed, CAST(len(text) AS INTEGER) AS n_kept_chars, md5(text) AS kept_md5, text, '[' || coalesce(removed, '') || ']' AS removed
FROM docs LEFT JOIN spans USING (doc_id)
"""
