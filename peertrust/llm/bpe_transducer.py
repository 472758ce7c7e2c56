"""BPE encoding and decoding with a minimal acyclic transducer as the lexicon.

The frequent words of the corpus (counted over all documents) and their token ids
are compiled into a minimal automaton: words share prefixes and suffixes, each
edge carries how many words come before it, so the numbers met on a path add up
to the word's place in the table of outputs.  The automaton is a handful of sorted
arrays in one file, which every worker memory-maps; all new words of a chunk of text
walk it at once, a byte per step.  Words outside the lexicon are merged exactly, rank
by rank, all words of a chunk in step.  What a worker has once encoded it keeps in a
table of bounded size (``wordstream``).  Lexicon and table are a matter of speed only:
any lexicon gives the same ids.

Sizes: the lexicon has at most ``LEXICON_WORDS`` words of the corpus.  Words are
counted exactly: a partition reports every word that it has, of at most
``LEXICON_LETTERS`` letters, and Spark adds the counts up.

Defined results: a null text is empty and has no tokens; very long words are
merged with a heap, in ``n log n``.
"""

from __future__ import annotations

import hashlib
import heapq
import io
import json
import os
import tempfile
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_and_text, saved, slices
from .wordstream import WordTable, numbered, ragged

LEXICON_WORDS = 40_000
LEXICON_LETTERS = 64
#: Text whose words are looked up together.
CHUNK_BYTES = 4 << 20
_END = "</w>"


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def byte_letters() -> list[str]:
    """The letter that stands for each byte in byte-level vocabularies: printable
    Latin-1 bytes for themselves, the others from U+0100 on."""
    plain = {*range(33, 127), *range(161, 173), *range(174, 256)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class KeyTable:
    """Open addressing over 32-bit keys, for whole arrays of lookups."""

    def __init__(self, keys: np.ndarray, values: np.ndarray, missing: int):
        bits = max(4, int(4 * max(1, len(keys))).bit_length())
        self.shift, self.mask, self.missing = np.uint32(32 - bits), np.uint32((1 << bits) - 1), missing
        self.values = np.full(1 << bits, missing, np.int32)
        self.keys = np.zeros(1 << bits, np.uint32)
        self.used = np.zeros(1 << bits, bool)
        keys, values = keys.astype(np.uint32), values.astype(np.int32)
        slot, todo = self._slot(keys), np.arange(len(keys))
        while len(todo):
            free = todo[~self.used[slot[todo]]]
            at, first = np.unique(slot[free], return_index=True)
            self.keys[at], self.values[at], self.used[at] = keys[free[first]], values[free[first]], True
            todo = todo[self.keys[slot[todo]] != keys[todo]]
            slot[todo] = slot[todo] + np.uint32(1) & self.mask

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return keys * np.uint32(2654435769) >> self.shift

    def find(self, keys: np.ndarray) -> np.ndarray:
        slot = self._slot(keys)
        same = self.keys[slot] == keys
        out = np.where(same, self.values[slot], np.int32(self.missing))
        todo = np.flatnonzero(~same & self.used[slot])
        while len(todo):
            slot_t = slot[todo] + np.uint32(1) & self.mask
            slot[todo] = slot_t
            same = self.keys[slot_t] == keys[todo]
            out[todo[same]] = self.values[slot_t[same]]
            todo = todo[~same & self.used[slot_t]]
        return out


class MergeTable:
    """Vocabulary and merge ranks of a tokenizer file; encodes single words."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.vocab = spec["model"]["vocab"]
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = {i: t for t, i in self.vocab.items()} | {i: t for t, i in self.special.items()}
        ids = self.vocab
        merges = (m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"])
        merges = [(ids[a], ids[b], ids[a + b]) for a, b in merges]
        self.rank_of = {(a, b): rank for rank, (a, b, _) in enumerate(merges)}
        self.merged, self.none = [c for _, _, c in merges], len(merges)
        triples = np.array(merges, np.int64).reshape(-1, 3)
        self._ranks = KeyTable(triples[:, 0] << 16 | triples[:, 1], np.arange(len(merges)), self.none)
        self._merged = triples[:, 2].astype(np.int32)
        letters = byte_letters()
        self.inner = [ids[c] for c in letters]
        self.final = [ids[c + _END] for c in letters]
        self._inner, self._final = np.array(self.inner, np.int32), np.array(self.final, np.int32)
        self.split_special = regex.compile("(" + "|".join(map(regex.escape, self.special)) + ")") if self.special else None

    def word(self, word: str) -> list[int]:
        data = word.encode()
        symbols = [self.inner[b] for b in data[:-1]]
        symbols.append(self.final[data[-1]])
        return self._short(symbols) if len(symbols) <= 24 else self._long(symbols)

    def words(self, data: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of many words, one after another, and how many each word has.

        Words of like length are the rows of a matrix; a round merges the leftmost
        pair of the least rank in every row."""
        n = np.fromiter(map(len, data), np.int64, len(data))
        buf = np.frombuffer(b"".join(data), np.uint8)
        at, count = np.cumsum(n) - n, np.zeros(len(data), np.int64)
        parts: list[tuple[np.ndarray, np.ndarray]] = []
        for low, high in ((1, 6), (7, 10), (11, 14), (15, 24)):
            rows = np.flatnonzero((n >= low) & (n <= high))
            if len(rows):
                symbols, alive = self._rounds(buf, at[rows], n[rows], high)
                count[rows] = alive.sum(axis=1)
                parts.append((rows, symbols[alive]))
        rows = np.flatnonzero(n > 24)
        if len(rows):
            long = [self.word(data[i].decode()) for i in rows.tolist()]
            count[rows] = [len(x) for x in long]
            parts.append((rows, np.array(list(chain.from_iterable(long)), np.int32)))
        start, out = np.cumsum(count) - count, np.zeros(int(count.sum()), np.int32)
        for rows, flat in parts:
            c = count[rows]
            out[np.repeat(start[rows] - (np.cumsum(c) - c), c) + np.arange(int(c.sum()))] = flat
        return out, count

    def _rounds(self, buf: np.ndarray, at: np.ndarray, n: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
        column = np.arange(width)
        letters = buf[np.minimum(at[:, None] + column, len(buf) - 1)]
        last = column == (n - 1)[:, None]
        symbols = np.where(last, self._final[letters], self._inner[letters])
        alive = column < n[:, None]
        after = np.where(last, width, column + 1).astype(np.int32) * np.ones((len(n), 1), np.int32)
        before = (column - 1).astype(np.int32) * np.ones((len(n), 1), np.int32)
        ranks = np.full((len(n), width), self.none, np.int32)
        pairs = alive[:, 1:]
        ranks[:, :-1][pairs] = self._find(symbols[:, :-1][pairs], symbols[:, 1:][pairs])
        rows = np.arange(len(n))
        while len(rows):
            i = ranks[rows].argmin(axis=1)
            best = ranks[rows, i]
            go = best < self.none
            rows, i, best = rows[go], i[go], best[go]
            if not len(rows):
                break
            j = after[rows, i]
            symbols[rows, i] = self._merged[best]
            alive[rows, j] = False
            ranks[rows, j] = self.none
            k = after[rows, j]
            after[rows, i] = k
            more = np.flatnonzero(k < width)
            before[rows[more], k[more]] = i[more]
            ranks[rows, i] = self.none
            ranks[rows[more], i[more]] = self._find(symbols[rows[more], i[more]], symbols[rows[more], k[more]])
            h = before[rows, i]
            less = np.flatnonzero(h >= 0)
            ranks[rows[less], h[less]] = self._find(symbols[rows[less], h[less]], symbols[rows[less], i[less]])
        return symbols, alive

    def _find(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return self._ranks.find(a.astype(np.uint32) << np.uint32(16) | b.astype(np.uint32))

    def _short(self, symbols: list[int]) -> list[int]:
        get, none = self.rank_of.get, self.none
        ranks = [get(pair, none) for pair in zip(symbols, symbols[1:])]  # noqa: B905
        while ranks:
            best = min(ranks)
            if best == none:
                break
            i = ranks.index(best)
            symbols[i : i + 2] = (self.merged[best],)
            del ranks[i]
            if i < len(ranks):
                ranks[i] = get((symbols[i], symbols[i + 1]), none)
            if i:
                ranks[i - 1] = get((symbols[i - 1], symbols[i]), none)
        return symbols

    def _long(self, symbols: list[int]) -> list[int]:
        n, rank_of = len(symbols), self.rank_of
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        queue = [(r, i) for i in range(n - 1) if (r := rank_of.get((symbols[i], symbols[i + 1]))) is not None]
        heapq.heapify(queue)
        while queue:
            rank, i = heapq.heappop(queue)
            j = right[i]
            if symbols[i] < 0 or j >= n or rank_of.get((symbols[i], symbols[j])) != rank:
                continue
            symbols[i], symbols[j] = self.merged[rank], -1
            right[i] = right[j]
            if right[j] < n:
                left[right[j]] = i
            for a in (left[i], i):
                if a >= 0 and (b := right[a]) < n and (r := rank_of.get((symbols[a], symbols[b]))) is not None:
                    heapq.heappush(queue, (r, a))
        return [s for s in symbols if s >= 0]


# --- the automaton -------------------------------------------------------------


def compile_lexicon(entries: dict[bytes, list[int]]) -> dict[str, np.ndarray]:
    """The minimal automaton of the words, as arrays: sorted edge keys
    ``state * 256 + byte``, targets, words passed over, final states, outputs."""
    register: dict[tuple, int] = {}
    states: list[tuple[bool, tuple]] = []

    def settle(node) -> int:
        key = (node[0], tuple(sorted(node[1].items())))
        if key not in register:
            register[key] = len(states)
            states.append(key)
        return register[key]

    root = [False, {}]
    path: list[tuple] = [(0, root)]  # the label that led here, and the node
    before = b""

    def fold(depth: int) -> None:
        while len(path) > depth + 1:
            label, node = path.pop()
            path[-1][1][1][label] = settle(node)

    ordered = sorted(w for w in entries if w)
    for word in ordered:
        same = len(os.path.commonprefix([before, word]))
        fold(same)
        for label in word[same:]:
            path.append((label, [False, {}]))
        path[-1][1][0] = True
        before = word
    fold(0)
    start = settle(root)
    count = [0] * len(states)
    keys, targets, passed = [], [], []
    for s, (final, edges) in enumerate(states):  # children come before their parents
        total = int(final)
        for label, to in edges:
            keys.append(s * 256 + label)
            targets.append(to)
            passed.append(total)
            total += count[to]
        count[s] = total
    outputs = [entries[w] for w in ordered]
    return {
        "start": np.array([start]),
        "keys": np.array(keys, np.int64),
        "targets": np.array(targets, np.int32),
        "passed": np.array(passed, np.int32),
        "final": np.array([f for f, _ in states], bool),
        "bounds": np.concatenate([[0], np.cumsum([len(x) for x in outputs], dtype=np.int64)]).astype(np.int32),
        "ids": np.array(list(chain.from_iterable(outputs)), np.int32),
    }


def packed(arrays: dict[str, np.ndarray]) -> bytes:
    """One file: a JSON head with the place of each array, then the arrays."""
    head, body, at = {}, io.BytesIO(), 0
    for name, a in arrays.items():
        raw = np.ascontiguousarray(a).tobytes()
        raw += b"\0" * (-len(raw) % 8)
        head[name] = (at, str(a.dtype), len(a))
        body.write(raw)
        at += len(raw)
    line = json.dumps(head).encode()
    line += b" " * (-(len(line) + 8) % 8)
    return len(line).to_bytes(8, "little") + line + body.getvalue()


class Lexicon:
    """The memory-mapped automaton."""

    def __init__(self, blob: bytes):
        with tempfile.TemporaryFile() as f:  # the mapping outlives the nameless file
            f.write(blob)
            f.flush()
            mapped = np.memmap(f, np.uint8, "r")
        size = int.from_bytes(mapped[:8].tobytes(), "little")
        head = json.loads(mapped[8 : 8 + size].tobytes())
        for name, (at, kind, n) in head.items():
            at += 8 + size
            setattr(self, name, mapped[at : at + n * np.dtype(kind).itemsize].view(kind))
        self._edge = KeyTable(np.asarray(self.keys), np.arange(len(self.keys)), -1)

    def find(self, data: list[bytes]) -> np.ndarray:
        """The place of each word in the table of outputs, or -1."""
        n = np.fromiter(map(len, data), np.int64, len(data))
        buf = np.frombuffer(b"".join(data), np.uint8)
        at = np.cumsum(n) - n
        state, place = np.full(len(n), int(self.start[0])), np.zeros(len(n), np.int64)
        lanes = np.flatnonzero(n > 0)
        state[n == 0] = -1
        step = 0
        while len(lanes):
            e = self._edge.find((state[lanes] * 256 + buf[at[lanes] + step]).astype(np.uint32))
            ok = e >= 0
            state[lanes[~ok]] = -1
            lanes, e = lanes[ok], e[ok]
            state[lanes] = self.targets[e]
            place[lanes] += self.passed[e]
            step += 1
            lanes = lanes[n[lanes] > step]
        good = state >= 0
        good[good] = self.final[state[good]]
        return np.where(good, place, -1)

    def outputs(self, places: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of the words at ``places``, one after another, and their counts."""
        first = self.bounds[places].astype(np.int64)
        count = self.bounds[places + 1] - first
        return self.ids[np.repeat(first - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))], count


class Encoder:
    """Words to ids: the automaton first, exact merges for the rest."""

    def __init__(self, path: str, blob: bytes | None):
        self.table = MergeTable(path)
        self.lexicon = Lexicon(blob) if blob else None
        self._tables: dict[str, WordTable] = {}
        self._texts: list | None = None

    def ids_table(self) -> WordTable:
        """Words with their ids."""
        if "ids" not in self._tables:
            self._tables["ids"] = WordTable(lambda words: [self._rows(words)], [np.uint32])
        return self._tables["ids"]

    def text_table(self) -> WordTable:
        """Words with the number of their ids, the ids as decimals and the tokens,
        each with a space behind it."""
        if self._texts is None:
            size = max(self.table.tokens) + 1
            self._texts = []
            for texts in ([f"{i} ".encode() for i in range(size)], [f"{self.table.tokens.get(i, '')} ".encode() for i in range(size)]):
                bounds = np.concatenate([[0], np.cumsum([len(x) for x in texts])])
                self._texts.append((np.frombuffer(b"".join(texts), np.uint8), bounds))
            self._tables["text"] = WordTable(self._text_rows, [np.uint16, np.uint8, np.uint8])
        return self._tables["text"]

    def _rows(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        flat, edge = self.flat_ids(words)
        return flat, np.diff(edge)

    def _text_rows(self, words: list[str]) -> list[tuple[np.ndarray, np.ndarray]]:
        flat, edge = self.flat_ids(words)
        out = [(np.diff(edge), np.ones(len(words), np.int64))]
        for data, bounds in self._texts:
            size = bounds[flat + 1] - bounds[flat]
            total = np.concatenate([[0], np.cumsum(size)])
            out.append((data[ragged(bounds[flat], size)], np.diff(total[edge])))
        return out

    def flat_ids(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of the words, one after another, and the bounds of each word."""
        data, special = [w.encode() for w in words], self.table.special
        count = np.zeros(len(words), np.int64)
        parts = []
        rest = np.arange(len(words))
        if self.lexicon is not None:
            places = self.lexicon.find(data)
            hit, rest = np.flatnonzero(places >= 0), np.flatnonzero(places < 0)
            ids, n = self.lexicon.outputs(places[hit])
            count[hit] = n
            parts.append((hit, ids))
        named = [i for i in rest.tolist() if words[i] in special] if any(map(set(words).__contains__, special)) else []
        if named:
            count[named] = 1
            parts.append((np.array(named), np.array([special[words[i]] for i in named], np.int32)))
            rest = np.setdiff1d(rest, named)
        ids, n = self.table.words([data[i] for i in rest.tolist()])
        count[rest] = n
        parts.append((rest, ids))
        start, out = np.cumsum(count) - count, np.zeros(int(count.sum()), np.int32)
        for rows, ids in parts:
            c = count[rows]
            out[np.repeat(start[rows] - (np.cumsum(c) - c), c) + np.arange(int(c.sum()))] = ids
        return out, np.concatenate([[0], np.cumsum(count)])

    def encode_all(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of the texts, one after another, and the bounds of each text."""
        table = self.ids_table()
        number, edge = numbered(table, texts, self.table.split_special)
        flat, count = table.rows[0].take(number)
        return flat, np.concatenate([[0], np.cumsum(count)])[edge]

    def encode(self, text: str) -> list[int]:
        return self.encode_all([text or ""])[0].tolist()

    def decode(self, ids: Iterable[int]) -> str:
        return " ".join(self.table.tokens[i] for i in ids)


_ENCODERS: dict[tuple, Encoder] = {}


def encoder(path: str, blob: bytes | None) -> Encoder:
    """One encoder for each worker process."""
    key = (path, hashlib.sha256(blob).digest() if blob else None)
    if key not in _ENCODERS:
        _ENCODERS.clear()
        _ENCODERS[key] = Encoder(path, blob)
    return _ENCODERS[key]


# --- Spark ----------------------------------------------------------------------


def word_counts(docs: DataFrame, path: str) -> DataFrame:
    """``word, n``: how often each word of at most ``LEXICON_LETTERS`` letters stands in
    all documents, exactly."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        special = MergeTable(path).split_special
        table, seen = WordTable(lambda words: [], []), np.zeros(1 << 16, np.int64)

        def report() -> pa.RecordBatch:
            bounds = table.letters.bounds[: len(table) + 1].tolist()
            text = table.letters.data[: table.letters.used].astype("<u4").tobytes().decode("utf-32-le", "surrogatepass")
            some = [i for i, n in enumerate(seen[: len(table)].tolist()) if n and bounds[i + 1] - bounds[i] <= LEXICON_LETTERS]
            return pa.RecordBatch.from_arrays([pa.array([text[bounds[i] : bounds[i + 1]] for i in some], pa.string()), pa.array(seen[some], pa.int64())], names=["word", "n"])

        for batch in batches:
            for part in slices(batch, "text", CHUNK_BYTES):
                if table.full():
                    yield report()
                    seen[:] = 0
                number, _ = numbered(table, part.column(0).to_pylist(), special)
                if len(table) > len(seen):
                    seen = np.concatenate([seen, np.zeros(2 * len(table) - len(seen), np.int64)])
                seen += np.bincount(number, minlength=len(seen))
        yield report()

    return id_and_text(docs).select("text").mapInArrow(count, "word string, n long").groupBy("word").agg(F.sum("n").alias("n"))


def frequent_words(docs: DataFrame, path: str, limit: int = LEXICON_WORDS) -> DataFrame:
    """``word, n``: the most frequent words over all documents, at most ``limit``: those
    whose count reaches a sixteenth of an octave that not more than ``limit`` reach."""
    counted = saved(word_counts(docs, path))
    level = F.floor(F.log2("n") * 16).cast("int")
    levels = sorted(counted.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("words")).collect(), key=lambda r: -r.level)  # 16 an octave at most
    least, total = None, 0
    for r in levels:
        total += r.words
        if total > limit:
            break
        least = r.level
    return counted.where(level >= least) if least is not None else counted.limit(0)


def build_lexicon(docs: DataFrame | None, path: str, limit: int = LEXICON_WORDS) -> bytes:
    """The packed automaton: the vocabulary's own whole words and the corpus's
    frequent words (``docs`` None: only the former); bounded by ``limit`` each."""
    table = MergeTable(path)
    whole = {t[: -len(_END)] for t in table.vocab if t.endswith(_END)}
    words = {w for w in whole if w.isascii() and w}
    if docs is not None:
        words |= {r.word for r in frequent_words(docs, path, limit).select("word").collect()}
    return packed(compile_lexicon({w.encode(): table.word(w) for w in words if w and w not in table.special}))


def encode_documents(docs: DataFrame, path: str | None = None, lexicon: bytes | None = None) -> DataFrame:
    """``doc_id``, ``ids`` (token ids of the whole text)."""
    path = path or default_tokenizer()
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, shared.value)
        for batch in batches:
            for part in slices(batch, "text", CHUNK_BYTES):
                flat, edge = enc.encode_all(part.column(1).to_pylist())
                ids = pa.ListArray.from_arrays(pa.array(edge, pa.int32()), pa.array(flat.astype(np.int32)))
                yield pa.RecordBatch.from_arrays([part.column(0), ids], names=["doc_id", "ids"])

    return id_and_text(docs).mapInArrow(run, "doc_id long, ids array<int>")


def decode_documents(ids: DataFrame, path: str | None = None) -> DataFrame:
    """``doc_id``, ``text``: the tokens of ``ids`` joined by spaces, as a file
    without a decoder has them; null ids give an empty text."""
    path = path or default_tokenizer()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tokens = encoder(path, None).table.tokens
        for batch in batches:
            texts = [" ".join([tokens[i] for i in row or ()]) for row in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], names=["doc_id", "text"])

    return ids.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("ids").cast("array<int>").alias("ids")).mapInArrow(run, "doc_id long, text string")


def encoding_digests(docs: DataFrame, path: str | None = None, lexicon: bytes | None = None) -> DataFrame:
    """``doc_id, n_tokens, ids_sha256, decoded_sha256``: the ids and the tokens of the
    words are joined as text, as ``decode_documents`` does, and hashed."""
    path = path or default_tokenizer()
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path, shared.value)
        table = enc.text_table()
        for batch in batches:
            for part in slices(batch, "text", CHUNK_BYTES):
                number, edge = numbered(table, part.column(1).to_pylist(), enc.table.split_special)
                each, _ = table.rows[0].take(number)
                columns = [part.column(0), pa.array(np.diff(np.concatenate([[0], np.cumsum(each, dtype=np.int64)])[edge]), pa.int64())]
                for rows in table.rows[1:]:
                    data, size = rows.take(number)
                    data, bounds = memoryview(data), np.concatenate([[0], np.cumsum(size)])[edge].tolist()
                    columns.append(pa.array([hashlib.sha256(data[a : max(a, b - 1)]).hexdigest() for a, b in zip(bounds, bounds[1:], strict=False)], pa.string()))
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return id_and_text(docs).mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op6``: token counts and digests of ids and decoded texts, all documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    path = default_tokenizer()
    return encoding_digests(docs, path, build_lexicon(docs, path))
