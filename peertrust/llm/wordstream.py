"""Texts to numbered words, a block of code points at a time.

The words of a block are found by the class of each code point, hashed by prefix
sums, and looked up all together in a table of the words that this worker has met;
every hit is compared with the stored word, letter by letter.  Words not met
before are encoded together and join the table, which starts afresh when it holds
``TABLE_WORDS`` of them, so its memory doesn't follow the corpus.
"""

from __future__ import annotations

import unicodedata
from collections.abc import Callable, Iterator
from functools import cache

import numpy as np
import regex

from .bytehash import BASE, INVERSE, mix, powers_of

#: Words that the table holds before it starts afresh.
TABLE_WORDS = 1_000_000
#: Code points looked at together.
BLOCK_LETTERS = 1 << 20
#: Longer words are compared and encoded one by one.
LONG_WORD = 64
_OTHER, _SPACE, _LETTER, _NUMBER = range(4)
#: What follows an apostrophe in a word of its own (fixed values).
_SUFFIXES = ("s", "t", "re", "ve", "m", "ll", "d")


@cache
def letter_classes() -> np.ndarray:
    """The class of every code point: letters and numbers as the pattern engine
    has them, and its white space."""
    out = np.zeros(0x110000, np.uint8)
    text = "".join(map(chr, (*range(0xD800), *range(0xE000, 0x40000))))  # none is assigned beyond
    for kind, pattern in ((_SPACE, r"\s"), (_LETTER, r"\p{L}"), (_NUMBER, r"\p{N}")):
        found = "".join(regex.findall(f"{pattern}+", text))
        out[np.frombuffer(found.encode("utf-32-le"), np.uint32)] = kind
    out[0x1C:0x20] = _OTHER  # the engine that wrote the file doesn't count these four as white space
    return out


def code_points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


def cuts(points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where the words of a block start and end; a block begins and ends at white
    space or at an end of the text."""
    n = len(points)
    group = letter_classes()[points]
    opens = np.empty(n, bool)
    opens[0] = True
    np.not_equal(group[1:], group[:-1], out=opens[1:])
    opens |= group == _NUMBER
    quote = np.flatnonzero((points == 39) & opens)
    quote = quote[quote + 1 < n]
    if len(quote):
        first = points[quote + 1]
        second = np.where(quote + 2 < n, points[np.minimum(quote + 2, n - 1)], 0)
        size = np.zeros(len(quote), np.int64)
        for suffix in _SUFFIXES:
            fits = first == ord(suffix[0])
            if len(suffix) == 2:
                fits &= second == ord(suffix[1])
            size[fits] = len(suffix)
        quote, size = quote[size > 0], size[size > 0]
        opens[quote + 1] = False
        after = quote + size + 1
        after = after[after < n]
        opens[after] = True
    start = np.flatnonzero(opens)
    end = np.append(start[1:], n)
    words = group[start] != _SPACE
    return start[words], end[words]


class _Index:
    """Open addressing from a 64-bit hash to a word's number."""

    def __init__(self, bits: int = 16):
        self.bits, self.n = bits, 0
        self.keys, self.values = np.zeros(1 << bits, np.uint64), np.full(1 << bits, -1, np.int32)

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        slot, mask = self._slot(keys), (1 << self.bits) - 1
        out = self.values[slot]
        todo = np.flatnonzero((out >= 0) & (self.keys[slot] != keys))
        at = slot[todo]
        while len(todo):
            at = at + 1 & mask
            out[todo] = self.values[at]
            more = (out[todo] >= 0) & (self.keys[at] != keys[todo])
            todo, at = todo[more], at[more]
        return out

    def add(self, keys: np.ndarray, values: np.ndarray) -> None:
        """``keys`` are distinct and not there yet."""
        if 2 * (self.n + len(keys)) > 1 << self.bits:
            old = self.values >= 0
            bigger = _Index(max(self.bits + 1, int(3 * (self.n + len(keys))).bit_length()))
            bigger._put(self.keys[old], self.values[old])
            self.bits, self.keys, self.values = bigger.bits, bigger.keys, bigger.values
        self._put(keys, values)
        self.n += len(keys)

    def _put(self, keys: np.ndarray, values: np.ndarray) -> None:
        slot, mask, todo = self._slot(keys), (1 << self.bits) - 1, np.arange(len(keys))
        while len(todo):
            free = todo[self.values[slot[todo]] < 0]
            at, first = np.unique(slot[free], return_index=True)
            self.keys[at], self.values[at] = keys[free[first]], values[free[first]]
            placed = np.zeros(len(keys), bool)
            placed[free[first]] = True
            todo = todo[~placed[todo]]
            slot[todo] = slot[todo] + 1 & mask


def ragged(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """``first[i], first[i] + 1, ...`` (``count[i]`` of them), for all ``i`` in turn."""
    before = np.cumsum(count) - count
    return np.repeat(first - before, count) + np.arange(int(count.sum()))


class _Rows:
    """Rows of unlike length, one after another, that can grow."""

    def __init__(self, kind):
        self.data, self.bounds, self.used, self.n = np.zeros(1 << 12, kind), np.zeros(1 << 10, np.int64), 0, 0

    def add(self, flat: np.ndarray, count: np.ndarray) -> None:
        while self.used + len(flat) > len(self.data):
            self.data = np.concatenate([self.data, np.zeros_like(self.data)])
        while self.n + len(count) + 1 > len(self.bounds):
            self.bounds = np.concatenate([self.bounds, np.zeros_like(self.bounds)])
        self.data[self.used : self.used + len(flat)] = flat
        self.bounds[self.n + 1 : self.n + 1 + len(count)] = self.used + np.cumsum(count)
        self.used, self.n = self.used + len(flat), self.n + len(count)

    def count(self, rows: np.ndarray) -> np.ndarray:
        return self.bounds[rows + 1] - self.bounds[rows]

    def take(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The rows one after another, and the size of each."""
        first = self.bounds[rows]
        count = self.bounds[rows + 1] - first
        return self.data[ragged(first, count)], count


def _hashes(points: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    n = len(points)
    prefix = np.zeros(n + 1, np.uint64)
    letters = points.astype(np.uint64)
    letters += np.uint64(0x632BE59BD9B4E019)
    letters *= powers_of(BASE, n + 1)[:n]
    np.cumsum(letters, out=prefix[1:])
    out = prefix[end]
    out -= prefix[start]
    out *= powers_of(INVERSE, n + 1)[start]
    return mix(out)


class WordTable:
    """Numbers for words, and what ``encode`` has made of each.

    ``encode(words)`` gets new words and gives, for every word, its rows: a list of
    ``(flat values, how many each word has)``, one pair for each array in ``kinds``.
    """

    def __init__(self, encode: Callable[[list[str]], list[tuple[np.ndarray, np.ndarray]]], kinds: list):
        self.encode, self.kinds = encode, kinds
        self.clear()

    def clear(self) -> None:
        self.index, self.letters, self.rows = _Index(), _Rows(np.uint32), [_Rows(k) for k in self.kinds]
        self.odd: dict[str, int] = {}  # long words, and those whose hash another word has

    def __len__(self) -> int:
        return self.letters.n

    def full(self) -> bool:
        return len(self) > TABLE_WORDS or self.letters.used > 16 * TABLE_WORDS

    def _learn(self, words: list[str]) -> np.ndarray:
        at = len(self)
        self.letters.add(code_points("".join(words)), np.fromiter(map(len, words), np.int64, len(words)))
        for rows, (flat, count) in zip(self.rows, self.encode(words), strict=True):
            rows.add(flat, count)
        return np.arange(at, len(self))

    def by_name(self, words: list[str]) -> np.ndarray:
        """The numbers of words by a plain dictionary."""
        new = [w for w in dict.fromkeys(words) if w not in self.odd]
        if new:
            self.odd |= zip(new, self._learn(new).tolist(), strict=True)
        return np.array([self.odd[w] for w in words], np.int64)

    def numbers(self, points: np.ndarray, text: str) -> tuple[np.ndarray, np.ndarray]:
        """``start, number`` of every word of a block (``points`` of ``text``)."""
        start, end = cuts(points)
        if not len(start):
            return start, start
        size, key = end - start, _hashes(points, start, end)
        out = self.index.find(key).astype(np.int64)
        short = size <= LONG_WORD
        new = np.flatnonzero((out < 0) & short)
        if len(new):
            keys, first = np.unique(key[new], return_index=True)
            first = new[first]
            made = self._learn([text[a:b] for a, b in zip(start[first].tolist(), end[first].tolist(), strict=True)])
            self.index.add(keys, made.astype(np.int32))
            out[new] = made[np.searchsorted(keys, key[new])]
        rows = np.flatnonzero(short)
        same = np.ones(len(start), bool)
        same[~short] = False
        kept = self.letters.count(out[rows])
        unlike = kept != size[rows]
        same[rows[unlike]] = False
        rows = rows[~unlike]
        stored, count = self.letters.take(out[rows])
        differs = stored != points[ragged(start[rows], count)]
        if differs.any():
            same[rows[np.unique(np.searchsorted(np.cumsum(count), np.flatnonzero(differs), side="right"))]] = False
        odd = np.flatnonzero(~same)
        if len(odd):
            out[odd] = self.by_name([text[a:b] for a, b in zip(start[odd].tolist(), end[odd].tolist(), strict=True)])
        return start, out


_BREAK = regex.compile(r"[\t-\r \x85\xa0]")


def blocks(text: str, limit: int = BLOCK_LETTERS) -> Iterator[str]:
    """The text in blocks of about ``limit`` letters that end before white space."""
    at, n = 0, len(text)
    while n - at > limit and (found := _BREAK.search(text, at + limit)):
        yield text[at : found.start()]
        at = found.start()
    yield text[at:] if at else text


def normal(text: str) -> str:
    """NFC and lower case letter by letter (no rule for a final sigma)."""
    if text.isascii():
        return text.lower()
    if not unicodedata.is_normalized("NFC", text):
        text = unicodedata.normalize("NFC", text)
    return text.replace("Σ", "σ").lower()


def numbered(table: WordTable, texts: list[str], special: regex.Pattern | None = None) -> tuple[np.ndarray, np.ndarray]:
    """The numbers of all words of the texts, one text after another, and where each
    text's words begin (and, at last, end).  ``special`` cuts out words that stand
    for themselves.  Numbers are good until the next call."""
    if table.full():
        table.clear()
    parts, begin, named = [], [], []  # what is joined, where texts begin, (place, special word)
    at = 0
    for text in texts:
        begin.append(at)
        pieces = special.split(text) if special is not None and "<|" in text else (text,)
        for i, piece in enumerate(pieces):
            if i % 2:
                named.append((at, piece))
            else:
                part = normal(piece)
                parts.append(part)
                at += len(part) + 1
    begin.append(at)
    starts, numbers, at = [np.empty(0, np.int64)], [np.empty(0, np.int64)], 0
    joined = "\n".join(parts)
    for block in blocks(joined):
        if block:
            start, number = table.numbers(code_points(block), block)
            starts.append(start + at)
            numbers.append(number)
        at += len(block)
    start, number = np.concatenate(starts), np.concatenate(numbers)
    if named:
        places = np.array([place for place, _ in named], np.int64)
        where = np.searchsorted(start, places)
        number = np.insert(number, where, table.by_name([word for _, word in named]))
        start = np.insert(start, where, places)
    return number, np.searchsorted(start, np.array(begin, np.int64))
