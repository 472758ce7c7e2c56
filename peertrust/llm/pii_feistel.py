"""Format-preserving pseudonyms for personal data, by keyed Feistel permutations.

Found values are validated first, then permuted inside their own format: card
numbers (Luhn) become other numbers with a right check digit, phone numbers keep
their country prefix and punctuation, addresses of hosts stay valid octets, dates
become other dates in the same notation, and e-mail names, the labels of their hosts
(but the last) and hexadecimal secrets keep their length and alphabet.  The permutation
depends on the key, the kind and the format alone: equal values get equal pseudonyms in
every document, different values get different ones, and the holder of the key can
undo it.

Values of up to ``SHORT_WORD`` letters are permuted as one number; in longer ones the
halves are strings, to which each round adds a keyed stream letter by letter, so the
time follows the length.

Each text is handled by itself: no shuffle, and no state between rows.

Defined results: a null text stays null (no spans); texts without personal data
come back unchanged; candidates that fail their validation stay as they are; e-mail
addresses come back in lower case.
"""

from __future__ import annotations

import calendar
import datetime as dt
import hashlib
import hmac
import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DEMO_KEY = b"peertrust demonstration key"
ROUNDS = 8
#: Letters of a value that is permuted as a number.
SHORT_WORD = 64
_DIGITS = "0123456789"
_HEX = "0123456789abcdef"
_NAME = "abcdefghijklmnopqrstuvwxyz0123456789"
#: First and last day that dates are permuted among.
_FIRST, _LAST = dt.date(1900, 1, 1), dt.date(2099, 12, 31)

#: One alternative for each kind; the longest kinds first (fixed values).
PATTERN = re.compile(
    r"(?P<email>(?<![\w.+-])[A-Za-z0-9][\w.+-]*@[A-Za-z0-9][A-Za-z0-9-]*(?:\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,})"
    r"|(?P<secret>(?<![0-9A-Za-z])(?=[0-9a-fA-F]*[0-9])(?=[0-9a-fA-F]*[a-fA-F])[0-9a-fA-F]{32,64}(?![0-9A-Za-z]))"
    r"|(?P<ip>(?<![\w.])(?:[0-9]{1,3}\.){3}[0-9]{1,3}(?![\w]|\.[0-9]))"
    r"|(?P<date>(?<![\w-])(?:[0-9]{4}-[0-9]{2}-[0-9]{2}|[0-9]{1,2}/[0-9]{1,2}/[0-9]{4}|[0-9]{1,2}\.[0-9]{1,2}\.[0-9]{4})(?![\w-]))"
    r"|(?P<phone>(?<![\w+])\+[0-9]{1,3}[ -]?\(?[0-9]{2,4}\)?[ -]?[0-9]{3,4}[ -]?[0-9]{3,4}(?!\w))"
    r"|(?P<ssn>(?<![\w-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-]))"
    r"|(?P<card>(?<![\w.-])[0-9](?:[ -]?[0-9]){12,18}(?![\w-]))"
)
#: A text without any of these holds nothing to find.
_HINT = re.compile(r"[0-9]")
KINDS = ("email", "secret", "ip", "date", "phone", "ssn", "card")


def luhn_digit(digits: str) -> str:
    """The digit that makes ``digits`` plus it valid."""
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = int(c) * (2 if i % 2 == 0 else 1)
        total += d - 9 if d > 9 else d
    return str(-total % 10)


class Feistel:
    """A keyed permutation of the numbers below ``size``: an alternating Feistel
    network over two parts of the range, walked until it lands inside."""

    def __init__(self, key: bytes, tweak: str, size: int):
        self.size = size
        width = max(2, (size - 1).bit_length())
        self.a, self.b = width - width // 2, width // 2
        self.key = hmac.new(key, f"{tweak}|{size}".encode(), hashlib.sha256).digest()

    def _round(self, i: int, half: int, bits: int) -> int:
        data = i.to_bytes(1, "big") + half.to_bytes(max(self.a, self.b) // 8 + 1, "big")
        seed = hashlib.blake2b(data, key=self.key, digest_size=64).digest()
        out = seed if bits <= 512 else hashlib.shake_256(seed).digest(bits // 8 + 1)
        return int.from_bytes(out, "big") & ((1 << bits) - 1)

    def _once(self, x: int, back: bool) -> int:
        left, right = x >> self.b, x & ((1 << self.b) - 1)
        for i in range(ROUNDS - 1, -1, -1) if back else range(ROUNDS):
            if i % 2:
                right ^= self._round(i, left, self.b)
            else:
                left ^= self._round(i, right, self.a)
        return left << self.b | right

    def permute(self, x: int, back: bool = False) -> int:
        if self.size < 2:
            return x
        y = self._once(x, back)
        while y >= self.size:
            y = self._once(y, back)
        return y


def permute_digits(key: bytes, digits: np.ndarray, base: int, back: bool = False) -> np.ndarray:
    """A keyed permutation of the strings of as many digits below ``base``: an
    alternating Feistel network whose rounds add a stream, digit by digit."""
    half = len(digits) // 2
    parts = [digits[:half].astype(np.int64), digits[half:].astype(np.int64)]
    for i in range(ROUNDS - 1, -1, -1) if back else range(ROUNDS):
        to, by = parts[i % 2], parts[1 - i % 2]
        seed = hashlib.blake2b(i.to_bytes(1, "big") + by.astype(np.uint8).tobytes(), key=key, digest_size=64).digest()
        stream = np.frombuffer(hashlib.shake_256(seed).digest(4 * len(to)), "<u4").astype(np.int64)
        parts[i % 2] = (to - stream if back else to + stream) % base
    return np.concatenate(parts)


class Pseudonymizer:
    """Finds and replaces personal data; ``back`` undoes it."""

    def __init__(self, key: bytes, back: bool = False):
        self.key, self.back = key, back
        self._feistel: dict[tuple[str, int], Feistel] = {}

    def _permute(self, tweak: str, x: int, size: int) -> int:
        f = self._feistel.get((tweak, size))
        if f is None:
            f = self._feistel[tweak, size] = Feistel(self.key, tweak, size)
        return f.permute(x, self.back)

    def _word(self, tweak: str, word: str, alphabet: str) -> str:
        """A word over ``alphabet`` to one as long, in lower case."""
        if len(word) > SHORT_WORD:
            place = np.zeros(256, np.uint8)
            place[np.frombuffer(alphabet.encode(), np.uint8)] = np.arange(len(alphabet))
            key = hmac.new(self.key, f"{tweak}|{len(word)}|long".encode(), hashlib.sha256).digest()
            new = permute_digits(key, place[np.frombuffer(word.lower().encode(), np.uint8)], len(alphabet), self.back)
            return np.frombuffer(alphabet.encode(), np.uint8)[new].tobytes().decode()
        base, x = len(alphabet), 0
        for c in word.lower():
            x = x * base + alphabet.index(c)
        x, out = self._permute(f"{tweak}|{len(word)}", x, base ** len(word)), []
        for _ in word:
            x, d = divmod(x, base)
            out.append(alphabet[d])
        return "".join(out)[::-1]

    def _digits(self, tweak: str, value: str, keep: int = 0) -> str:
        """The digits of ``value`` after the first ``keep``; the rest stays."""
        at = [i for i, c in enumerate(value) if c in _DIGITS][keep:]
        new = iter(self._word(tweak, "".join(value[i] for i in at), _DIGITS))
        out = list(value)
        for i in at:
            out[i] = next(new)
        return "".join(out)

    def _letters(self, tweak: str, v: str) -> str:
        """The letters and digits of ``v`` permuted, in lower case; the rest stays."""
        shape = "".join("x" if c.lower() in _NAME else c for c in v)
        new = iter(self._word(f"{tweak}|{shape}", "".join(c.lower() for c in v if c.lower() in _NAME), _NAME))
        return "".join(next(new) if c == "x" else c for c in shape)

    def email(self, v: str) -> str | None:
        name, _, host = v.rpartition("@")
        *labels, last = host.split(".")
        return "@".join([self._letters("email", name), ".".join([*(self._letters("host", x) for x in labels), last.lower()])])

    def secret(self, v: str) -> str | None:
        new = self._word("secret", v, _HEX)
        return new.upper() if v.isupper() else new

    def ip(self, v: str) -> str | None:
        parts = v.split(".")
        if any(int(p) > 255 or (len(p) > 1 and p[0] == "0") for p in parts):
            return None
        x = self._permute("ip", int.from_bytes(bytes(map(int, parts)), "big"), 1 << 32)
        return ".".join(map(str, x.to_bytes(4, "big")))

    def date(self, v: str) -> str | None:
        sep = next(c for c in v if c not in _DIGITS)
        a, b, c = v.split(sep)
        y, m, d = (a, b, c) if sep == "-" else (c, a, b) if sep == "/" else (c, b, a)
        y, m, d = int(y), int(m), int(d)
        if not (_FIRST.year <= y <= _LAST.year and 1 <= m <= 12 and 1 <= d <= calendar.monthrange(y, m)[1]):
            return None
        padded = sep == "-" or len(a) == len(b) == 2
        if not padded and (a[0] == "0" or b[0] == "0"):
            return None  # a mixed notation is no date format
        size, x = (_LAST - _FIRST).days + 1, (dt.date(y, m, d) - _FIRST).days
        while True:
            x = self._permute(f"date|{sep}|{padded}", x, size)
            day = _FIRST + dt.timedelta(x)
            if padded or day.month < 10 or day.day < 10:  # else it would read as a padded date
                break
        pad = "02d" if padded else "d"
        y, m, d = (format(day.year, "04d"), format(day.month, pad), format(day.day, pad))
        return sep.join((y, m, d) if sep == "-" else (m, d, y) if sep == "/" else (d, m, y))

    def phone(self, v: str) -> str | None:
        country = re.match(r"\+([0-9]{1,3})", v)[1]
        shape = re.sub("[0-9]", "0", v)
        n = sum(c in _DIGITS for c in v)
        return self._digits(f"phone|{country}|{shape}", v, len(country)) if 8 <= n <= 15 else None

    def ssn(self, v: str) -> str | None:
        def valid(x: str) -> bool:
            return x[:3] not in ("000", "666") and x[0] != "9" and x[4:6] != "00" and x[7:] != "0000"

        if not valid(v):
            return None
        while not valid(v := self._digits("ssn", v)):
            pass
        return v

    def card(self, v: str) -> str | None:
        digits = re.sub("[ -]", "", v)
        if luhn_digit(digits[:-1]) != digits[-1] or len(set(digits)) == 1:
            return None
        while True:
            body = self._word("card", digits[:-1], _DIGITS)
            digits = body + luhn_digit(body)
            if len(set(digits)) > 1:
                break
        new = iter(digits)
        return "".join(next(new) if c in _DIGITS else c for c in v)

    def replace(self, text: str | None) -> tuple[str | None, list[tuple[str, int, int]]]:
        """The text with pseudonyms, and ``kind, start, end`` of each in it."""
        if text is None or not (_HINT.search(text) or "@" in text):
            return text, []
        out, spans, at, shift = [], [], 0, 0
        for m in PATTERN.finditer(text):
            new = getattr(self, m.lastgroup)(m[0])
            if new is None:
                continue
            out += (text[at : m.start()], new)
            at = m.end()
            spans.append((m.lastgroup, m.start() + shift, m.start() + shift + len(new)))
            shift += len(new) - len(m[0])
        if not spans:
            return text, []
        out.append(text[at:])
        return "".join(out), spans


def pseudonymize(docs: DataFrame, key: bytes = DEMO_KEY, back: bool = False) -> DataFrame:
    """``doc_id, text, n_<kind>..., spans``: one row per row of ``docs``."""
    spans_type = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = Pseudonymizer(key, back)
        for batch in batches:
            done = [p.replace(t) for t in batch.column(1).to_pylist()]
            counts = [pa.array([sum(s[0] == k for s in spans) for _, spans in done], pa.int32()) for k in KINDS]
            spans = [[{"kind": k, "start": a, "end": b} for k, a, b in s] for _, s in done]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([t for t, _ in done], pa.string()), *counts, pa.array(spans, spans_type)],
                names=["doc_id", "text", *(f"n_{k}" for k in KINDS), "spans"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, f"doc_id long, text string, {', '.join(f'n_{k} int' for k in KINDS)}, spans array<struct<kind:string,start:int,end:int>>")


def pseudonymize_documents(docs: DataFrame, key: bytes = DEMO_KEY) -> DataFrame:
    """``docs`` with its own columns and pseudonyms in ``text``."""

    @F.pandas_udf("string")
    def replaced(text: pd.Series) -> pd.Series:
        p = Pseudonymizer(key)
        return text.map(lambda t: p.replace(t)[0])

    out = docs.withColumn("text", replaced(F.col("text").cast("string")))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.length("text").cast("long"))
    return out


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op7``: pseudonyms in all documents."""
    out = pseudonymize(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.withColumn("spans", F.to_json("spans"))
