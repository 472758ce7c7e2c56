"""Hashed words and word runs of many texts at once, on their UTF-8 bytes.

Letters are ASCII letters, digits, ``_`` and every byte from 128 on; ASCII and
Latin-1 capitals are lowered.  Words never cross texts.
"""

from __future__ import annotations

import numpy as np

from .bytehash import HashedBytes, mix

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_WORD = np.zeros(256, np.uint8)
_WORD[[*range(48, 58), *range(65, 91), 95, *range(97, 123), *range(128, 256)]] = 1
_SPACE = [9, 10, 11, 12, 13, 28, 29, 30, 31, 32]
#: 0: white space, 1: letters, 2: anything else.
_WORDPUNCT = np.where(_WORD == 1, 1, 2).astype(np.uint8)
_WORDPUNCT[_SPACE] = 0
#: 0: white space, 1: anything else.
_FIELDS = (_WORDPUNCT > 0).astype(np.uint8)
CLASSES = {"wordpunct": _WORDPUNCT, "fields": _FIELDS, "words": _WORD}


def lowered(buf: np.ndarray) -> np.ndarray:
    out = _LOWER[buf]
    if len(buf) > 1:
        capital = np.flatnonzero((buf[:-1] == 0xC3) & (buf[1:] >= 0x80) & (buf[1:] <= 0x9E) & (buf[1:] != 0x97)) + 1
        out[capital] += 32
    return out


def tokens(buf: np.ndarray, offsets: np.ndarray, kind: str, prefix: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """``text number, hash`` of every token, in order; with ``prefix``, behind them
    those of the first ``prefix`` bytes of every longer token."""
    n = len(buf)
    if not n:
        return np.empty(0, np.int64), np.empty(0, np.uint64)
    buf = lowered(buf)
    group = CLASSES[kind][buf]
    cut = np.zeros(n + 1, bool)
    cut[offsets] = True
    cut[1:n] |= group[1:] != group[:-1]
    cut[0] = cut[n] = True
    start = np.flatnonzero(cut[:n] & (group > 0))
    end = np.flatnonzero(cut[1:] & (group > 0)) + 1
    text, hashed = np.searchsorted(offsets, start, side="right") - 1, HashedBytes(buf)
    whole = mix(hashed.ranges(start, end))
    if not prefix:
        return text, whole
    long = np.flatnonzero(end - start > prefix)
    heads = mix(~hashed.ranges(start[long], start[long] + prefix))
    return np.concatenate([text, text[long]]), np.concatenate([whole, heads])


def runs(text: np.ndarray, hashes: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """``text number, hash`` of every run of ``k`` tokens of one text; a text with
    fewer tokens, but any, gives the run of all it has."""
    n = len(hashes)
    if not n:
        return text, hashes
    salted = [mix(hashes + np.uint64(0x51ED270B7F4A7C15 * (j + 1) & (1 << 64) - 1)) for j in range(k)]
    out = np.zeros(n, np.uint64)
    for j in range(min(k, n)):
        same = text[j:] == text[: n - j]
        out[: n - j] += np.where(same, salted[j][j:], np.uint64(0))
    edge = np.concatenate([[0], np.flatnonzero(text[1:] != text[:-1]) + 1, [n]])
    size = np.diff(edge)
    last = np.repeat(edge[:-1] + np.maximum(size - k, 0), size)
    keep = np.arange(n) <= last
    return text[keep], mix(out[keep])
