"""Polynomial hashes of byte ranges, for whole chunks of text at once.

``P[i]`` is the sum of ``T[b_j] * B**j`` over the first ``i`` bytes, modulo 2**64;
a range's hash is the difference of two prefixes, divided by the power of its
start, so it depends on the bytes alone.  Equal hashes are candidates; whoever
needs certainty compares the bytes.
"""

from __future__ import annotations

import numpy as np

BASE = 0x9E3779B97F4A7C15 | 1
INVERSE = pow(BASE, -1, 1 << 64)
#: A fixed random word for each byte value.
LETTERS = np.random.Generator(np.random.PCG64(20_240_501)).integers(0, 1 << 64, 256, dtype=np.uint64)
_powers: dict[int, np.ndarray] = {}


def powers_of(base: int, n: int) -> np.ndarray:
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(n, 1 << 16)
        steps = np.full(size, base, np.uint64)
        steps[0] = 1
        have = _powers[base] = np.cumprod(steps, dtype=np.uint64)
    return have


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads the bits of 64-bit words (low bits of a polynomial hash are weak)."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class HashedBytes:
    """A buffer with its prefix hashes; another ``seed``, other hashes."""

    def __init__(self, buf: np.ndarray, seed: int = 0):
        n = len(buf)
        base = (BASE + 2 * seed) % (1 << 64)
        self.buf = buf
        self.prefix = np.zeros(n + 1, np.uint64)
        np.cumsum(LETTERS[buf] * powers_of(base, n + 1)[:n], out=self.prefix[1:])
        self.inverse = powers_of(pow(base, -1, 1 << 64) if seed else INVERSE, n + 1)

    def ranges(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """The hash of each ``buf[start:end]`` (not mixed)."""
        return (self.prefix[end] - self.prefix[start]) * self.inverse[start]

    def grams(self, k: int) -> np.ndarray:
        """The mixed hash of every run of ``k`` bytes."""
        n = len(self.buf) - k + 1
        if n <= 0:
            return np.empty(0, np.uint64)
        return mix((self.prefix[k:] - self.prefix[:n]) * self.inverse[:n])

    def common(self, a: np.ndarray, b: np.ndarray, limit: int) -> np.ndarray:
        """How many bytes the suffixes at ``a`` and ``b`` share, up to ``limit``
        (both must reach that far): a binary search over range hashes."""
        length = np.zeros(len(a), np.int64)
        step = 1 << (limit.bit_length() - 1)
        while step:
            ok = np.flatnonzero(length + step <= limit)
            x, y = a[ok] + length[ok], b[ok] + length[ok]
            same = self.ranges(x, x + step) == self.ranges(y, y + step)
            length[ok[same]] += step
            step >>= 1
        return length


def merge_sorted_suffixes(text: HashedBytes, suffix: np.ndarray, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """The order of the suffixes by their first ``limit`` bytes (ties by place in
    ``suffix``), and the bytes that each shares with the one before it.

    A mergesort whose comparisons are binary searches for the common extension.
    Runs are opened by the first eight bytes; all runs are merged level by level,
    every element finding its rank in the neighbouring run by binary search, all
    of them in step.
    """
    n = len(suffix)
    if not n:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    head = np.zeros(n, np.uint64)
    for j in range(min(8, limit)):
        head = head << np.uint64(8) | text.buf[suffix + j].astype(np.uint64)
    order = np.argsort(head, kind="stable")
    sorted_head = head[order]
    opens = np.concatenate([[True], sorted_head[1:] != sorted_head[:-1]])
    begin = np.flatnonzero(opens)
    run_n = np.diff(np.concatenate([begin, [n]]))
    run_of = np.cumsum(opens) - 1
    width, widest = 1, int(run_n.max())

    def after(x: np.ndarray, y: np.ndarray, tie: np.ndarray) -> np.ndarray:
        """Whether suffix ``y`` comes before ``x`` (``tie`` where they are equal)."""
        shared = text.common(x, y, limit)
        end = shared >= limit
        at = np.minimum(shared, limit - 1)
        return np.where(end, tie, text.buf[y + at] < text.buf[x + at])

    while width < widest:
        lanes = np.flatnonzero((run_n > width)[run_of])
        base, size = begin[run_of[lanes]], run_n[run_of[lanes]]
        within = lanes - base
        block = within // width
        left = block % 2 == 0
        other = np.where(left, block + 1, block - 1) * width
        lo = np.minimum(other, size)
        first = lo.copy()
        hi = np.minimum(other + width, size)
        mine = suffix[order[lanes]]
        live = np.flatnonzero(lo < hi)
        while len(live):
            mid = (lo[live] + hi[live]) >> 1
            y = suffix[order[base[live] + mid]]
            before = after(mine[live], y, ~left[live])
            lo[live[before]] = mid[before] + 1
            hi[live[~before]] = mid[~before]
            live = live[lo[live] < hi[live]]
        place = base + (block // 2 * 2 * width) + (within - block * width) + (lo - first)
        new = order.copy()
        new[place] = order[lanes]
        order = new
        width *= 2
    shared = np.zeros(n, np.int64)
    if n > 1:
        shared[1:] = text.common(suffix[order[1:]], suffix[order[:-1]], limit)
    return order, shared
