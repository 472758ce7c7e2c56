"""FLAC media columns: encode, verify, decode, and PCM blocks with sample offsets.

``encode_streams`` writes whole FLAC streams (stream info with MD5, a seek table
with a point for each frame, frames of constant, verbatim, fixed-predictor or
linear-predictor subframes with Rice-coded residuals, CRC-8 and CRC-16).
``decode_streams`` reads them back, checking both checksums of every frame.

Both work on many frames at once.  A frame is a lane: step ``t`` decodes sample
``t`` of every frame of a chunk, so a chunk of a few megabytes costs a few hundred
array operations, whatever the number of frames.  ``decode_stream`` is the general
decoder, frame after frame and bit by bit (stereo, any partitioning, escapes,
wasted bits, up to 32 coefficients); lanes with features that the encoder here does
not write go through it too.

Defined results: null texts are empty payloads; the payload is padded with blanks
to a positive multiple of 192 bytes, one byte a sample (minus 128); equal texts
give equal streams.  Broken streams raise ``ValueError``.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import id_and_text, slices, utf8

#: Samples of a frame, payload unit, and the nominal rate of byte streams.
BLOCK, UNIT, RATE = 576, 192, 8000
_LPC_BITS, _LPC_SHIFT = 10, 7


def _crc_table(poly: int, bits: int) -> np.ndarray:
    out = []
    for b in range(256):
        c = b << (bits - 8)
        for _ in range(8):
            c = ((c << 1) ^ poly if c >> (bits - 1) & 1 else c << 1) & ((1 << bits) - 1)
        out.append(c)
    return np.array(out, np.uint16)


CRC8, CRC16 = _crc_table(0x07, 8), _crc_table(0x8005, 16)


def crcs(buf: np.ndarray, start: np.ndarray, n: np.ndarray, bits: int) -> np.ndarray:
    """The CRC of ``buf[start : start + n]`` for every lane."""
    order = np.argsort(-n, kind="stable")
    at, left = start[order], n[order]
    crc = np.zeros(len(at), np.uint16)
    table = CRC8 if bits == 8 else CRC16
    longest = int(left[0]) if len(left) else 0
    live = np.searchsorted(-left, -np.arange(longest), side="left")  # lanes with more than t bytes
    for t in range(longest):
        m = live[t]
        c = crc[:m]
        if bits == 8:
            crc[:m] = table[c ^ buf[at[:m] + t]]
        else:
            crc[:m] = (c << np.uint16(8)) ^ table[(c >> np.uint16(8)) ^ buf[at[:m] + t]]
    out = np.empty_like(crc)
    out[order] = crc
    return out


def _number(k: int) -> bytes:
    """A frame number in the UTF-8 manner, up to 36 bits."""
    if k < 128:
        return bytes([k])
    tail, lead = [], 0x3F
    while k > lead:
        tail.append(0x80 | k & 63)
        k >>= 6
        lead >>= 1
    return bytes([(0xFF ^ (lead << 1 | 1)) & 0xFF | k, *reversed(tail)])


def _heads(numbers: np.ndarray, sizes: np.ndarray) -> list[bytes]:
    """Frame headers without their CRC-8: mono, 8 bits, rate as in the stream info."""
    out = []
    for k, n in zip(numbers.tolist(), sizes.tolist(), strict=True):
        code, extra = (2, b"") if n == BLOCK else (7, (n - 1).to_bytes(2, "big"))
        out.append(b"\xff\xf8" + bytes([code << 4, 1 << 1]) + _number(k) + extra)
    return out


def _put(bits: np.ndarray, at: np.ndarray, value: np.ndarray, width: int) -> None:
    for j in range(width):
        bits[at + j] = value >> (width - 1 - j) & 1


def _per_frame(x: np.ndarray, start: np.ndarray) -> np.ndarray:
    return np.add.reduceat(x, start, dtype=np.int64)


#: Frames that are encoded together: their arrays stay in the processor's cache.
_GROUP = 128


def encode_frames(payload: np.ndarray, start: np.ndarray, size: np.ndarray, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The encoded frames of ``payload[start : start + size]``, which lie one after
    another, and their bounds."""
    parts, heads, sizes = [], [], []
    for i in range(0, len(start), _GROUP):
        g = slice(i, i + _GROUP)
        a, b = start[g][0], start[g][-1] + size[g][-1]
        part, bounds, head_n = _frames_without_checksums(payload[a:b], start[g] - a, size[g], number[g])
        parts.append(part)
        heads.append(head_n)
        sizes.append(np.diff(bounds))
    out, head_n, frame_n = (np.concatenate(x) for x in (parts, heads, sizes))
    bounds = np.concatenate([[0], np.cumsum(frame_n)])
    out[bounds[:-1] + head_n] = crcs(out, bounds[:-1], head_n, 8).astype(np.uint8)
    tail = crcs(out, bounds[:-1], frame_n - 2, 16)
    out[bounds[1:] - 2], out[bounds[1:] - 1] = (tail >> 8).astype(np.uint8), (tail & 255).astype(np.uint8)
    return out, bounds


def _frames_without_checksums(payload: np.ndarray, start: np.ndarray, size: np.ndarray, number: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Frames whose checksums are zero, their bounds, and the lengths of their headers."""
    n_frames = len(start)
    s = payload.astype(np.int32) - 128
    total = len(s)
    within = np.arange(total) - np.repeat(start, size)
    prev1 = np.where(within >= 1, np.concatenate([[0], s[:-1]]), 0).astype(np.int32)
    prev2 = np.where(within >= 2, np.concatenate([[0, 0], s[:-2]])[:total], 0).astype(np.int32)

    # a predictor of two coefficients for each frame, from its autocorrelation
    r0, r1, r2 = (_per_frame(s * p, start).astype(np.float64) for p in (s, prev1, prev2))
    det = r0 * r0 - r1 * r1
    safe = np.where(det > 0, det, 1)
    c1 = np.where(det > 0, (r1 * r0 - r2 * r1) / safe, 0)
    c2 = np.where(det > 0, (r2 * r0 - r1 * r1) / safe, 0)
    limit = (1 << (_LPC_BITS - 1)) - 1
    q1, q2 = (np.clip(np.rint(c * (1 << _LPC_SHIFT)), -limit - 1, limit).astype(np.int32) for c in (c1, c2))
    guess = (np.repeat(q1, size) * prev1 + np.repeat(q2, size) * prev2) >> _LPC_SHIFT

    best_bits = 8 + 8 * size  # verbatim
    kind = np.full(n_frames, 1)  # 0 constant, 1 verbatim, 8 + order fixed, 33 linear of order 2
    param = np.zeros(n_frames, np.int64)
    folded = np.zeros(total, np.int32)
    for order, residual, extra, code in ((0, s, 0, 8), (1, s - prev1, 0, 9), (2, s - 2 * prev1 + prev2, 0, 10), (2, s - guess, 9 + 2 * _LPC_BITS, 33)):
        z = np.where(within >= order, residual << 1 ^ residual >> 31, 0)
        n = size - order
        mean = _per_frame(z, start) / np.maximum(n, 1)
        k = np.clip(np.floor(np.log2(np.maximum(mean * 0.7, 1))), 0, 14).astype(np.int64)
        bits = 8 + 8 * order + extra + 10 + n * (1 + k) + _per_frame(z >> np.repeat(k, size).astype(np.int32), start)
        better = bits < best_bits
        best_bits = np.where(better, bits, best_bits)
        kind, param = np.where(better, code, kind), np.where(better, k, param)
        mask = np.repeat(better, size)
        folded[mask] = z[mask]
    flat = _per_frame((s != np.repeat(s[start], size)).astype(np.int32), start) == 0
    kind, best_bits = np.where(flat, 0, kind), np.where(flat, 16, best_bits)

    heads = _heads(number, size)
    head_n = np.fromiter(map(len, heads), np.int64, n_frames)
    frame_n = head_n + 1 + (best_bits + 7) // 8 + 2
    bounds = np.concatenate([[0], np.cumsum(frame_n)])
    body = 8 * (bounds[:-1] + head_n + 1)  # where the subframe begins, in bits
    bits = np.zeros(8 * int(bounds[-1]), np.uint8)
    _put(bits, body + 1, kind, 6)
    flat_i = np.flatnonzero(kind == 0)
    _put(bits, body[flat_i] + 8, payload[start[flat_i]].astype(np.int64) ^ 128, 8)
    order = np.select([kind == 9, (kind == 10) | (kind == 33)], [1, 2], 0)
    at = body + 8
    for j in range(2):
        i = np.flatnonzero((order > j) & (kind > 1))
        _put(bits, at[i] + 8 * j, payload[start[i] + j].astype(np.int64) ^ 128, 8)
    at = at + 8 * order
    i = np.flatnonzero(kind == 33)
    _put(bits, at[i], np.full(len(i), _LPC_BITS - 1), 4)
    _put(bits, at[i] + 4, np.full(len(i), _LPC_SHIFT), 5)
    _put(bits, at[i] + 9, q1[i].astype(np.int64), _LPC_BITS)
    _put(bits, at[i] + 9 + _LPC_BITS, q2[i].astype(np.int64), _LPC_BITS)
    at[i] += 9 + 2 * _LPC_BITS
    coded = np.flatnonzero(kind > 1)
    _put(bits, at[coded] + 6, param[coded], 4)  # method 0, partition order 0
    at = at + 10
    sample = np.flatnonzero(np.repeat(kind > 1, size) & (within >= np.repeat(order, size)))
    if len(sample):
        frame = np.repeat(np.arange(n_frames), size)[sample]
        z, k = folded[sample].astype(np.int64), param[frame]
        q = z >> k
        width = q + 1 + k
        ends = np.cumsum(width)
        first = np.flatnonzero(np.concatenate([[True], frame[1:] != frame[:-1]]))
        base = np.zeros(n_frames, np.int64)
        base[frame[first]] = ends[first] - width[first]
        pos = at[frame] + (ends - width - base[frame]) + q
        bits[pos] = 1
        for kv in np.unique(k).tolist():
            here = np.flatnonzero(k == kv) if kv else ()
            if len(here):
                _put(bits, pos[here] + 1, z[here], kv)
    out = np.packbits(bits)
    for i in np.flatnonzero(kind == 1).tolist():
        a = body[i] // 8 + 1
        out[a : a + size[i]] = payload[start[i] : start[i] + size[i]] ^ 128
    joined = np.frombuffer(b"".join(heads), np.uint8)
    to = np.repeat(bounds[:-1], head_n) + (np.arange(len(joined)) - np.repeat(np.cumsum(head_n) - head_n, head_n))
    out[to] = joined
    return out, bounds, head_n


def padded(data: bytes) -> bytes:
    """``data`` with blanks up to a positive multiple of 192 bytes."""
    return data + b" " * (UNIT - len(data) if len(data) < UNIT else -len(data) % UNIT)


def encode_streams(payloads: list[bytes]) -> list[bytes]:
    """One whole FLAC stream for each payload (multiples of 192 bytes)."""
    if not payloads:
        return []
    lengths = np.fromiter(map(len, payloads), np.int64, len(payloads))
    per = -(-lengths // BLOCK)
    first = np.cumsum(per) - per
    doc = np.repeat(np.arange(len(payloads)), per)
    number = np.arange(len(doc)) - first[doc]
    offsets = np.cumsum(lengths) - lengths
    start = offsets[doc] + number * BLOCK
    size = np.minimum(BLOCK, lengths[doc] - number * BLOCK)
    frames, bounds = encode_frames(np.frombuffer(b"".join(payloads), np.uint8), start, size, number)
    raw, out = frames.tobytes(), []
    for i, payload in enumerate(payloads):
        a, b = int(first[i]), int(first[i] + per[i])
        edges = bounds[a : b + 1]
        sizes = np.diff(edges)
        signed = (np.frombuffer(payload, np.uint8) ^ 128).tobytes()
        info = (
            BLOCK.to_bytes(2, "big") * 2 + int(sizes.min()).to_bytes(3, "big") + int(sizes.max()).to_bytes(3, "big")
            + (RATE << 44 | 0 << 41 | 7 << 36 | len(payload)).to_bytes(8, "big") + hashlib.md5(signed).digest()
        )
        seek = np.zeros(b - a, np.dtype([("sample", ">u8"), ("offset", ">u8"), ("n", ">u2")]))
        seek["sample"], seek["offset"], seek["n"] = number[a:b] * BLOCK, edges[:-1] - edges[0], size[a:b]
        table = seek.tobytes()
        head = b"fLaC\x00" + len(info).to_bytes(3, "big") + info + b"\x83" + len(table).to_bytes(3, "big") + table
        out.append(head + raw[edges[0] : edges[-1]])
    return out


# --- decoding -------------------------------------------------------------------


def read_metadata(stream: bytes) -> dict:
    """Stream info, seek points, and where the frames begin."""
    if stream[:4] != b"fLaC":
        raise ValueError("not a FLAC stream")
    at, out = 4, {"seek": np.zeros(0, [("sample", ">u8"), ("offset", ">u8"), ("n", ">u2")])}
    last = False
    while not last:
        last, kind, n = bool(stream[at] & 128), stream[at] & 127, int.from_bytes(stream[at + 1 : at + 4], "big")
        block = stream[at + 4 : at + 4 + n]
        if len(block) != n:
            raise ValueError("the metadata are cut off")
        if kind == 0:
            x = int.from_bytes(block[10:18], "big")
            out |= {"block": int.from_bytes(block[2:4], "big"), "rate": x >> 44, "channels": (x >> 41 & 7) + 1, "bits": (x >> 36 & 31) + 1, "samples": x & (1 << 36) - 1, "md5": block[18:34]}
        elif kind == 3:
            seek = np.frombuffer(block, out["seek"].dtype)
            out["seek"] = seek[seek["sample"] != (1 << 64) - 1]
        at += 4 + n
    return out | {"frames": at}


class _Bits:
    def __init__(self, data: bytes, at: int):
        self.data, self.at = data, at * 8

    def take(self, n: int) -> int:
        a, b = self.at >> 3, (self.at + n + 7) >> 3
        if b > len(self.data):
            raise ValueError("the stream is cut off")
        x = int.from_bytes(self.data[a:b], "big") >> (8 * (b - a) - (self.at & 7) - n) & (1 << n) - 1
        self.at += n
        return x

    def signed(self, n: int) -> int:
        x = self.take(n)
        return x - (1 << n) if n and x >> (n - 1) else x

    def unary(self) -> int:
        n = 0
        while not self.take(1):
            n += 1
        return n


def _subframe(r: _Bits, n: int, bits: int) -> list[int]:
    if r.take(1):
        raise ValueError("a subframe begins with a set bit")
    kind, wasted = r.take(6), r.take(1)
    if wasted:
        wasted += r.unary()
        bits -= wasted
    if kind == 0:
        out = [r.signed(bits)] * n
    elif kind == 1:
        out = [r.signed(bits) for _ in range(n)]
    elif 8 <= kind <= 12 or kind >= 32:
        order = kind - 8 if kind < 32 else kind - 31
        out, shift = [r.signed(bits) for _ in range(order)], 0
        if kind < 32:
            weights = ([], [1], [2, -1], [3, -3, 1], [4, -6, 4, -1])[order]
        else:
            precision, shift = r.take(4) + 1, r.signed(5)
            weights = [r.signed(precision) for _ in range(order)]
        wide = 4 + r.take(2)
        if wide > 5:
            raise ValueError("unknown residual coding")
        parts = r.take(4)
        for p in range(1 << parts):
            k = r.take(wide)
            m = (n >> parts) - (order if p == 0 else 0)
            raw = r.take(5) if k == (1 << wide) - 1 else None
            for _ in range(m):
                if raw is None:
                    z = r.unary() << k | r.take(k)
                    e = z >> 1 ^ -(z & 1)
                else:
                    e = r.signed(raw)
                out.append(e + (sum(w * x for w, x in zip(weights, reversed(out), strict=False)) >> shift))  # noqa: B023
    else:
        raise ValueError("reserved subframe")
    return [x << wasted for x in out]


_SIZES = {1: 192, **{i: 576 << (i - 2) for i in range(2, 6)}, **{i: 256 << (i - 8) for i in range(8, 16)}}


def _crc(data: bytes, bits: int) -> int:
    buf = np.frombuffer(data, np.uint8)
    return int(crcs(buf, np.zeros(1, np.int64), np.array([len(buf)]), bits)[0])


def decode_frame(stream: bytes, at: int, info: dict) -> tuple[list[list[int]], int]:
    """The channels of the frame at byte ``at``, and where it ends."""
    r = _Bits(stream, at)
    if r.take(14) != 0x3FFE or r.take(1):
        raise ValueError("no frame begins here")
    r.take(1)
    size, rate, channels, depth = r.take(4), r.take(4), r.take(4), r.take(3)
    r.take(1)
    lead = r.take(8)
    if lead >= 192:  # the leading ones count the bytes of the frame number
        r.take(8 * (8 - (lead ^ 255).bit_length() - 1))
    n = _SIZES.get(size) or (r.take(8 if size == 6 else 16) + 1 if size in (6, 7) else 0)
    if rate in (12, 13, 14):
        r.take(8 if rate == 12 else 16)
    if not n or channels > 10 or rate == 15:
        raise ValueError("reserved frame header")
    end = r.at // 8
    if r.take(8) != _crc(stream[at:end], 8):
        raise ValueError("the header's checksum differs")
    depth = {0: info["bits"], 1: 8, 2: 12, 4: 16, 5: 20, 6: 24, 7: 32}[depth]
    if channels < 8:
        out = [_subframe(r, n, depth) for _ in range(channels + 1)]
    else:
        a = _subframe(r, n, depth + (channels == 9))
        b = _subframe(r, n, depth + (channels != 9))
        if channels == 8:
            out = [a, [x - y for x, y in zip(a, b, strict=True)]]
        elif channels == 9:
            out = [[x + y for x, y in zip(a, b, strict=True)], b]
        else:
            mid = [x << 1 | y & 1 for x, y in zip(a, b, strict=True)]
            out = [[m + y >> 1 for m, y in zip(mid, b, strict=True)], [m - y >> 1 for m, y in zip(mid, b, strict=True)]]
    end = (r.at + 7) // 8
    if int.from_bytes(stream[end : end + 2], "big") != _crc(stream[at:end], 16) or len(stream) < end + 2:
        raise ValueError("the frame's checksum differs")
    return out, end + 2


def decode_stream(stream: bytes) -> list[list[int]]:
    """Channels of any FLAC stream, frame after frame; checks the MD5 of 8-bit ones."""
    info = read_metadata(stream)
    at, out = info["frames"], [[] for _ in range(info["channels"])]
    while at < len(stream) and (not info["samples"] or len(out[0]) < info["samples"]):
        block, at = decode_frame(stream, at, info)
        for channel, more in zip(out, block, strict=True):
            channel += more
    if info["bits"] == 8 and info["channels"] == 1 and any(info["md5"]) and hashlib.md5(np.array(out[0], np.int8).tobytes()).digest() != info["md5"]:
        raise ValueError("the stream's MD5 differs")
    return out


def decode_frames(buf: np.ndarray, start: np.ndarray, end: np.ndarray, size: np.ndarray, number: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Mono 8-bit frames, all at once: samples plus 128, and which lanes hold
    something that only ``decode_frame`` reads (their samples are left zero)."""
    heads = _heads(number, size)
    head_n = np.fromiter(map(len, heads), np.int64, len(heads))
    joined = np.frombuffer(b"".join(heads), np.uint8)
    at = np.repeat(start, head_n) + (np.arange(len(joined)) - np.repeat(np.cumsum(head_n) - head_n, head_n))
    odd = np.zeros(len(start), bool)
    if len(joined):
        np.logical_or.at(odd, np.repeat(np.arange(len(start)), head_n), buf[at] != joined)
    if (crcs(buf, start, head_n, 8) != buf[start + head_n])[~odd].any():
        raise ValueError("a header's checksum differs")
    stored = buf[end - 2].astype(np.uint16) << np.uint16(8) | buf[end - 1]
    if (crcs(buf, start, end - start - 2, 16) != stored).any():
        raise ValueError("a frame's checksum differs")
    padded_buf = np.concatenate([buf, np.zeros(16, np.uint8)])
    window = np.zeros(len(buf) + 8, np.uint64)
    for j in range(8):
        window |= padded_buf[j : j + len(window)].astype(np.uint64) << np.uint64(56 - 8 * j)

    def look(pos: np.ndarray) -> np.ndarray:
        return window[pos >> 3] << (pos & 7).astype(np.uint64)

    def field(pos: np.ndarray, width: int) -> np.ndarray:
        return (look(pos) >> np.uint64(64 - width)).astype(np.int64)

    def signed(pos: np.ndarray, width: int) -> np.ndarray:
        x = field(pos, width)
        return x - ((x >> (width - 1)) << width)

    pos = 8 * (start + head_n + 1)
    kind = field(pos + 1, 6)
    order = np.select([(kind >= 8) & (kind <= 10), kind >= 32], [kind - 8, kind - 31], 0)
    coded = ((kind >= 8) & (kind <= 10)) | (kind == 33)
    after = pos + 8 + 8 * order
    precision, shift = field(after, 4) + 1, signed(after + 4, 5)
    linear = kind == 33
    odd |= (field(pos, 1) == 1) | (field(pos + 7, 1) == 1) | ~(coded | (kind <= 1)) | linear & ((precision != _LPC_BITS) | (shift < 0))
    rice = after + np.where(linear, 9 + 2 * _LPC_BITS, 0)
    k = field(rice + 6, 4)
    odd |= coded & ((field(rice, 6) != 0) | (k == 15))

    offsets = np.cumsum(size) - size
    out = np.zeros(int(size.sum()), np.int32)
    i = np.flatnonzero((kind == 0) & ~odd)
    if len(i):
        where = np.repeat(offsets[i], size[i]) + (np.arange(int(size[i].sum())) - np.repeat(np.cumsum(size[i]) - size[i], size[i]))
        out[where] = np.repeat(signed(pos[i] + 8, 8), size[i])
    for i in np.flatnonzero((kind == 1) & ~odd).tolist():
        a = pos[i] // 8 + 1
        out[offsets[i] : offsets[i] + size[i]] = buf[a : a + size[i]].view(np.int8)
    lanes = np.flatnonzero(coded & ~odd)
    if len(lanes):
        lanes = lanes[np.argsort(-size[lanes], kind="stable")]
        n, o = size[lanes], order[lanes]
        at, kk = rice[lanes] + 10, k[lanes].astype(np.uint64)
        low = np.uint64(64) - np.maximum(kk, np.uint64(1))
        longest = int(n[0])
        live = np.searchsorted(-n, -np.arange(longest), side="left")
        e = np.zeros((longest, len(lanes)), np.int32)
        for t in range(longest):
            m = int(live[t])
            if t < 2:  # the first samples of a predictor are stored as they are
                warm = o[:m] > t
                e[t, :m][warm] = signed(pos[lanes[:m][warm]] + 8 + 8 * t, 8)
                here = np.flatnonzero(~warm)
            else:
                here = slice(0, m)
            p = at[here]
            x = look(p)
            top = (x >> np.uint64(32)).astype(np.float64)
            zeros = 31 - ((top.view(np.int64) >> 52) - 1023)
            if (top == 0).any():  # more than 32 zeros
                zeros = zeros.copy()
                more = np.flatnonzero(top == 0)
                zeros[more] = 0
                while len(more):
                    y = (look(p[more] + zeros[more]) >> np.uint64(32)).astype(np.float64)
                    gone = y == 0
                    zeros[more[gone]] += 32
                    done = more[~gone]
                    zeros[done] += 31 - ((y[~gone].view(np.int64) >> 52) - 1023)
                    more = more[gone]
                    if len(more) and int(zeros[more].max()) > 8 * BLOCK:
                        raise ValueError("a residual has no end")
                x = look(p + zeros + 1)
            else:
                x = x << (zeros + 1).astype(np.uint64)
            kq = kk[here]
            rest = np.where(kq > 0, x >> low[here], np.uint64(0)).astype(np.int64)
            z = zeros << kq.astype(np.int64) | rest
            value = (z >> 1 ^ -(z & 1)).astype(np.int32)
            if t < 2:
                e[t, here] = value
            else:
                e[t, :m] = value
            at[here] = p + zeros + 1 + kq.astype(np.int64)
        kind_l = kind[lanes]
        one = np.flatnonzero(kind_l == 9)
        if len(one):
            e[:, one] = np.cumsum(e[:, one], axis=0)
        two = np.flatnonzero(kind_l == 10)
        if len(two):
            d = e[:, two]
            d[1:2] -= d[0:1]
            e[:, two] = np.cumsum(np.concatenate([d[:1], np.cumsum(d[1:], axis=0)]), axis=0)
        lin = np.flatnonzero(kind_l == 33)
        if len(lin):
            base = after[lanes[lin]] + 9
            w1, w2 = signed(base, _LPC_BITS).astype(np.int32), signed(base + _LPC_BITS, _LPC_BITS).astype(np.int32)
            sh = shift[lanes[lin]].astype(np.int32)
            d = np.ascontiguousarray(e[:, lin])
            for t in range(2, longest):
                d[t] += (w1 * d[t - 1] + w2 * d[t - 2]) >> sh
            e[:, lin] = d
        for length in np.unique(n).tolist():
            group = np.flatnonzero(n == length)
            where = offsets[lanes[group], None] + np.arange(length)[None, :]
            out[where] = e[:length, group].T
    return (out + 128), odd


def decode_streams(streams: list[bytes]) -> list[bytes]:
    """The payloads (samples plus 128) of mono 8-bit streams with a full seek
    table; any other stream, or odd frame, goes to the general decoder."""
    infos = [read_metadata(s) for s in streams]
    out: list[bytes | None] = [None] * len(streams)
    fast = []
    for i, (s, info) in enumerate(zip(streams, infos, strict=True)):
        seek = info["seek"]
        if (info["channels"], info["bits"], info["block"]) == (1, 8, BLOCK) and len(seek) and int(seek["n"].astype(np.int64).sum()) == info["samples"] and len(seek) == -(-info["samples"] // BLOCK):
            fast.append(i)
        else:
            out[i] = (np.array(decode_stream(s)[0], np.int64) + 128).astype(np.uint8).tobytes()
    if fast:
        starts, ends, sizes, numbers, base = [], [], [], [], 0
        for i in fast:
            seek, at = infos[i]["seek"], infos[i]["frames"]
            a = seek["offset"].astype(np.int64) + (base + at)
            starts.append(a)
            ends.append(np.concatenate([a[1:], [base + len(streams[i])]]))
            sizes.append(seek["n"].astype(np.int64))
            numbers.append(np.arange(len(seek)))
            base += len(streams[i])
        start, end, size, number = (np.concatenate(x) for x in (starts, ends, sizes, numbers))
        buf = np.frombuffer(b"".join(streams[i] for i in fast), np.uint8)
        if (start < 0).any() or (end > len(buf)).any() or (end - start < 8).any():
            raise ValueError("the seek table is wrong")
        samples, odd = decode_frames(buf, start, end, size, number)
        if odd.any():
            offsets = np.cumsum(size) - size
            for lane in np.flatnonzero(odd).tolist():
                block, _ = decode_frame(buf[start[lane] : end[lane]].tobytes(), 0, {"bits": 8})
                samples[offsets[lane] : offsets[lane] + size[lane]] = np.array(block[0]) + 128
        raw, at = samples.astype(np.uint8), 0
        for i in fast:
            n = infos[i]["samples"]
            payload = raw[at : at + n]
            if hashlib.md5((payload ^ 128).tobytes()).digest() != infos[i]["md5"]:
                raise ValueError("the stream's MD5 differs")
            out[i] = payload.tobytes()
            at += n
    return out


def features(payloads: list[bytes]) -> list[str]:
    """``peak``, ``energy``, ``zero`` crossings and ``mean`` of each payload's
    samples, as whole numbers."""
    if not payloads:
        return []
    n = np.fromiter(map(len, payloads), np.int64, len(payloads))
    start = np.cumsum(n) - n
    s = np.frombuffer(b"".join(payloads), np.uint8).astype(np.int32) - 128
    negative = s < 0
    crossing = np.zeros(len(s), np.int32)
    crossing[1:] = negative[1:] != negative[:-1]
    crossing[start] = 0
    peak = np.maximum.reduceat(np.abs(s), start)
    energy, zero, mean = _per_frame(s * s, start), _per_frame(crossing, start), _per_frame(s, start) // n
    return [f"peak={a};energy={b};zero={c};mean={d}" for a, b, c, d in zip(peak.tolist(), energy.tolist(), zero.tolist(), mean.tolist(), strict=True)]


# --- Spark ----------------------------------------------------------------------


def encode_documents(docs: DataFrame) -> DataFrame:
    """``doc_id, n_bytes, media``: every whole text as a FLAC stream."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text", 2 << 20):
                raw = [t.encode() for t in part.column(1).to_pylist()]
                media = encode_streams([padded(t) for t in raw])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(t) for t in raw], pa.int64()), pa.array(media, pa.binary())], names=["doc_id", "n_bytes", "media"])

    return id_and_text(docs).mapInArrow(run, "doc_id long, n_bytes long, media binary")


def pcm_blocks(media: DataFrame, id_column: str = "doc_id", column: str = "media") -> DataFrame:
    """One row per frame of each stream: ``first_sample`` and ``n_samples``, the
    frame's byte ``offset`` behind the metadata, and its ``pcm`` (signed 8-bit).
    Null streams give no rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = [(i, s) for i, s in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True) if s is not None]
            rows = []
            for (i, stream), payload in zip(keep, decode_streams([s for _, s in keep]), strict=True):
                pcm = (np.frombuffer(payload, np.uint8) ^ 128).tobytes()
                seek = read_metadata(stream)["seek"]
                for k, (first, offset, n) in enumerate(seek.tolist() or [(0, 0, len(pcm))]):
                    rows.append((i, k, first, n, offset, pcm[first : first + n]))
            cols = list(zip(*rows, strict=True)) or [()] * 6
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["doc_id", "block", "first_sample", "n_samples", "offset", "pcm"])

    source = media.select(F.col(id_column).cast("long").alias("doc_id"), F.col(column).cast("binary").alias("media"))
    return source.mapInArrow(run, "doc_id long, block int, first_sample long, n_samples int, offset long, pcm binary")


def media_digests(docs: DataFrame) -> DataFrame:
    """The streams are written, read back from their bytes, verified and digested
    in one pass; nothing is shuffled and no stream outlives its chunk."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text", 2 << 20):
                data, offsets = utf8(part.column(1))
                raw, edges = data.tobytes(), offsets.tolist()
                texts = [raw[a:b] for a, b in zip(edges, edges[1:], strict=False)]
                media = encode_streams([padded(t) for t in texts])
                payload = decode_streams(media)
                columns = {
                    "n_bytes": pa.array([len(t) for t in texts], pa.int64()),
                    "payload_bytes": pa.array([len(p) for p in payload], pa.int64()),
                    "payload_sha256": pa.array([hashlib.sha256(p).hexdigest() for p in payload], pa.string()),
                    "tail_crc32": pa.array([zlib.crc32(p[-16:]) for p in payload], pa.int64()),
                    "media_bytes": pa.array([len(m) for m in media], pa.int64()),
                    "media_sha256": pa.array([hashlib.sha256(m).hexdigest() for m in media], pa.string()),
                    "feature": pa.array(features(payload), pa.string()),
                }
                yield pa.RecordBatch.from_arrays([part.column(0), *columns.values()], names=["doc_id", *columns])

    return id_and_text(docs).mapInArrow(
        run, "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op9``: all documents as FLAC streams, read back."""
    return media_digests(spark.read.parquet(f"{sf_dir}/documents.parquet"))
