"""Substring dedup by a distributed, hash-compared suffix sort.

Removes every byte that lies in a string of ``LENGTH`` bytes which also starts in
a document with a smaller id.

A suffix sort of the whole corpus would move each suffix.  Here only anchors move.
Every window of ``LENGTH`` bytes names the least of its hashed ``GRAM``-byte grams
as its anchor; equal windows name equal anchors, and neighbouring windows mostly
share one, so there is about one anchor in sixteen bytes.  The windows of one
anchor form a segment.

1.  Each chunk of text sends, for each anchor, the gram's hash, the segment's hash
    and its place, packed into one binary row for each bucket of gram hashes.
    Within the chunk, equal segments go out once, and their later documents are
    marked as covered right there, after a comparison of the bytes; so a passage that
    a third of the corpus repeats costs one entry a chunk.
2.  A bucket groups its entries by gram.  Equal segments (48 bits of the gram's hash
    and 48 of the segment's): all but those of the smallest document are covered.  A
    gram with unlike segments may still share windows among them; one set of
    occurrences for each unlike segment goes on.
3.  Those segments fetch their bytes and meet again, by gram, in a suffix sort:
    prefix polynomial hashes and binary search give common extensions, a mergesort
    compares suffixes with them, and runs of suffixes with ``LENGTH`` common bytes
    are verified byte by byte.  Windows outside the smallest document of a run are
    covered.  A gram with more than ``HOT_SEGMENTS`` unlike segments is parted first:
    windows that reach far to its left meet by the bytes left of it, the others by
    those to its right.
4.  What step 2 has covered by hash alone is verified.  Equal segments are the nodes
    of a binary tree below the smallest one, so no document is asked for more than two
    others a segment.  Neighbouring segments of two documents make one range; the
    parent's side sends a 128-bit cryptographic digest of its bytes, which must be that
    of the child's bytes for the range to be covered.  If it isn't, two strings with equal hashes were met, and the
    job ends with an error instead of a wrong result; with another ``seed`` the hashes
    are others.
5.  Covered ranges return to their documents, are united and cut out.

Buckets are numbered by size of the input, so their memory doesn't grow with it, but
for the entries (some 30 bytes each) of one gram, which meet in one task.

Defined results: null texts are empty; texts shorter than ``LENGTH`` lose nothing; a
text is cut into pieces that overlap, so only itself has to fit in memory; rows that
repeat a ``doc_id`` neither cover one another nor are told apart otherwise: equal ones
get equal results, unlike texts of one id lose each their own bytes; rows without
``doc_id`` neither lose nor cover anything.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .bytehash import HashedBytes, merge_sorted_suffixes, mix
from .common import id_and_text, saved, slices, text_or_empty, utf8
from .wordstream import ragged

LENGTH = 50
GRAM = 16
#: Unlike segments of a gram from which its windows meet by their further bytes.
HOT_SEGMENTS = 4_096
#: Text bytes behind one bucket of grams, and of one group of documents.
BUCKET_BYTES, GROUP_BYTES = 8 << 20, 4 << 20
_PLACE_BITS = 28
#: Kinds of rows: segments and their bytes; covered ranges; segments to be sorted; ranges
#: to be verified; segments of a hot gram to be sorted.
_SEGMENTS, _COVERED, _WANTED, _CLAIMED, _HOT = range(5)
#: ``to``: the group that a row goes to next; ``then``: the one after that.
_BLOB = "to int, kind int, then int, blob binary"
_CHUNK = 2 << 20


@dataclass(frozen=True)
class Plan:
    """What the tasks have to know."""

    length: int = LENGTH
    gram: int = GRAM
    buckets: int = 16
    sorts: int = 64
    groups: int = 17
    hot: int = HOT_SEGMENTS
    chunk: int = _CHUNK
    seed: int = 0
    #: Bits of a segment's hash that are compared (up to 48) before its bytes are.
    bits: int = 48


# --- packing of number columns into binary rows ------------------------------------


def _planes(a: np.ndarray) -> bytes:
    """16-bit planes of numbers: planes of equal high parts compress to nothing."""
    a = np.ascontiguousarray(a)
    if a.dtype.itemsize <= 2:
        return a.tobytes()
    return np.ascontiguousarray(a.view(np.uint16).reshape(len(a), -1).T).tobytes()


def _from_planes(data: memoryview, kind: str, n: int) -> np.ndarray:
    dtype = np.dtype(kind)
    if dtype.itemsize <= 2:
        return np.frombuffer(data, dtype, n)
    planes = np.frombuffer(data, np.uint16, n * dtype.itemsize // 2).reshape(-1, n)
    return np.ascontiguousarray(planes.T).view(dtype).reshape(n)


def pack_columns(doc: np.ndarray, variant: np.ndarray, columns: list[np.ndarray], tail: bytes = b"") -> bytes:
    """Entries ordered by document: a table of documents, and the other columns."""
    edge = np.flatnonzero(np.concatenate([[True], (doc[1:] != doc[:-1]) | (variant[1:] != variant[:-1])])) if len(doc) else np.empty(0, np.int64)
    each = np.diff(np.concatenate([edge, [len(doc)]])).astype(np.uint32)
    head = np.array([len(doc), len(edge)], np.int64).tobytes()
    return b"".join([head, _planes(doc[edge].astype(np.int64)), _planes(variant[edge].astype(np.int64)), _planes(each), *map(_planes, columns), tail])


def unpack_columns(blob: bytes, kinds: list[str]) -> tuple[np.ndarray, np.ndarray, list[np.ndarray], memoryview]:
    n, m = np.frombuffer(blob, np.int64, 2).tolist()
    data, at = memoryview(blob), 16

    def read(kind: str, count: int) -> np.ndarray:
        nonlocal at
        out = _from_planes(data[at:], kind, count)
        at += np.dtype(kind).itemsize * count
        return out

    ids, variants, each = read("<i8", m), read("<i8", m), read("<u4", m)
    columns = [read(k, n) for k in kinds]
    return np.repeat(ids, each), np.repeat(variants, each), columns, data[at:]


def _split(to: np.ndarray) -> list[tuple[int, np.ndarray]]:
    """Indices for each target, in their order."""
    order = np.argsort(to, kind="stable")
    if not len(order):
        return []
    cuts = np.flatnonzero(np.diff(to[order])) + 1
    return [(int(to[part[0]]), part) for part in np.split(order, cuts)]


def _blobs(rows: list[tuple[int, int, int, bytes]]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int32(), pa.int32(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], names=["to", "kind", "then", "blob"])


# --- the groups of documents ---------------------------------------------------------


def _group_numpy(doc: np.ndarray, groups: int) -> np.ndarray:
    x = doc.astype(np.int64).view(np.uint64)
    x = x ^ (x >> np.uint64(7)) ^ (x >> np.uint64(19))
    return ((x & np.uint64((1 << 63) - 1)) % np.uint64(groups)).astype(np.int64)


def _group_column(groups: int):
    x = F.coalesce(F.col("doc_id"), F.xxhash64("text"))  # rows without id meet nothing, wherever they are
    x = x.bitwiseXOR(F.shiftrightunsigned(x, 7)).bitwiseXOR(F.shiftrightunsigned(x, 19))
    return F.pmod(x.bitwiseAND(F.lit((1 << 63) - 1)), F.lit(groups)).cast("int")


# --- anchors ---------------------------------------------------------------------------


def segments(text: HashedBytes, offsets: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """``gram hash, first window, last window, text number`` of every segment."""
    n = len(text.buf)
    if n >= 1 << _PLACE_BITS:
        raise ValueError(f"a text has {n} bytes; at most {(1 << _PLACE_BITS) - 1} can be sorted in one piece")
    empty = np.empty(0, np.int64)
    if n < length:
        return np.empty(0, np.uint64), empty, empty, empty
    grams = text.grams(gram)
    place = np.uint64((1 << _PLACE_BITS) - 1)
    least = (grams & ~place) | np.arange(len(grams), dtype=np.uint64)
    span, have = length - gram + 1, 1
    while have * 2 <= span:
        least = np.minimum(least[:-have], least[have:])
        have *= 2
    rest = span - have
    if rest:
        least = np.minimum(least[:-rest], least[rest:])
    anchor = (least & place).astype(np.int64)  # of the window at each place
    size = np.diff(offsets)
    inside = np.zeros(n + 1, np.int32)  # windows must not leave their text
    fits = size >= length
    np.add.at(inside, offsets[:-1][fits], 1)
    np.add.at(inside, offsets[1:][fits] - length + 1, -1)
    window = np.flatnonzero(np.cumsum(inside[: len(anchor)]) > 0)
    if not len(window):
        return np.empty(0, np.uint64), empty, empty, empty
    a = anchor[window]
    opens = np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]]))
    first, last = window[opens], window[np.concatenate([opens[1:] - 1, [len(window) - 1]])]
    return grams[a[opens]], first, last, np.searchsorted(offsets, first, side="right") - 1


def _collision() -> RuntimeError:
    return RuntimeError("two unlike strings have one hash: run again with another seed")


def _pieces(part: pa.RecordBatch, plan: Plan) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, int]]:
    """``doc_id, variant, bytes, offsets, place in the text`` of the texts of a part, in
    order of documents; a text longer than a chunk comes in pieces, such that every
    window lies in one of them."""
    ids, variant = (part.column(i).to_numpy(zero_copy_only=False) for i in (0, 2))
    order = np.lexsort((variant, ids))
    part = part.take(pa.array(order))
    buf, offsets = utf8(part.column(1))
    if len(ids) > 1 or len(buf) <= 2 * plan.chunk:
        yield ids[order], variant[order], buf, offsets, 0
        return
    for at in range(0, len(buf) - plan.length + 1, plan.chunk):
        piece = buf[at : at + plan.chunk + plan.length - 1]
        yield ids, variant, piece, np.array([0, len(piece)], np.int64), at


def _same_in_chunk(buf: np.ndarray, doc: np.ndarray, first: np.ndarray, last: np.ndarray, head: np.ndarray, again: np.ndarray, length: int) -> None:
    """Compares segments with those that they are held equal to, in ranges."""
    at = np.flatnonzero(again)
    if not len(at):
        return
    shift = first[at] - first[head[at]]
    if (last[at] - last[head[at]] != shift).any():
        raise _collision()
    opens = np.concatenate([[True], (np.diff(at) != 1) | (np.diff(shift) != 0) | (first[at[1:]] != last[at[:-1]] + 1) | (np.diff(head[at]) != 1)])
    begin = np.flatnonzero(opens)
    end = np.append(begin[1:], len(at)) - 1
    where = ragged(first[at[begin]], last[at[end]] + length - first[at[begin]])
    if not np.array_equal(buf[where], buf[where - np.repeat(shift[begin], last[at[end]] + length - first[at[begin]])]):
        raise _collision()


def _anchors(plan: Plan):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text", plan.chunk):
                for piece in _pieces(part, plan):
                    rows = _chunk_rows(*piece, plan)
                    if rows:
                        yield _blobs(rows)

    return run


def _chunk_rows(ids: np.ndarray, variants: np.ndarray, buf: np.ndarray, offsets: np.ndarray, base: int, plan: Plan) -> list[tuple[int, int, int, bytes]]:
    text, length = HashedBytes(buf, plan.seed), plan.length
    key, first, last, number = segments(text, offsets, length, plan.gram)
    if not len(key):
        return []
    whole = mix(text.ranges(first, last + length) + (last - first).astype(np.uint64))
    doc, variant, start = ids[number], variants[number], first - offsets[number] + base
    windows = (last - first).astype(np.uint8)
    same = mix(key) ^ whole
    order = np.argsort(same, kind="stable")  # documents stay in order
    s = same[order]
    opens = np.concatenate([[True], s[1:] != s[:-1]])
    head = np.empty(len(key), np.int64)
    head[order] = order[np.flatnonzero(opens)][np.cumsum(opens) - 1]
    again = (doc != doc[head]) & (key == key[head]) & (whole == whole[head])
    _same_in_chunk(buf, doc, first, last, head, again, length)
    rows = []
    covered = np.flatnonzero(again)
    for to, pick in _split(_group_numpy(doc[covered], plan.groups)):
        at = covered[pick]
        rows.append((to % plan.buckets, _COVERED, to, pack_columns(doc[at], variant[at], [start[at].astype(np.uint32), windows[at].astype(np.uint16)])))
    fresh = np.flatnonzero(~again)
    for to, pick in _split((key[fresh] % np.uint64(plan.buckets)).astype(np.int64)):
        at = fresh[pick]
        rows.append((to, _SEGMENTS, to, pack_columns(doc[at], variant[at], _entry(key[at], whole[at], start[at], windows[at], plan.bits))))
    return rows


_ENTRY = ["<u2", "<u4", "<u2", "<u4", "<u4", "u1"]


def _entry(key: np.ndarray, whole: np.ndarray, start: np.ndarray, windows: np.ndarray, bits: int) -> list[np.ndarray]:
    """The upper 48 bits of the gram's and of the segment's hash, its place and width."""
    whole = whole & np.uint64((1 << 64) - (1 << (64 - bits)))
    halves = [x for h in (key, whole) for x in ((h >> np.uint64(48)).astype(np.uint16), (h >> np.uint64(16)).astype(np.uint32))]
    return [*halves, start.astype(np.uint32), windows.astype(np.uint8)]


def _joined(high: np.ndarray, low: np.ndarray) -> np.ndarray:
    return high.astype(np.uint64) << np.uint64(32) | low


def _meet(plan: Plan):
    def run(table: pa.Table) -> pa.Table:
        kind, then = table.column("kind").to_pylist(), table.column("then").to_pylist()
        entries = [b for b, k in zip(table.column("blob"), kind, strict=True) if k == _SEGMENTS]
        rows = [(t, k, t, b.as_py()) for b, k, t in zip(table.column("blob"), kind, then, strict=True) if k != _SEGMENTS]
        if not entries:
            return pa.Table.from_batches([_blobs(rows)])
        key = np.concatenate([_joined(*unpack_columns(b.as_py(), _ENTRY)[2][:2]) for b in entries])
        order = np.argsort(key, kind="stable")
        k = key[order]
        twin = np.zeros(len(k) + 1, bool)
        twin[1:-1] = k[1:] == k[:-1]
        keep = np.zeros(len(k), bool)
        keep[order[twin[1:] | twin[:-1]]] = True  # grams seen once share no window
        del order, k, twin
        parts, at = [], 0
        for b in entries:
            doc, variant, columns, _ = unpack_columns(b.as_py(), _ENTRY)
            pick = np.flatnonzero(keep[at : at + len(doc)])
            parts.append((doc[pick], variant[pick], *(c[pick] for c in columns)))
            at += len(doc)
        key = key[keep]
        doc, variant, _, _, high, low, start, windows = (np.concatenate([p[i] for p in parts]) for i in range(8))
        whole = _joined(high, low)
        del parts, high, low
        order = np.lexsort((doc, whole, key))
        key, whole, doc, variant, start, windows = key[order], whole[order], doc[order], variant[order], start[order], windows[order]
        if len(key):
            new_key = np.concatenate([[True], key[1:] != key[:-1]])
            new = new_key | np.concatenate([[True], whole[1:] != whole[:-1]])
            root = np.flatnonzero(new)[np.cumsum(new) - 1]
            least = doc[root]
            covered = np.flatnonzero(doc != least)
            parent = _parents(covered, root)
            many = _unlike(new_key, new)
            for row_kind, at in ((_WANTED, np.flatnonzero((doc == least) & (many > 1) & (many <= plan.hot))), (_HOT, np.flatnonzero((doc == least) & (many > plan.hot)))):
                for to, pick in _split(_group_numpy(doc[at], plan.groups)):
                    i = at[pick]
                    i = i[np.lexsort((variant[i], doc[i]))]
                    rows.append((to, row_kind, to, pack_columns(doc[i], variant[i], [start[i], windows[i].astype(np.uint16), key[i]])))
            for to, pick in _split(_group_numpy(doc[parent], plan.groups)):
                pick = pick[np.lexsort((start[parent[pick]], variant[parent[pick]], doc[parent[pick]]))]
                i, j = parent[pick], covered[pick]
                rows.append((to, _CLAIMED, to, pack_columns(doc[i], variant[i], [start[i], windows[j].astype(np.uint16), doc[j], variant[j], start[j]])))
        return pa.Table.from_batches([_blobs(rows)])

    return run


def _parents(covered: np.ndarray, root: np.ndarray) -> np.ndarray:
    """The entry that each covered one is compared with: those of one ``root`` make a
    binary tree below it, in their order."""
    of = root[covered]
    first = np.flatnonzero(np.concatenate([[True], of[1:] != of[:-1]])) if len(of) else np.empty(0, np.int64)
    begin = np.repeat(first, np.diff(np.append(first, len(of))))
    above = (np.arange(len(of)) - begin) // 2 - 1
    return np.where(above < 0, of, covered[np.maximum(begin + above, 0)]) if len(of) else of


def _unlike(new_key: np.ndarray, new: np.ndarray) -> np.ndarray:
    """For each entry, how many unlike segments its gram has."""
    number = np.cumsum(new_key) - 1
    return np.bincount(number, weights=new)[number]


def _fetch(plan: Plan):
    """The bytes of segments that have to be sorted, and digests of ranges that others
    are held equal to."""

    def run(docs: pa.Table, wanted: pa.Table) -> pa.Table:
        if not wanted.num_rows or not docs.num_rows:
            return pa.Table.from_batches([_blobs([])])
        ids, variants, buf, offsets = _texts(docs)
        kind = wanted.column("kind").to_numpy()
        rows = []
        for hot in (False, True):
            some = wanted.filter(pa.array(kind == (_HOT if hot else _WANTED)))
            if some.num_rows:
                doc, variant, (start, windows, key) = _gather(some, ["<u4", "<u2", "<u8"])
                at = offsets[_row_of(ids, variants, doc, variant)] + start
                windows = windows.astype(np.int64)
                if hot:
                    which, skip, windows, key = _sides(buf, at, windows, key, plan)
                    doc, variant, start, at = doc[which], variant[which], (start[which] + skip).astype(np.uint32), at[which] + skip
                rows += _segment_rows(buf, at, doc, variant, start, windows, key, plan)
        claims = wanted.filter(pa.array(kind == _CLAIMED))
        if claims.num_rows:
            rows += _digest_rows(buf, offsets, ids, variants, claims, plan)
        return pa.Table.from_batches([_blobs(rows)])

    return run


def _segment_rows(buf: np.ndarray, at: np.ndarray, doc: np.ndarray, variant: np.ndarray, start: np.ndarray, windows: np.ndarray, key: np.ndarray, plan: Plan) -> list[tuple[int, int, int, bytes]]:
    rows, size = [], windows + plan.length
    for to, i in _split((key % np.uint64(plan.sorts)).astype(np.int64)):
        i = i[np.lexsort((variant[i], doc[i]))]
        rows.append((to, _SEGMENTS, to, pack_columns(doc[i], variant[i], [start[i], windows[i].astype(np.uint16)], buf[ragged(at[i], size[i])].tobytes())))
    return rows


def _sides(buf: np.ndarray, at: np.ndarray, windows: np.ndarray, key: np.ndarray, plan: Plan) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Segments of a hot gram in two: ``segment, windows skipped, windows more, key``.

    A window that begins ``left`` bytes or more before the gram holds those bytes; any
    other one holds ``right`` bytes behind the gram.  The two are keyed by them."""
    length, gram = plan.length, plan.gram
    span = length - gram
    left, right = span // 2, span - span // 2 + 1
    size = windows + length
    own = HashedBytes(buf[ragged(at, size)], plan.seed)
    begin = np.cumsum(size) - size
    column = np.arange(span + 1)
    grams = own.grams(gram) >> np.uint64(16)
    # the anchor is the gram's first place that all windows hold
    place = ((grams[begin[:, None] + column] == key[:, None]) & (column >= windows[:, None])).argmax(axis=1)
    which, skip, more, new = [], [], [], []
    far = np.flatnonzero(place >= left)
    if len(far):
        which.append(far)
        skip.append(np.zeros(len(far), np.int64))
        more.append(np.minimum(windows[far], place[far] - left))
        new.append(mix(own.ranges(begin[far] + place[far] - left, begin[far] + place[far] + gram)))
    first = np.maximum(place - left + 1, 0)
    near = np.flatnonzero(first <= windows)
    if len(near):
        which.append(near)
        skip.append(first[near])
        more.append(windows[near] - first[near])
        new.append(mix(~own.ranges(begin[near] + place[near], begin[near] + place[near] + gram + right)))
    return tuple(np.concatenate(x) for x in (which, skip, more, new))


def _digest_rows(buf: np.ndarray, offsets: np.ndarray, ids: np.ndarray, variants: np.ndarray, claims: pa.Table, plan: Plan) -> list[tuple[int, int, int, bytes]]:
    doc, variant, (start, windows, child, child_variant, child_start) = _gather(claims, ["<u4", "<u2", "<i8", "<i8", "<u4"])
    row = _row_of(ids, variants, doc, variant)
    start, child_start = start.astype(np.int64), child_start.astype(np.int64)
    order = np.lexsort((start, child_start - start, child_variant, child, row))
    row, child, child_variant, start, child_start, end = (x[order] for x in (row, child, child_variant, start, child_start, start + windows + plan.length))
    same = (row[1:] == row[:-1]) & (child[1:] == child[:-1]) & (child_variant[1:] == child_variant[:-1])
    same &= (child_start - start)[1:] == (child_start - start)[:-1]
    same &= start[1:] <= end[:-1]
    opens = np.flatnonzero(np.concatenate([[True], ~same]))
    closes = np.append(opens[1:], len(row)) - 1
    size = end[closes] - start[opens]
    at, data = offsets[row[opens]] + start[opens], memoryview(buf)
    digest = np.frombuffer(b"".join([_digest(data[a:b]) for a, b in zip(at.tolist(), np.minimum(at + size, offsets[row[opens] + 1]).tolist(), strict=True)]), np.uint64).reshape(-1, 2)
    child, child_variant, child_start = child[opens], child_variant[opens], child_start[opens]
    rows = []
    for to, i in _split(_group_numpy(child, plan.groups)):
        pick = np.lexsort((child_variant[i], child[i]))
        i = i[pick]
        rows.append((to % plan.sorts, _CLAIMED, to, pack_columns(child[i], child_variant[i], [child_start[i].astype(np.uint32), size[i].astype(np.uint32), digest[i, 0], digest[i, 1]])))
    return rows


def _digest(data) -> bytes:
    return hashlib.blake2b(data, digest_size=16).digest()


def _gather(table: pa.Table, kinds: list[str]) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
    parts = [unpack_columns(b.as_py(), kinds)[:3] for b in table.column("blob")]
    return np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts]), [np.concatenate([p[2][i] for p in parts]) for i in range(len(kinds))]


def _texts(docs: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Ids and variants in order, with the bytes of their texts."""
    docs = docs.filter(docs.column("doc_id").is_valid())
    ids, variants = docs.column("doc_id").to_numpy(), docs.column("variant").to_numpy()
    order = np.lexsort((variants, ids))
    buf, offsets = utf8(docs.column("text").take(pa.array(order)))
    return ids[order], variants[order], buf, offsets


def _row_of(ids: np.ndarray, variants: np.ndarray, doc: np.ndarray, variant: np.ndarray) -> np.ndarray:
    """The first row of ``ids, variants`` (in order) for each wanted pair, all there."""
    low, high = np.searchsorted(ids, doc, side="left"), np.searchsorted(ids, doc, side="right")
    live = np.flatnonzero(high - low > 1)
    while len(live):  # several rows of the same id
        middle = (low[live] + high[live]) >> 1
        less = variants[middle] < variant[live]
        low[live[less]] = middle[less] + 1
        high[live[~less]] = middle[~less]
        live = live[low[live] < high[live]]
    return low


def covered_windows(buf: np.ndarray, size: np.ndarray, doc: np.ndarray, length: int, seed: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """For segments lying one after another in ``buf``: the segment and the place in
    it of every window that a segment of a smaller document has too.

    Windows with a hash of their own are left out; the others are sorted as
    suffixes, and runs with ``length`` common bytes are verified on the bytes.
    """
    text = HashedBytes(buf, seed)
    begin = np.cumsum(size) - size
    count = size - length + 1
    segment = np.repeat(np.arange(len(size)), count)
    place = np.arange(int(count.sum())) - np.repeat(np.cumsum(count) - count, count)
    at = begin[segment] + place
    hashed = mix(text.ranges(at, at + length))
    order = np.argsort(hashed, kind="stable")
    h = hashed[order]
    twin = np.zeros(len(h) + 1, bool)
    twin[1:-1] = h[1:] == h[:-1]
    keep = np.sort(order[twin[1:] | twin[:-1]])
    segment, place, at = segment[keep], place[keep], at[keep]
    order, shared = merge_sorted_suffixes(text, at, length)
    if not len(order):
        return segment[:0], place[:0]
    a = at[order]
    same = shared >= length
    check = np.flatnonzero(same)
    for j in range(length):  # equal hashes are no proof
        check = check[buf[a[check] + j] == buf[a[check - 1] + j]]
    same[:] = False
    same[check] = True
    run = np.cumsum(~same) - 1
    owner = doc[segment[order]]
    least = np.full(int(run[-1]) + 1, np.iinfo(np.int64).max)
    np.minimum.at(least, run, owner)
    hit = order[owner > least[run]]
    return segment[hit], place[hit]


def _sort(plan: Plan):
    def run(table: pa.Table) -> pa.Table:
        docs, variants, starts, sizes, texts, rows = [], [], [], [], [], []
        for kind, then, b in zip(table.column("kind").to_pylist(), table.column("then").to_pylist(), table.column("blob"), strict=True):
            if kind != _SEGMENTS:
                rows.append((then, kind, then, b.as_py()))
                continue
            doc, variant, (start, windows), tail = unpack_columns(b.as_py(), ["<u4", "<u2"])
            docs.append(doc)
            variants.append(variant)
            starts.append(start)
            sizes.append(windows.astype(np.int64) + plan.length)
            texts.append(np.frombuffer(tail, np.uint8))
        if docs:
            doc, variant, start, size, buf = map(np.concatenate, (docs, variants, starts, sizes, texts))
            segment, place = covered_windows(buf, size, doc, plan.length, plan.seed)
            order = np.lexsort((place, segment))
            segment, place = segment[order], place[order]
            # neighbouring windows become one range
            opens = np.flatnonzero(np.concatenate([[True], (segment[1:] != segment[:-1]) | (place[1:] != place[:-1] + 1)])) if len(segment) else np.empty(0, np.int64)
            closes = np.concatenate([opens[1:] - 1, [len(segment) - 1]]) if len(opens) else opens
            owner, owner_variant, first = doc[segment[opens]], variant[segment[opens]], start[segment[opens]] + place[opens]
            more = (place[closes] - place[opens]).astype(np.uint16)
            for to, pick in _split(_group_numpy(owner, plan.groups)):
                pick = pick[np.lexsort((owner_variant[pick], owner[pick]))]
                rows.append((to, _COVERED, to, pack_columns(owner[pick], owner_variant[pick], [first[pick].astype(np.uint32), more[pick]])))
        return pa.Table.from_batches([_blobs(rows)])

    return run


_RESULT = "doc_id long, text_bytes binary, n_bytes long, n_removed long, n_spans long, kept_sha256 string, spans array<struct<start:long,end:long>>"


def _cut(length: int, with_texts: bool):
    kinds = [pa.int64(), pa.binary(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))]
    names = ["doc_id", "text_bytes", "n_bytes", "n_removed", "n_spans", "kept_sha256", "spans"]

    def run(docs: pa.Table, ranges: pa.Table) -> pa.Table:
        if not docs.num_rows:
            return pa.Table.from_arrays([pa.array([], k) for k in kinds], names=names)
        ids, variants = docs.column("doc_id").to_pylist(), docs.column("variant").to_pylist()
        buf, offsets = utf8(docs.column("text"))
        by_doc: dict[tuple[int, int], tuple[int, int]] = {}
        lo = hi = np.empty(0, np.int64)
        kind = ranges.column("kind").to_numpy()
        parts = []
        claims, ranges = (ranges.filter(pa.array(kind == k)) for k in (_CLAIMED, _COVERED))
        if claims.num_rows:
            parts.append(_verified(docs, claims))
        if ranges.num_rows:
            doc, variant, (start, windows) = _gather(ranges, ["<u4", "<u2"])
            parts.append((doc, variant, start.astype(np.int64), start.astype(np.int64) + windows + length))
        if parts:
            doc, variant, lo, hi = (np.concatenate(c) for c in zip(*parts, strict=True))
            order = np.lexsort((lo, variant, doc))
            doc, variant, lo, hi = doc[order], variant[order], lo[order], hi[order]
            edge = np.flatnonzero(np.concatenate([[True], (doc[1:] != doc[:-1]) | (variant[1:] != variant[:-1])]))
            by_doc = dict(zip(zip(doc[edge].tolist(), variant[edge].tolist(), strict=True), zip(edge.tolist(), [*edge[1:].tolist(), len(doc)], strict=True), strict=True))
        rows = []
        for i, doc_id in enumerate(ids):
            data = buf[offsets[i] : offsets[i + 1]]
            spans = []
            if (doc_id, variants[i]) in by_doc:
                a, b = by_doc[doc_id, variants[i]]
                starts, ends = lo[a:b], np.minimum(np.maximum.accumulate(hi[a:b]), len(data))
                opens = np.flatnonzero(np.concatenate([[True], starts[1:] > ends[:-1]]))
                spans = list(zip(starts[opens].tolist(), ends[np.concatenate([opens[1:] - 1, [len(starts) - 1]])].tolist(), strict=True))
            if spans:
                edges = [0, *(x for s in spans for x in s), len(data)]
                kept = b"".join(data[x:y].tobytes() for x, y in zip(edges[::2], edges[1::2], strict=True))
            else:
                kept = data.tobytes()
            rows.append((doc_id, kept if with_texts else None, len(data), len(data) - len(kept), len(spans), hashlib.sha256(kept).hexdigest(), [{"start": x, "end": y} for x, y in spans]))
        return pa.Table.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)

    return run


def _verified(docs: pa.Table, claims: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """``doc, variant, start, end`` of claimed ranges, whose bytes must have the digests
    of those that they are held equal to."""
    ids, variants, buf, offsets = _texts(docs)
    doc, variant, (start, size, d1, d2) = _gather(claims, ["<u4", "<u4", "<u8", "<u8"])
    at, data = offsets[_row_of(ids, variants, doc, variant)] + start, memoryview(buf)
    mine = b"".join([_digest(data[a : a + n]) for a, n in zip(at.tolist(), size.tolist(), strict=True)])
    if mine != np.column_stack([d1, d2]).tobytes():
        raise _collision()
    return doc, variant, start.astype(np.int64), start.astype(np.int64) + size


def remove_shared_substrings(docs: DataFrame, length: int = LENGTH, with_texts: bool = True, **plan) -> DataFrame:
    """``doc_id, text_bytes`` (what is left), ``n_bytes, n_removed, n_spans,
    kept_sha256, spans`` for every row of ``docs``; spans are byte ranges of the
    original text, maximal and in order.  ``plan``: see ``Plan``."""
    gram = max(1, min(GRAM, length * 2 // 5))
    if length - gram + 1 > 256:
        raise ValueError("the length is at most 256 bytes more than its gram")
    rows = id_and_text(docs, F.xxhash64(text_or_empty()).alias("variant"))
    each = rows.groupBy("doc_id").agg(F.sum(F.octet_length("text")).alias("n"), (F.col("doc_id").isNotNull() & (F.min("variant") != F.max("variant"))).alias("unlike"))
    total, unlike = each.agg(F.sum("n"), F.max("unlike")).first()
    total = total or 0
    if not unlike:  # ids tell all texts apart
        rows = rows.withColumn("variant", F.lit(0).cast("long"))
    buckets = max(16, total // BUCKET_BYTES)
    plan = Plan(length, gram, buckets, 4 * buckets, max(16, total // GROUP_BYTES) | 1, **plan)
    anchors = rows.filter(F.col("doc_id").isNotNull() & (F.octet_length("text") >= length)).mapInArrow(_anchors(plan), _BLOB)
    met = saved(anchors.groupBy("to").applyInArrow(_meet(plan), _BLOB))
    # after this each document's group is met twice, by one and the same exchange
    grouped = rows.withColumn("to", _group_column(plan.groups))
    wanted = met.filter(F.col("kind").isin(_WANTED, _CLAIMED, _HOT))
    fetched = grouped.groupBy("to").cogroup(wanted.groupBy("to")).applyInArrow(_fetch(plan), _BLOB)
    sorted_ranges = fetched.groupBy("to").applyInArrow(_sort(plan), _BLOB)
    ranges = met.filter(F.col("kind") == _COVERED).unionByName(sorted_ranges)
    return grouped.groupBy("to").cogroup(ranges.groupBy("to")).applyInArrow(_cut(length, with_texts), _RESULT)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``op3``: all documents without the 50-byte strings of smaller documents."""
    out = remove_shared_substrings(spark.read.parquet(f"{sf_dir}/documents.parquet"), with_texts=False)
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")
