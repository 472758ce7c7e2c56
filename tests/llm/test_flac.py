import hashlib
import random
import zlib

import numpy as np
import pytest

from peertrust.llm import flac_media as flac


def payloads():
    rng = random.Random(2)
    text = "Of ththe Éclair naïve and the other. "
    out = [b"", b"a", b"x" * 192, b"y" * 576, b"z" * 577, text.encode() * 50, bytes(rng.randrange(256) for _ in range(5000)),
           bytes(int(128 + 100 * np.sin(i / 9)) for i in range(3000)), bytes(i % 256 for i in range(2000)), b"\x00" * 10 + b"\xff" * 700, b"q" * 80_000 + b"w"]
    out += [bytes(rng.choice(b"ab \n\xc3") for _ in range(rng.randrange(2000))) for _ in range(20)]
    out.append(b" " * 575 + b"\xff")
    out.append(bytes(128 for _ in range(570)) + b"\xff\x00\xff\x00\xff\x00")
    return [flac.padded(p) for p in out]


def test_round_trip_and_general_decoder_agree():
    data = payloads()
    media = flac.encode_streams(data)
    assert flac.decode_streams(media) == data
    kinds = set()
    for p, m in zip(data, media):
        assert [x + 128 for x in flac.decode_stream(m)[0]] == list(p)
        info = flac.read_metadata(m)
        kinds |= {m[info["frames"] + int(o) + 6] >> 1 for o in info["seek"]["offset"][:100]}
        assert info["samples"] == len(p) and info["md5"] == hashlib.md5(bytes(b ^ 128 for b in p)).digest()
    assert {0, 1} < kinds and kinds & {8, 9, 10} and 33 in kinds
    assert flac.encode_streams([]) == [] and flac.decode_streams([]) == []


def test_crc_values_are_the_known_ones():
    assert flac._crc(b"123456789", 8) == 0xF4
    assert flac._crc(b"123456789", 16) == 0xFEE8


@pytest.mark.parametrize("k", [0, 127, 128, 2047, 2048, 65535, 65536, 2**21, 2**31 - 1])
def test_frame_numbers(k):
    coded = flac._number(k)
    if k < 0xD800:
        assert coded == chr(k).encode()
    lead = coded[0]
    n = 1 if lead < 128 else 8 - (lead ^ 255).bit_length()
    assert len(coded) == n


def test_broken_frames_are_found():
    media = flac.encode_streams([flac.padded(b"hello " * 400)])[0]
    start = flac.read_metadata(media)["frames"]
    rng = random.Random(3)
    for _ in range(40):
        at = rng.randrange(start, len(media))
        broken = media[:at] + bytes([media[at] ^ 1 << rng.randrange(8)]) + media[at + 1 :]
        for decode in (flac.decode_stream, lambda s: flac.decode_streams([s])):
            with pytest.raises(ValueError):
                decode(broken)


def test_general_decoder_reads_stereo_partitions_and_wasted_bits():
    class W:
        def __init__(self):
            self.s = ""

        def put(self, x, n):
            self.s += format(x & (1 << n) - 1, f"0{n}b") if n else ""

    w = W()
    left, right = [4, 6, 8, -2], [2, 2, 10, 6]
    for x, n in ((0x3FFE, 14), (0, 1), (0, 1), (6, 4), (0, 4), (8, 4), (1, 3), (0, 1), (0, 8), (3, 8)):
        w.put(x, n)
    head = int(w.s, 2).to_bytes(len(w.s) // 8, "big")
    w.put(flac._crc(head, 8), 8)
    w.put(0, 1), w.put(8, 6), w.put(1, 1), w.put(1, 1)  # fixed order 0, one wasted bit
    w.put(0, 2), w.put(1, 4)  # two partitions
    for part in (left[:2], left[2:]):
        w.put(2, 4)
        for x in part:
            x >>= 1
            z = 2 * x if x >= 0 else -2 * x - 1
            w.s += "0" * (z >> 2) + "1"
            w.put(z, 2)
    w.put(0, 1), w.put(8, 6), w.put(0, 1), w.put(1, 2), w.put(0, 4), w.put(31, 5), w.put(9, 5)  # the difference, an escaped partition
    for a, b in zip(left, right):
        w.put(a - b, 9)
    w.s += "0" * (-len(w.s) % 8)
    body = int(w.s, 2).to_bytes(len(w.s) // 8, "big")
    frame = body + flac._crc(body, 16).to_bytes(2, "big")
    assert flac.decode_frame(frame, 0, {"bits": 8})[0] == [left, right]


def test_frames(spark, sf):
    docs = spark.createDataFrame([(1, None, 1), (2, "", 1), (3, "héllo", 1), (3, "héllo", 1), (None, "x" * 200_000, 1)], "doc_id long, text string, media int")
    rows = flac.media_digests(docs).collect()
    assert len(rows) == 5
    by = {r.doc_id: r for r in rows}
    assert by[1].asDict() | {"doc_id": 2} == by[2].asDict() and by[1].payload_bytes == 192
    want = flac.padded("héllo".encode())
    assert by[3].payload_sha256 == hashlib.sha256(want).hexdigest() and by[3].tail_crc32 == zlib.crc32(want[-16:])
    blocks = flac.pcm_blocks(flac.encode_documents(docs)).filter("doc_id = 3").collect()
    assert bytes(b ^ 128 for b in blocks[0].pcm) == want and blocks[0].first_sample == 0
    assert flac.media_digests(docs.limit(0)).count() == 0
    texts = {r.doc_id: r.text.encode() for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for r in flac.media_digests(spark.read.parquet(f"{sf}/documents.parquet")).collect():
        p = flac.padded(texts[r.doc_id])
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256) == (len(texts[r.doc_id]), len(p), hashlib.sha256(p).hexdigest())
