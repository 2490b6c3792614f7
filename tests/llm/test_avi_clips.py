import hashlib
import random
import struct
import zlib

import numpy as np
import pytest
from freshview.llm import avi_clips as A


def payloads():
    rng = random.Random(8)
    cases = [b"", b"a", b"x" * 64, b"y" * 65, bytes(range(256)) * 40, "é😀".encode() * 700, b"\xff\x00" * 4000]
    return [A.payload_of(c) for c in cases + [rng.randbytes(rng.randrange(20000)) for _ in range(12)] + [rng.randbytes(600_000)]]


def test_round_trip():
    want = payloads()
    files = A.store(want)
    assert [p for p, _, _ in A.read_back(files)] == want
    assert A.store(want[3:4])[0] == files[3]
    no_index = files[4][: files[4].rindex(b"idx1")]
    no_index = no_index[:4] + struct.pack("<I", len(no_index) - 8) + no_index[8:]
    assert A.read_back([no_index])[0][0] == want[4]
    for bad in (b"", b"RIFF", files[4][:300], b"x" * 400):
        with pytest.raises(ValueError):
            A.read_back([bad])


def test_general_decoder_reads_the_same():
    for p in payloads()[:7]:
        for f in A.read_avi(A.store([p])[0])[0]:
            head = A.Frame(f)
            plane = A.decode_frame(head)[0]
            assert (plane.reshape(plane.shape[0] // 8, 8, -1, 8) == plane[::8, ::8][:, None, :, None]).all()
            assert plane[::8, ::8].tobytes() in p


def test_ac_coefficients():
    assert A.ZIGZAG[:10].tolist() == [0, 1, 8, 16, 9, 2, 3, 10, 17, 24] and sorted(A.ZIGZAG) == list(range(64))
    # one block: DC level 2 (quantiser 8), first AC coefficient 5 of length 3, then end of block
    ac = bytes([0x10] + [0, 2] + [0] * 14 + [0x00, 0x03])
    bits = "0010" + "10" + "01" + "101" + "00"
    bits += "1" * (-len(bits) % 8)
    scan = int(bits, 2).to_bytes(len(bits) // 8, "big")
    head = A.frame_header(1)
    cut = head.index(b"\xff\xc0")
    data = head[:cut] + A._segment(0xC0, struct.pack(">BHHB3B", 8, 8, 8, 1, 1, 0x11, 0))
    dc = bytes([0x00] + [9 if n == 4 else 0 for n in range(1, 17)] + list(range(9)))
    data += A._segment(0xC4, dc) + A._segment(0xC4, ac) + A._segment(0xDA, bytes([1, 1, 0, 0, 63, 0])) + scan + b"\xff\xd9"
    plane = A.decode_frame(A.Frame(data))[0]
    want = [128 + 2 + 5 * 0.5 * np.sqrt(0.125) * np.cos((2 * x + 1) * np.pi / 16) for x in range(8)]
    assert np.abs(plane - np.rint(want)).max() <= 1 and plane.shape == (8, 8)


def test_shots():
    dark, light = np.zeros((4, 64), np.uint8), np.full((4, 64), 200, np.uint8)
    assert A.shots([dark] * 5 + [light] * 7 + [dark] * 3) == [0, 5, 12]
    assert A.shots([]) == [] and A.shots([dark]) == [0]


def test_frames(spark):
    texts = [None, "", "a", "é" * 5000, "z" * 64, "same", "same", ("a" * 4096 + "\x00" * 4096) * 3]
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, media string")
    got = sorted(A.media_features(df).collect())
    assert len(got) == len(texts)
    for r in got:
        raw = (texts[r.doc_id] or "").encode()
        p = A.payload_of(raw)
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
        assert r.media_sha256 == hashlib.sha256(A.store([p])[0]).hexdigest()
    assert got[5][1:] == got[6][1:] and got[0][1:] == got[1][1:]
    rows = A.clips(A.store_media(df)).filter("doc_id = 7").orderBy("clip").collect()
    assert [(r.first_frame, r.n_frames) for r in rows] == [(k, 1) for k in range(6)] and rows[2].start_s == 2 / 25
    assert A.media_features(df.limit(0)).count() == 0
