"""Media columns as AVI with motion-JPEG: store bytes, read them back, detect shots.

Storing is exact although JPEG is not: each byte is one 8 x 8 block of a baseline grey
frame, flat, with DC quantiser 8, so its DC level is the byte less 128 and no AC
coefficient is needed. A frame has 64 blocks a row and at most 64 rows; every row is a
restart interval, so rows decode independently and all rows of a batch decode in step
as array arithmetic. Reading parses the RIFF chunks, takes frames from the ``idx1``
index (or from the ``movi`` list where there is none), reads each frame's tables and
decodes it; frames of another layout (any baseline frame, grey or colour) go through a
general Huffman decoder and inverse DCT.

Shots are cut where the difference of grey histograms between neighbours exceeds an
adaptive threshold, the mean plus ``SHOT_DEVIATIONS`` standard deviations of the
differences in the window before it, since the last cut, and at least ``SHOT_FLOOR``.

Defined cases: null and empty texts are stored as 64 zero bytes; equal texts give equal
values; a text of any length is stored (rows are coded in chunks); each input row gives
one row; truncated or foreign bytes raise ``ValueError`` in the parser; other columns
are not read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import slices, table

ROW, ROWS, RATE = 64, 64, 25
SHOT_WINDOW, SHOT_DEVIATIONS, SHOT_FLOOR, BINS = 8, 3.0, 0.25, 16
CHUNK_ROWS, BLOCK_BYTES = 1 << 13, 1 << 20
# Order in which the coefficients of a block are coded.
ZIGZAG = np.argsort([(i // 8 + i % 8, (i // 8 if (i // 8 + i % 8) % 2 else i % 8)) [0] * 64 + (i // 8 if (i // 8 + i % 8) % 2 else i % 8) for i in range(64)])

_LENGTH = np.array([abs(d).bit_length() for d in range(-255, 256)], np.int64)


def _segment(marker: int, body: bytes) -> bytes:
    return struct.pack(">BBH", 0xFF, marker, len(body) + 2) + body


def frame_header(rows: int) -> bytes:
    """Everything before the coded data: quantiser 8 for DC, codes of 4 bits for DC lengths 0 to 8, one bit for end of block."""
    quantiser = bytes([0, 8] + [1] * 63)
    dc = bytes([0x00] + [9 if n == 4 else 0 for n in range(1, 17)] + list(range(9)))
    ac = bytes([0x10] + [1] + [0] * 15 + [0])
    return (
        b"\xff\xd8"
        + _segment(0xDB, quantiser)
        + _segment(0xC0, struct.pack(">BHHB3B", 8, rows * 8, ROW * 8, 1, 1, 0x11, 0))
        + _segment(0xC4, dc)
        + _segment(0xC4, ac)
        + _segment(0xDD, struct.pack(">H", ROW))
        + _segment(0xDA, bytes([1, 1, 0x00, 0, 63, 0]))
    )


def code_rows(rows: np.ndarray, markers: np.ndarray) -> tuple[bytes, np.ndarray]:
    """Coded rows, each followed by its marker, and the end of each in the result."""
    streams, ends, done = [], [], 0
    for at in range(0, len(rows), CHUNK_ROWS):
        part = rows[at : at + CHUNK_ROWS].astype(np.int64) - 128
        change = np.diff(part, axis=1, prepend=0)
        size = _LENGTH[change + 255]
        bits = np.where(change > 0, change, change + (1 << size) - 1)
        code = (size << (size + 1)) | (bits << 1)
        width = size + 5
        stop = np.cumsum(width, axis=1)
        whole = (stop[:, -1] + 7) >> 3
        first = np.cumsum(whole) - whole
        place = first[:, None] * 8 + stop - width
        value = (code << (24 - (place & 7) - width)).ravel()
        byte = (place >> 3).ravel()
        total = int(whole.sum())
        out = sum(np.bincount(byte + k, (value >> (16 - 8 * k)) & 255, total + 3) for k in range(3)).astype(np.int64)[:total]
        out[first + whole - 1] += (1 << (whole * 8 - stop[:, -1])) - 1
        full = out == 255
        shift = np.cumsum(full) - full + 2 * np.repeat(np.arange(len(part)), whole)
        end = (first + whole) + np.cumsum(full)[first + whole - 1] + 2 * np.arange(1, len(part) + 1)
        stream = np.zeros(int(end[-1]), np.uint8)
        stream[np.arange(total) + shift] = out
        stream[end - 2], stream[end - 1] = 0xFF, markers[at : at + CHUNK_ROWS]
        streams.append(stream.tobytes())
        ends.append(end + done)
        done += len(stream)
    return b"".join(streams), np.concatenate(ends)


def _chunk(name: bytes, body: bytes) -> bytes:
    return name + struct.pack("<I", len(body)) + body + b"\0" * (len(body) & 1)


def write_avi(frames: list[bytes], height: int) -> bytes:
    """An AVI file of one motion-JPEG stream with an index."""
    largest = max(map(len, frames))
    main = struct.pack("<14I", 1_000_000 // RATE, largest * RATE, 0, 0x10, len(frames), 0, 1, largest, ROW * 8, height * 8, 0, 0, 0, 0)
    stream = struct.pack("<4s4sIHHIIIIIIII4H", b"vids", b"MJPG", 0, 0, 0, 0, 1, RATE, 0, len(frames), largest, 0xFFFFFFFF, 0, 0, 0, ROW * 8, height * 8)
    form = struct.pack("<IiiHH4sIiiII", 40, ROW * 8, height * 8, 1, 24, b"MJPG", ROW * 8 * height * 8 * 3, 0, 0, 0, 0)
    header = _chunk(b"LIST", b"hdrl" + _chunk(b"avih", main) + _chunk(b"LIST", b"strl" + _chunk(b"strh", stream) + _chunk(b"strf", form)))
    body, index, at = [b"movi"], [], 4
    for f in frames:
        index.append(struct.pack("<4s3I", b"00dc", 0x10, at, len(f)))
        body.append(_chunk(b"00dc", f))
        at += len(body[-1])
    return _chunk(b"RIFF", b"AVI " + header + _chunk(b"LIST", b"".join(body)) + _chunk(b"idx1", b"".join(index)))


def read_avi(data: bytes) -> tuple[list[memoryview], float]:
    """Frames of the first video stream, by the index where there is one, and the frame rate."""
    view = memoryview(data)
    if len(data) < 12 or data[:4] != b"RIFF" or data[8:12] != b"AVI ":
        raise ValueError("no AVI")
    rate, movi, index = float(RATE), None, None

    def walk(at: int, stop: int):
        while at + 8 <= stop:
            size = struct.unpack_from("<I", data, at + 4)[0]
            if at + 8 + size > stop:
                raise ValueError("a chunk ends after its list")
            yield data[at : at + 4], at + 8, size
            at += 8 + size + (size & 1)

    stop = min(len(data), 8 + struct.unpack_from("<I", data, 4)[0])
    for name, at, size in walk(12, stop):
        if name == b"LIST" and data[at : at + 4] == b"hdrl":
            for inner, a, _ in walk(at + 4, at + size):
                if inner == b"avih" and (micros := struct.unpack_from("<I", data, a)[0]):
                    rate = 1_000_000 / micros
        elif name == b"LIST" and data[at : at + 4] == b"movi":
            movi = (at, size)
        elif name == b"idx1":
            index = (at, size)
    if movi is None:
        raise ValueError("no frames")
    frames = []
    if index:
        entries = list(struct.iter_unpack("<4s3I", view[index[0] : index[0] + index[1] // 16 * 16]))
        # offsets count from the list's type, in some files from the file's start
        origin = movi[0] if not entries or entries[0][2] < movi[0] else 0
        for name, _, at, size in entries:
            if name[2:] in (b"dc", b"db"):
                if data[origin + at : origin + at + 4] != name:
                    raise ValueError("the index points past its chunk")
                frames.append(view[origin + at + 8 : origin + at + 8 + size])
    else:
        frames = [view[a : a + n] for name, a, n in walk(movi[0] + 4, movi[0] + movi[1]) if name[2:] in (b"dc", b"db")]
    return frames, rate


class Frame:
    """Tables and geometry of a baseline frame."""

    def __init__(self, data) -> None:
        if bytes(data[:2]) != b"\xff\xd8":
            raise ValueError("no JPEG frame")
        self.quantisers, self.codes, self.restart, self.parts = {}, {}, 0, []
        at = 2
        while True:
            if at + 4 > len(data):
                raise ValueError("a frame ends in its header")
            marker, size = data[at + 1], (data[at + 2] << 8) | data[at + 3]
            body = bytes(data[at + 4 : at + 2 + size])
            at += 2 + size
            if marker == 0xDB:
                while body:
                    wide = body[0] >> 4
                    self.quantisers[body[0] & 15] = np.frombuffer(body[1 : 65 + 64 * wide], ">u2" if wide else "u1").astype(np.int64)
                    body = body[65 + 64 * wide :]
            elif marker == 0xC4:
                while body:
                    n = sum(body[1:17])
                    self.codes[body[0]] = (body[1:17], body[17 : 17 + n])
                    body = body[17 + n :]
            elif marker in (0xC0, 0xC1):
                self.height, self.width = struct.unpack(">HH", body[1:5])
                self.parts = [(body[6 + 3 * k], body[7 + 3 * k] >> 4, body[7 + 3 * k] & 15, body[8 + 3 * k]) for k in range(body[5])]
            elif 0xC2 <= marker <= 0xCF:
                raise ValueError("only baseline frames are read")
            elif marker == 0xDD:
                self.restart = struct.unpack(">H", body)[0]
            elif marker == 0xDA:
                self.tables = {body[1 + 2 * k]: body[2 + 2 * k] for k in range(body[0])}
                self.scan = data[at:]
                return

    def flat_rows(self) -> bool:
        """Whether every block row of one grey component restarts on its own."""
        return len(self.parts) == 1 and self.restart > 0 and self.width == 8 * self.restart and self.height % 8 == 0

    def key(self) -> tuple:
        table = self.tables[self.parts[0][0]]
        return self.restart, int(self.quantisers[self.parts[0][3]][0]), self.codes[table >> 4], self.codes[16 | (table & 15)]


def _lookup(code: tuple[bytes, bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Symbol and length of the code at the head of any 16 bits (length 0: none)."""
    symbol, length = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int64)
    value = k = 0
    for bits in range(1, 17):
        for _ in range(code[0][bits - 1]):
            a, b = value << (16 - bits), (value + 1) << (16 - bits)
            symbol[a:b], length[a:b] = code[1][k], bits
            value, k = value + 1, k + 1
        value <<= 1
    return symbol, length


def decode_flat_rows(scans: list, key: tuple) -> np.ndarray | None:
    """Grey values of DC-only rows of frames with the same tables; None where a block has AC coefficients."""
    width, quantiser, dc, ac = key
    data = np.frombuffer(b"".join(scans), np.uint8)
    (dc_symbol, dc_length), (ac_symbol, ac_length) = _lookup(dc), _lookup(ac)
    marks = np.flatnonzero((data[:-1] == 255) & (data[1:] != 0))
    starts = np.concatenate(([0], marks[:-1] + 2))
    out = np.empty((len(marks), width), np.uint8)
    for at in range(0, len(marks), CHUNK_ROWS):
        a, b = starts[at : at + CHUNK_ROWS], marks[at : at + CHUNK_ROWS]
        part = data[a[0] : b[-1]]
        keep = np.ones(len(part), bool)
        keep[1:] = (part[:-1] != 255) | (part[1:] != 0)
        for gap in (0, 1):
            keep[b[:-1] + gap - a[0]] = False
        place = np.concatenate(([0], np.cumsum(keep)))[a - a[0]] * 8
        part = np.concatenate((part[keep], np.zeros(8, np.uint8))).astype(np.int64)
        # 40 bits from any byte on
        window = (part[:-4] << 32) | (part[1:-3] << 24) | (part[2:-2] << 16) | (part[3:-1] << 8) | part[4:]
        level = np.zeros(len(a), np.int64)
        for k in range(width):
            head = window[np.minimum(place >> 3, len(window) - 1)] << (place & 7)
            code = (head >> 24) & 0xFFFF
            size = dc_symbol[code]
            used = dc_length[code]
            bits = (head >> (40 - used - size)) & ((1 << size) - 1)
            level += np.where(bits >> np.maximum(size - 1, 0), bits, bits - (1 << size) + 1)
            place += used + size
            code = ((window[np.minimum(place >> 3, len(window) - 1)] << (place & 7)) >> 24) & 0xFFFF
            if (used == 0).any() or (ac_length[code] == 0).any():
                raise ValueError("a code is in no table")
            if ac_symbol[code].any():
                return None
            place += ac_length[code]
            out[at : at + len(a), k] = np.clip((level * quantiser + 4) // 8 + 128, 0, 255)
    return out


def decode_frame(frame: Frame) -> list[np.ndarray]:
    """Planes of any baseline frame, at each component's own resolution, by Huffman decoding and inverse DCT."""
    basis = np.array([[(np.sqrt(0.125) if u == 0 else 0.5) * np.cos((2 * x + 1) * u * np.pi / 16) for u in range(8)] for x in range(8)])
    tables = {k: tuple(x.tolist() for x in _lookup(c)) for k, c in frame.codes.items()}
    most_h, most_v = max(p[1] for p in frame.parts), max(p[2] for p in frame.parts)
    if len(frame.parts) == 1:
        frame.parts = [(frame.parts[0][0], 1, 1, frame.parts[0][3])]
        most_h = most_v = 1
    across, down = -(-frame.width // (8 * most_h)), -(-frame.height // (8 * most_v))
    planes = [np.zeros((down * v, across * h, 64)) for _, h, v, _ in frame.parts]
    data, at, held, have = bytes(frame.scan), 0, 0, 0

    def need(n: int) -> None:
        nonlocal at, held, have
        while have < n:
            byte = data[at] if at < len(data) else 255
            if byte == 255 and at + 1 < len(data) and data[at + 1] != 0:
                byte = 255  # a marker: bits past the end are ones
            else:
                at += 2 if byte == 255 else 1
            held, have = (held << 8 | byte) & 0xFFFFFFFFFFFF, have + 8

    def take(n: int) -> int:
        nonlocal have
        need(n)
        have -= n
        return (held >> have) & ((1 << n) - 1)

    def symbol(table) -> int:
        nonlocal have
        need(16)
        code = (held >> (have - 16)) & 0xFFFF
        if not table[1][code]:
            raise ValueError("a code is in no table")
        have -= table[1][code]
        return table[0][code]

    def extended(n: int) -> int:
        bits = take(n) if n else 0
        return bits if not n or bits >> (n - 1) else bits - (1 << n) + 1

    level = [0] * len(planes)
    for unit in range(across * down):
        if frame.restart and unit and unit % frame.restart == 0:
            held = have = 0
            while not (data[at] == 255 and 0xD0 <= data[at + 1] <= 0xD7):
                at += 1
            at, level = at + 2, [0] * len(planes)
        for p, (name, h, v, _) in enumerate(frame.parts):
            dc, ac = tables[frame.tables[name] >> 4], tables[16 | (frame.tables[name] & 15)]
            for block in range(h * v):
                block_row = planes[p][unit // across * v + block // h, unit % across * h + block % h]
                level[p] += extended(symbol(dc))
                block_row[0] = level[p]
                k = 1
                while k < 64:
                    s = symbol(ac)
                    if s == 0:
                        break
                    k += s >> 4
                    if s & 15:
                        block_row[k] = extended(s & 15)
                    k += 1
    out = []
    for p, (_, _, _, q) in enumerate(frame.parts):
        blocks = np.zeros_like(planes[p])
        blocks[..., ZIGZAG] = planes[p] * frame.quantisers[q]
        pixels = basis @ blocks.reshape(*blocks.shape[:2], 8, 8) @ basis.T
        rows, columns = blocks.shape[:2]
        out.append(np.clip(np.rint(pixels + 128), 0, 255).astype(np.uint8).transpose(0, 2, 1, 3).reshape(rows * 8, columns * 8))
    return out


def decode_frames(frames: list) -> list[np.ndarray]:
    """One grey value a block (rows x columns) of every frame; flat rows of like frames decode together."""
    heads = [Frame(f) for f in frames]
    out: list[np.ndarray | None] = [None] * len(frames)
    groups: dict[tuple, list[int]] = {}
    for i, f in enumerate(heads):
        if f.flat_rows():
            groups.setdefault(f.key(), []).append(i)
    for key, members in groups.items():
        rows = decode_flat_rows([heads[i].scan for i in members], key)
        at = 0
        for i in members if rows is not None else ():
            out[i] = rows[at : at + heads[i].height // 8]
            at += heads[i].height // 8
    for i, f in enumerate(heads):
        if out[i] is None:
            plane = decode_frame(f)[0]
            out[i] = plane.reshape(plane.shape[0] // 8, 8, plane.shape[1] // 8, 8).mean((1, 3)).round().astype(np.uint8)
    return out  # type: ignore[return-value]


def shots(pictures: list[np.ndarray]) -> list[int]:
    """First frames of the shots, by adaptive histogram differences."""
    if not pictures:
        return []
    tall = np.array([np.bincount(p.ravel() >> (8 - (BINS - 1).bit_length()), minlength=BINS) / p.size for p in pictures])
    change = np.abs(np.diff(tall, axis=0)).sum(1)
    cuts = [0]
    for t, d in enumerate(change.tolist(), 1):
        recent = change[max(cuts[-1], t - 1 - SHOT_WINDOW) : t - 1]
        limit = max(SHOT_FLOOR, float(recent.mean() + SHOT_DEVIATIONS * recent.std()) if len(recent) > 1 else SHOT_FLOOR)
        if d > limit:
            cuts.append(t)
    return cuts


def store(payloads: list[bytes]) -> list[bytes]:
    """AVI files of payloads (lengths positive multiples of 64); all rows are coded together."""
    rows = np.frombuffer(b"".join(payloads), np.uint8).reshape(-1, ROW)
    counts = [len(p) // ROW for p in payloads]
    markers = np.concatenate([0xD0 + np.arange(n) % ROWS % 8 for n in counts])
    first = np.cumsum([0, *counts])
    for a, b in zip(first, first[1:]):
        markers[a + ROWS - 1 : b : ROWS] = 0xD9
        markers[b - 1] = 0xD9
    stream, ends = code_rows(rows, markers)
    out = []
    for a, b in zip(first.tolist(), first[1:].tolist()):
        frames = []
        for r in range(a, b, ROWS):
            stop = min(r + ROWS, b)
            frames.append(frame_header(stop - r) + stream[int(ends[r - 1]) if r else 0 : int(ends[stop - 1])])
        out.append(write_avi(frames, min(ROWS, b - a)))
    return out


def payload_of(text: bytes) -> bytes:
    return text + b"\0" * (-len(text) % ROW if text else ROW)


def read_back(files: list[bytes]) -> list[tuple[bytes, list[np.ndarray], float]]:
    """Payload, pictures and rate of each file."""
    parsed = [read_avi(f) for f in files]
    pictures = decode_frames([f for frames, _ in parsed for f in frames])
    out, at = [], 0
    for frames, rate in parsed:
        mine = pictures[at : at + len(frames)]
        at += len(frames)
        out.append((b"".join(p.tobytes() for p in mine), mine, rate))
    return out


def _blocks(texts: list[bytes]):
    begin = size = 0
    for i, t in enumerate(texts):
        if i > begin and size + len(t) > BLOCK_BYTES:
            yield begin, i
            begin, size = i, 0
        size += len(t)
    if begin < len(texts):
        yield begin, len(texts)


def _texts(column: pa.Array) -> list[bytes]:
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def media_features(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Store each text as AVI, read it back: sizes, hashes of what was read and stored, and a feature string."""
    src = df.select(df[doc_id].alias("doc_id"), df[text].cast("string").alias("text"))

    def run(batches):
        for batch in slices(batches):
            texts = _texts(batch.column(1))
            for a, b in _blocks(texts):
                files = store([payload_of(t) for t in texts[a:b]])
                rows = []
                for t, f, (payload, pictures, rate) in zip(texts[a:b], files, read_back(files)):
                    cuts = shots(pictures)
                    mean = sum(payload) / len(payload) if len(payload) < 4096 else float(np.frombuffer(payload, np.uint8).mean())
                    feature = f"frames={len(pictures)};seconds={len(pictures) / rate:.2f};shots={len(cuts)};cuts={'.'.join(map(str, cuts[1:]))};mean={mean:.3f}"
                    rows.append((len(t), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]), len(f), hashlib.sha256(f).hexdigest(), feature))
                kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string())
                names = ["n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), *(pa.array(c, k) for c, k in zip(zip(*rows), kinds))], names=["doc_id", *names])

    kind = src.schema["doc_id"].dataType.simpleString()
    return src.mapInArrow(run, f"doc_id {kind}, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string")


def store_media(df: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per row: doc_id, media binary."""
    src = df.select(df[doc_id].alias("doc_id"), df[text].cast("string").alias("text"))

    def run(batches):
        for batch in slices(batches):
            texts = _texts(batch.column(1))
            for a, b in _blocks(texts):
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(store([payload_of(t) for t in texts[a:b]]), pa.binary())], names=["doc_id", "media"])

    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, media binary")


def clips(df: DataFrame, doc_id: str = "doc_id", media: str = "media") -> DataFrame:
    """One row a shot: doc_id, clip, first_frame, n_frames, start_s, end_s. Null media has no clip."""
    src = df.select(df[doc_id].alias("doc_id"), df[media].alias("media")).filter("media is not null")

    def run(batches):
        for batch in slices(batches):
            for i, f in enumerate(batch.column(1).to_pylist()):
                frames, rate = read_avi(f)
                edges = [*shots(decode_frames(frames)), len(frames)]
                rows = [(k, a, b - a, a / rate, b / rate) for k, (a, b) in enumerate(zip(edges, edges[1:]))]
                owner = batch.column(0).take(pa.array([i] * len(rows), pa.int32()))
                kinds = (pa.int32(), pa.int32(), pa.int32(), pa.float64(), pa.float64())
                columns = list(zip(*rows)) or [()] * 5
                yield pa.RecordBatch.from_arrays([owner, *(pa.array(c, k) for c, k in zip(columns, kinds))], names=["doc_id", "clip", "first_frame", "n_frames", "start_s", "end_s"])

    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, clip int, first_frame int, n_frames int, start_s double, end_s double")


def op6_avi_clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_features(table(spark, sf_dir, "documents"))
