"""Byte-level BPE encoding and decoding with vectorised pre-tokenisation.

Text is cut without a regular expression. Every code point maps to a class by one
table lookup over an array; a class acts as a transition function on the states of a
small automaton, whose states also follow a contraction letter by letter. Functions
compose associatively, and the closure of the classes under composition is a small
monoid, so a composed function is one number and composing two arrays of functions is
one lookup. An associative scan (pairs, the pairs' scan, the rest) gives the function of
every prefix, hence the state before every code point; that state and the class say
whether a piece starts here, or, where white space or half a contraction is only known
by what follows, whether one started one code point before. The first class of a text is
a constant function, so texts lie one after another in an array. The slices go through a
cache of merged pieces; cache entries index into one pool of ids, and a document's ids
are gathered from the pool by array arithmetic. Ids keep their byte offsets (the running
sum of token lengths).

Defined cases: null and empty texts have no ids; each input row gives one output
row, repeated rows too; a text of any length is cut in one pass, and a single piece
of any length is merged in O(n log n) with a heap. Columns other than the id and the
text are not read.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import sys
import unicodedata
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import slices, table

# Classes: contraction letters that end one alone, or begin or end one of two; the rest by category.
ENDS_ONE, L, V_OR_R, E, LETTER, NUMBER, OTHER, QUOTE, WHITE, SPACE = range(10)
#: Classes of the first code point of a text are raised by this; the class after all texts is END.
FIRST = 10
END = 2 * FIRST
# States: what the piece is so far. A quote may begin a contraction, and l, v or r may go on with it.
(NOTHING, IN_LETTERS, IN_NUMBERS, IN_OTHER, AT_QUOTE, QUOTE_L, QUOTE_V_OR_R, CONTRACTED, ONE_SPACE, ONE_WHITE, ENDS_IN_SPACE, ENDS_IN_WHITE) = range(12)
STATES = 12
#: The code points of Unicode's White_Space property.
WHITE_SPACE = [*range(0x9, 0xE), 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
#: What follows the apostrophe of a contraction is s, t, m, d, ll, ve or re.
CONTRACTION_CLASSES = {"s": ENDS_ONE, "t": ENDS_ONE, "m": ENDS_ONE, "d": ENDS_ONE, "l": L, "v": V_OR_R, "r": V_OR_R, "e": E}
#: Entries of a worker's cache of pieces, and the longest piece kept, in code points.
CACHE_PIECES, CACHE_CHARS = 300_000, 64
#: Characters that are cut and encoded together.
BLOCK_CHARS = 1 << 19


def step(state: int, kind: int) -> tuple[int, bool, bool]:
    """What a class does in a state: the next state, and whether a piece starts here, or at the code point before."""
    if kind == END:
        return NOTHING, False, state in (QUOTE_L, QUOTE_V_OR_R)
    if kind >= FIRST:
        return step(NOTHING, kind - FIRST)[0], True, state in (QUOTE_L, QUOTE_V_OR_R)
    letter = kind <= LETTER
    fresh = IN_LETTERS if letter else {NUMBER: IN_NUMBERS, OTHER: IN_OTHER, QUOTE: AT_QUOTE, WHITE: ONE_WHITE, SPACE: ONE_SPACE}[kind]
    if state in (QUOTE_L, QUOTE_V_OR_R):
        if kind == (L if state == QUOTE_L else E):
            return CONTRACTED, False, False
        # no contraction: the letter after the quote began a piece, and goes on from there
        state, here, _ = step(IN_LETTERS, kind)
        return state, here, True
    if state in (NOTHING, CONTRACTED):
        return fresh, True, False
    if state == AT_QUOTE:
        if kind == ENDS_ONE:
            return CONTRACTED, False, False
        if kind in (L, V_OR_R):
            return (QUOTE_L if kind == L else QUOTE_V_OR_R), False, False
        state = IN_OTHER
    if state in (ONE_SPACE, ONE_WHITE, ENDS_IN_SPACE, ENDS_IN_WHITE):
        if kind in (WHITE, SPACE):
            return (ENDS_IN_SPACE if kind == SPACE else ENDS_IN_WHITE), False, False
        # of a run of white space the last one stands apart, and a space is taken along by what follows
        long = state in (ENDS_IN_SPACE, ENDS_IN_WHITE)
        if state in (ONE_SPACE, ENDS_IN_SPACE):
            return (IN_OTHER if kind == QUOTE else fresh), False, long
        return fresh, True, long
    inside = {IN_LETTERS: letter, IN_NUMBERS: kind == NUMBER, IN_OTHER: kind in (OTHER, QUOTE)}[state]
    return (state, False, False) if inside else (fresh, True, False)


def _transition_monoid() -> dict[str, np.ndarray]:
    """All functions that sequences of classes act by: ids of the classes', the table of compositions, and each one's state from the start."""
    letters = [tuple(step(s, k)[0] for s in range(STATES)) for k in range(END + 1)]
    ids: dict[tuple, int] = {}
    for f in letters:
        ids.setdefault(f, len(ids))
    members = list(ids)
    for f in members:
        for g in letters:
            both = tuple(g[s] for s in f)
            if both not in ids:
                ids[both] = len(ids)
                members.append(both)
    table = np.array([[ids[tuple(g[s] for s in f)] for g in members] for f in members], np.uint16)
    out = [step(s, k) for s in range(STATES) for k in range(END + 1)]
    return {
        "function": np.array([ids[f] for f in letters], np.uint16),
        "compose": table.ravel(),
        "state": np.array([f[NOTHING] for f in members], np.uint8),
        "here": np.array([x[1] for x in out]),
        "earlier": np.array([x[2] for x in out]),
    }


_tables: dict[str, np.ndarray] = {}


def classes() -> np.ndarray:
    """Class of every code point."""
    if "class" not in _tables:
        kinds = {"L": LETTER, "N": NUMBER}
        out = np.fromiter((kinds.get(unicodedata.category(chr(i))[0], OTHER) for i in range(sys.maxunicode + 1)), np.uint8, sys.maxunicode + 1)
        out[WHITE_SPACE] = WHITE
        out[0x20] = SPACE
        out[0x27] = QUOTE
        for letter, kind in CONTRACTION_CLASSES.items():
            out[ord(letter)] = kind
        _tables.update(_transition_monoid())
        _tables["class"] = out
    return _tables["class"]


def scan(functions: np.ndarray) -> np.ndarray:
    """The composition of every prefix of an array of function ids: neighbours first, then the scan of the pairs."""
    n = len(functions)
    if n < 2:
        return functions
    compose, members = _tables["compose"], len(_tables["state"])
    even, odd = functions[: n // 2 * 2 : 2], functions[1::2]
    pairs = scan(compose.take(even.astype(np.int32) * members + odd))
    out = np.empty_like(functions)
    out[0], out[1::2] = functions[0], pairs
    rest = functions[2::2]
    out[2::2] = compose.take(pairs[: len(rest)].astype(np.int32) * members + rest)
    return out


def cuts(points: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Start positions of the pieces of concatenated texts; ``first`` holds the texts' starts (non-empty texts)."""
    kinds = np.empty(len(points) + 1, np.uint8)
    classes().take(points, out=kinds[:-1])
    kinds[first] += FIRST
    kinds[-1] = END
    place = np.zeros(len(kinds), np.int16)
    place[1:] = _tables["state"].take(scan(_tables["function"].take(kinds[:-1])))
    place *= END + 1
    place += kinds
    start = _tables["here"].take(place)
    start[:-1] |= _tables["earlier"].take(place[1:])
    return np.flatnonzero(start[:-1])


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in lines if line.strip())}


class Codec:
    """Encoder and decoder by a rank file; one is kept in each Python worker."""

    def __init__(self, path: str) -> None:
        self.ranks = load_ranks(path)
        self.tokens = [b""] * (max(self.ranks.values()) + 1)
        for token, rank in self.ranks.items():
            self.tokens[rank] = token
        self.lengths = np.array([len(t) for t in self.tokens], np.int64)
        self._clear()

    def _clear(self) -> None:
        self.cache = _Pieces(self)
        self.pool = np.zeros(1 << 16, np.uint32)
        self.at = np.zeros(1 << 14, np.int64)
        self.size = np.zeros(1 << 14, np.int64)
        self.used = self.entries = 0

    def merge(self, piece: bytes) -> list[int]:
        """Merge adjacent pairs, lowest rank first, leftmost among equals."""
        ranks = self.ranks
        if piece in ranks:
            return [ranks[piece]]
        if len(piece) > 96:
            return self._merge_long(piece)
        parts = [piece[i : i + 1] for i in range(len(piece))]
        pairs = [ranks.get(parts[i] + parts[i + 1], 1 << 30) for i in range(len(parts) - 1)]
        while pairs:
            low = min(pairs)
            if low == 1 << 30:
                break
            i = pairs.index(low)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del pairs[i]
            if i < len(pairs):
                pairs[i] = ranks.get(parts[i] + parts[i + 1], 1 << 30)
            if i:
                pairs[i - 1] = ranks.get(parts[i - 1] + parts[i], 1 << 30)
        return [ranks[p] for p in parts]

    def _merge_long(self, piece: bytes) -> list[int]:
        ranks, n = self.ranks, len(piece)
        parts: list[bytes | None] = [piece[i : i + 1] for i in range(n)]
        left, right = list(range(-1, n - 1)), list(range(1, n + 1))
        heap = [(r, i, parts[i] + parts[i + 1]) for i in range(n - 1) if (r := ranks.get(parts[i] + parts[i + 1])) is not None]
        heapq.heapify(heap)
        while heap:
            _, i, pair = heapq.heappop(heap)
            j = right[i]
            if parts[i] is None or j >= n or parts[i] + parts[j] != pair:
                continue
            parts[i], parts[j], right[i] = pair, None, right[j]
            if right[i] < n:
                left[right[i]] = i
            for a, b in ((left[i], i), (i, right[i])):
                if a >= 0 and b < n and (r := ranks.get(parts[a] + parts[b])) is not None:
                    heapq.heappush(heap, (r, a, parts[a] + parts[b]))
        return [ranks[p] for p in parts if p is not None]

    def add(self, piece: str) -> int:
        """Append a piece's ids to the pool; its entry."""
        ids = self.merge(piece.encode("utf-8", "surrogatepass"))
        if self.used + len(ids) > len(self.pool):
            self.pool = np.append(self.pool, np.zeros(max(len(self.pool), len(ids)), np.uint32))
        if self.entries == len(self.at):
            self.at, self.size = (np.append(x, np.zeros(len(x), np.int64)) for x in (self.at, self.size))
        self.pool[self.used : self.used + len(ids)] = ids
        self.at[self.entries], self.size[self.entries] = self.used, len(ids)
        self.used += len(ids)
        self.entries += 1
        return self.entries - 1

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and where each text's ids begin (with the end)."""
        if self.entries > CACHE_PIECES:
            self._clear()
        lengths = np.fromiter(map(len, texts), np.int64, len(texts))
        whole = "".join(texts)
        bounds = np.concatenate(([0], np.cumsum(lengths)))
        if not whole:
            return np.zeros(0, np.uint32), np.zeros(len(texts) + 1, np.int64)
        points = np.frombuffer(whole.encode("utf-32-le", "surrogatepass"), np.uint32)
        starts = cuts(points, bounds[:-1][lengths > 0])
        edges = [*starts.tolist(), len(whole)]
        entry = np.fromiter(map(self.cache.__getitem__, [whole[a:b] for a, b in zip(edges, edges[1:])]), np.int64, len(starts))
        size = self.size[entry]
        ends = np.cumsum(size)
        ids = self.pool[np.repeat(self.at[entry] - (ends - size), size) + np.arange(int(ends[-1]))]
        pieces_before = np.searchsorted(starts, bounds)
        return ids, np.concatenate(([0], ends))[pieces_before]

    def offsets(self, ids: np.ndarray) -> np.ndarray:
        """Byte offset of each token, and the end."""
        return np.concatenate(([0], np.cumsum(self.lengths[ids])))

    def decode(self, ids) -> bytes:
        return b"".join(map(self.tokens.__getitem__, ids))


class _Pieces(dict):
    """From a piece to its entry; long pieces are merged anew each time."""

    def __init__(self, codec: Codec) -> None:
        self.codec = codec

    def __missing__(self, piece: str) -> int:
        entry = self.codec.add(piece)
        if len(piece) <= CACHE_CHARS:
            self[piece] = entry
        return entry


_codecs: dict[str, Codec] = {}


def codec(path: str) -> Codec:
    if path not in _codecs:
        _codecs[path] = Codec(path)
    return _codecs[path]


def blocks(texts: list[str]) -> Iterator[tuple[int, int]]:
    """Ranges of texts of about BLOCK_CHARS together; a longer text stands alone."""
    begin = chars = 0
    for i, text in enumerate(texts):
        if i > begin and chars + len(text) > BLOCK_CHARS:
            yield begin, i
            begin, chars = i, 0
        chars += len(text)
    if begin < len(texts):
        yield begin, len(texts)


def vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def encode_documents(df: DataFrame, doc_id: str = "doc_id", text: str = "text", path: str | None = None) -> DataFrame:
    """Per row: the id, ``ids`` array<int>, ``offsets`` array<long> (byte where each token begins)."""
    path = path or vocabulary()
    src = df.select(df[doc_id].alias("doc_id"), df[text].cast("string").alias("text"))

    def run(batches):
        tool = codec(path)
        for batch in slices(batches):
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for a, b in blocks(texts):
                ids, bounds = tool.encode(texts[a:b])
                parts = [ids[bounds[i] : bounds[i + 1]] for i in range(b - a)]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(a, b - a), pa.array([p.astype(np.int32) for p in parts], pa.list_(pa.int32())), pa.array([tool.offsets(p)[:-1] for p in parts], pa.list_(pa.int64()))],
                    names=["doc_id", "ids", "offsets"],
                )

    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, ids array<int>, offsets array<long>")


def decode_documents(df: DataFrame, doc_id: str = "doc_id", ids: str = "ids", path: str | None = None) -> DataFrame:
    """Per row: the id and ``decoded`` binary."""
    path = path or vocabulary()
    src = df.select(df[doc_id].alias("doc_id"), df[ids].alias("ids"))

    def run(batches):
        tool = codec(path)
        for batch in slices(batches):
            decoded = pa.array([tool.decode(x or ()) for x in batch.column(1).to_pylist()], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column(0), decoded], names=["doc_id", "decoded"])

    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, decoded binary")


def encode_digests(df: DataFrame, doc_id: str = "doc_id", text: str = "text", path: str | None = None) -> DataFrame:
    """Encode, then decode the ids in the same task: doc_id, n_tokens, ids_sha256, decoded_sha256."""
    path = path or vocabulary()
    src = df.select(df[doc_id].alias("doc_id"), df[text].cast("string").alias("text"))

    def run(batches):
        tool = codec(path)
        for batch in slices(batches):
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for a, b in blocks(texts):
                ids, bounds = tool.encode(texts[a:b])
                coded = memoryview(ids.astype("<u4")).cast("B")
                listed, edges = ids.tolist(), bounds.tolist()
                pairs = list(zip(edges, edges[1:]))
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(a, b - a),
                        pa.array([y - x for x, y in pairs], pa.int64()),
                        pa.array([hashlib.sha256(coded[4 * x : 4 * y]).hexdigest() for x, y in pairs], pa.string()),
                        pa.array([hashlib.sha256(tool.decode(listed[x:y])).hexdigest() for x, y in pairs], pa.string()),
                    ],
                    names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
                )

    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def op7_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_digests(table(spark, sf_dir, "documents"))
