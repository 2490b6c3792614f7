"""Benchmark decontamination with an FM-index per training shard.

Each task cuts its documents into shards of a bounded number of indexed words. A
shard's text is its words as symbols: a benchmark word has its own symbol, any other
word ends a run, since no phrase can span it, and runs shorter than the shortest
phrase cannot hold one. Over that text the task builds a suffix array by rank
doubling, the Burrows-Wheeler transform, and a wavelet matrix that answers rank
queries. All phrases are searched backwards together, one array step per word.
Matches are located by walking to sampled suffix positions; overlapping ones merge
into removal spans.

A phrase (window) is ``WINDOW`` consecutive words of a benchmark item, or all words
of a shorter item. The benchmark goes to the tasks in blocks of bounded size, several
to a broadcast of bounded size; a benchmark beyond that takes further passes, which hand
on word flags and items by row, without a shuffle.

Defined cases: null or wordless texts have no words and no hits; items without words
are never found; each input row gives one output row, also when ids or texts repeat;
repeated items are all reported; an item id that is null is left out of the list;
input columns other than id and text are not read.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import slices, table

#: Fixed values of the contract: A-Z is lowered, then these are the words, as UTF-8 bytes and as text.
WORD_BYTES = re.compile(rb"[0-9a-z\x80-\xff]+")
WORD_TEXT = re.compile(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+")
WINDOW = 10
#: Indexed words of a shard (a longer document is a shard of its own), and benchmark words of a block.
SHARD_WORDS, BLOCK_WORDS = 1 << 19, 1 << 20
#: Benchmark words that are broadcast together; a larger benchmark takes more passes over the documents.
PASS_WORDS = 1 << 21
#: Every so many-th suffix position is kept.
SAMPLE = 8


class WaveletMatrix:
    """Rank queries over symbols 0..2**levels-1; each level keeps its bits packed and a count per 64."""

    def __init__(self, symbols: np.ndarray, levels: int) -> None:
        self.n, self.levels = len(symbols), levels
        self.words, self.counts, self.zeros = [], [], []
        for level in range(levels - 1, -1, -1):
            bit = ((symbols >> level) & 1).astype(bool)
            padded = np.zeros((self.n // 64 + 1) * 64, np.uint8)
            padded[: self.n] = bit
            word = np.packbits(padded, bitorder="little").view("<u8")
            self.words.append(word)
            self.counts.append(np.concatenate(([0], np.cumsum(np.bitwise_count(word).astype(np.int64))))[:-1])
            self.zeros.append(self.n - int(np.count_nonzero(bit)))
            symbols = np.concatenate((symbols[~bit], symbols[bit]))

    def _ones(self, k: int, at: np.ndarray) -> np.ndarray:
        word, bit = at >> 6, (at & 63).astype(np.uint64)
        mask = (np.uint64(1) << bit) - np.uint64(1)
        return self.counts[k][word] + np.bitwise_count(self.words[k][word] & mask).astype(np.int64)

    def rank(self, symbol: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Occurrences of each symbol before each position."""
        low = np.zeros_like(at)
        for k in range(self.levels):
            one = (symbol >> (self.levels - 1 - k)) & 1 == 1
            ones_low, ones_at = self._ones(k, low), self._ones(k, at)
            low = np.where(one, self.zeros[k] + ones_low, low - ones_low)
            at = np.where(one, self.zeros[k] + ones_at, at - ones_at)
        return at - low

    def symbol_and_rank(self, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The symbol at each position and its occurrences before it."""
        symbol, low = np.zeros_like(at), np.zeros_like(at)
        for k in range(self.levels):
            word, bit = at >> 6, (at & 63).astype(np.uint64)
            one = (self.words[k][word] >> bit) & np.uint64(1) == 1
            symbol = symbol * 2 + one
            ones_low, ones_at = self._ones(k, low), self._ones(k, at)
            low = np.where(one, self.zeros[k] + ones_low, low - ones_low)
            at = np.where(one, self.zeros[k] + ones_at, at - ones_at)
        return symbol, at - low


def suffix_array(symbols: np.ndarray) -> np.ndarray:
    """Suffix array by rank doubling; symbol 0 ends a run and each of its occurrences is distinct."""
    n = len(symbols)
    ends = np.flatnonzero(symbols == 0)
    rank = symbols.astype(np.int64) + len(ends)
    rank[ends] = np.arange(len(ends))
    step = 1
    while True:
        nxt = np.zeros(n, np.int64)
        if step < n:
            nxt[:-step] = rank[step:] + 1
        key = rank * (n + len(ends) + int(symbols.max(initial=0)) + 3) + nxt
        order = np.argsort(key, kind="stable")
        new = np.empty(n, np.int64)
        new[order] = np.concatenate(([0], np.cumsum(np.diff(key[order]) != 0)))
        rank, step = new, step * 2
        if n == 0 or rank[order[-1]] == n - 1:
            return order


class FMIndex:
    """Over symbols with 0 as the end of each run, the last symbol included."""

    def __init__(self, symbols: np.ndarray, alphabet: int, sample: int = SAMPLE) -> None:
        order = suffix_array(symbols)
        self.n = len(symbols)
        last = symbols[order - 1]
        self.before = np.concatenate(([0], np.cumsum(np.bincount(symbols, minlength=alphabet))))
        self.matrix = WaveletMatrix(last, max(1, int(alphabet - 1).bit_length()))
        kept = (order % sample == 0) | (last == 0)
        padded = np.zeros((self.n // 64 + 1) * 64, np.uint8)
        padded[: self.n] = kept
        self.kept = np.packbits(padded, bitorder="little").view("<u8")
        self.kept_counts = np.concatenate(([0], np.cumsum(np.bitwise_count(self.kept).astype(np.int64))))[:-1]
        self.positions = order[kept]

    def search(self, words: np.ndarray, starts: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Row ranges [low, high) of all phrases, given by place and length in an array of symbols, searched backwards together."""
        low, high = np.zeros(len(starts), np.int64), np.full(len(starts), self.n, np.int64)
        for back in range(1, int(lengths.max(initial=0)) + 1):
            alive = np.flatnonzero((lengths >= back) & (high > low))
            symbol = words[starts[alive] + lengths[alive] - back].astype(np.int64)
            low[alive] = self.before[symbol] + self.matrix.rank(symbol, low[alive])
            high[alive] = self.before[symbol] + self.matrix.rank(symbol, high[alive])
        return low, np.maximum(low, high)

    def locate(self, rows: np.ndarray) -> np.ndarray:
        """Text positions of index rows: step back until a sampled position."""
        out, steps = np.zeros(len(rows), np.int64), np.zeros(len(rows), np.int64)
        live, rows = np.arange(len(rows)), rows.copy()
        while len(live):
            word, bit = rows >> 6, (rows & 63).astype(np.uint64)
            hit = (self.kept[word] >> bit) & np.uint64(1) == 1
            mask = (np.uint64(1) << bit[hit]) - np.uint64(1)
            at = self.kept_counts[word[hit]] + np.bitwise_count(self.kept[word[hit]] & mask).astype(np.int64)
            out[live[hit]] = self.positions[at] + steps[live[hit]]
            live, rows = live[~hit], rows[~hit]
            symbol, rank = self.matrix.symbol_and_rank(rows)
            rows = self.before[symbol] + rank
            steps[live] += 1
        return out


class Phrases:
    """A block of benchmark items: vocabulary, distinct windows, and the items of each window.

    Windows are places in one array of the items' words, and owners one array cut by
    window, so a block takes a few bytes a word beside its vocabulary.
    """

    def __init__(self, items: list[tuple], window: int) -> None:
        self.vocabulary: dict[bytes, int] = {}
        self.items = [str(i) if i is not None else None for i, _ in items]
        coded = [np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words_of(text)], np.int32) for _, text in items]
        self.words = np.concatenate([*coded, np.zeros(0, np.int32)])
        sizes = np.array([len(c) for c in coded], np.int64)
        begin = np.cumsum(sizes) - sizes
        length = np.minimum(sizes, window)
        count = np.where(sizes > 0, sizes - length + 1, 0)
        item = np.repeat(np.arange(len(items)), count)
        start = begin[item] + np.arange(len(item)) - np.repeat(np.cumsum(count) - count, count)
        starts, lengths, owners, owned = [], [], [], 0
        for n in np.unique(length[item]).tolist():
            mine = np.flatnonzero(length[item] == n)
            rows = np.ascontiguousarray(np.lib.stride_tricks.sliding_window_view(self.words, n)[start[mine]])
            _, first, which = np.unique(rows.view(np.dtype((np.void, 4 * n))).ravel(), return_index=True, return_inverse=True)
            starts.append(start[mine][first])
            lengths.append(np.full(len(first), n, np.int64))
            owners.append(np.unique(np.stack((which + owned, item[mine]), 1), axis=0))
            owned += len(first)
        self.starts, self.lengths = (np.concatenate([*x, np.zeros(0, np.int64)]) for x in (starts, lengths))
        pairs = np.concatenate([*owners, np.zeros((0, 2), np.int64)])
        self.owners = pairs[:, 1].astype(np.int32)
        self.owner_at = np.searchsorted(pairs[:, 0], np.arange(owned + 1))
        self.shortest = int(self.lengths.min(initial=window))


def words_of(text: str | None) -> list[bytes]:
    return WORD_BYTES.findall((text or "").encode("utf-8", "surrogatepass").lower())


def item_blocks(benchmark: DataFrame, item_id: str, text: str, window: int, block_words: int, pass_words: int) -> Iterator[list[Phrases]]:
    """The benchmark, row by row to the driver, as groups of blocks: one group goes out at a time."""
    group, items, words, held = [], [], 0, 0
    for row in benchmark.select(benchmark[item_id].cast("string"), benchmark[text].cast("string")).toLocalIterator():
        n = len(words_of(row[1]))
        if items and words + n > block_words:
            group.append(Phrases(items, window))
            held, items, words = held + words, [], 0
            if held >= pass_words:
                yield group
                group, held = [], 0
        items.append((row[0], row[1]))
        words += n
    yield [*group, *([Phrases(items, window)] if items else [])]


def _runs(symbols: np.ndarray, doc: np.ndarray, shortest: int) -> tuple[np.ndarray, np.ndarray]:
    """The runs of known words inside one document that are long enough, each ended by 0, and where each symbol came from."""
    known = symbols > 0
    edge = np.ones(len(symbols) + 1, bool)
    edge[1:-1] = (known[1:] != known[:-1]) | (doc[1:] != doc[:-1])
    starts = np.flatnonzero(edge[:-1])
    sizes = np.diff(np.append(starts, len(symbols)))
    good = known[starts] & (sizes >= shortest)
    starts, sizes = starts[good], sizes[good]
    total = sizes + 1
    first = np.cumsum(total) - total
    where = np.repeat(starts - first, total) + np.arange(int(total.sum()))
    text = np.zeros(len(where), np.int64)
    inside = np.ones(len(where), bool)
    inside[first + sizes] = False
    text[inside] = symbols[where[inside]]
    return text, where


def shard_hits(words: list[list[bytes]], blocks: list[Phrases]) -> tuple[list[np.ndarray], list[list[str]]]:
    """Per document: a flag for each word that an occurrence covers, and the ids of the items found."""
    sizes = np.array([len(w) for w in words], np.int64)
    begin = np.concatenate(([0], np.cumsum(sizes)))
    doc = np.repeat(np.arange(len(words)), sizes)
    cover = np.zeros(int(begin[-1]) + 1, np.int64)
    items: list[set[str]] = [set() for _ in words]
    for block in blocks:
        get = block.vocabulary.get
        symbols = np.fromiter((get(w, 0) for ws in words for w in ws), np.int64, len(doc))
        text, where = _runs(symbols, doc, block.shortest)
        if not len(text):
            continue
        index = FMIndex(text, len(block.vocabulary) + 1)
        low, high = index.search(block.words, block.starts, block.lengths)
        count = high - low
        which = np.repeat(np.arange(len(count)), count)
        rows = np.repeat(low - (np.cumsum(count) - count), count) + np.arange(int(count.sum()))
        at = where[index.locate(rows)]
        np.add.at(cover, at, 1)
        np.add.at(cover, at + block.lengths[which], -1)
        for d, w in set(zip(doc[at].tolist(), which.tolist())):
            items[d].update(i for k in block.owners[block.owner_at[w] : block.owner_at[w + 1]] if (i := block.items[k]) is not None)
    hit = np.cumsum(cover[:-1]) > 0
    return [hit[begin[i] : begin[i + 1]] for i in range(len(words))], [sorted(s) for s in items]


def removal_spans(text: str | None, hit: np.ndarray) -> list[tuple[int, int]]:
    """Merged runs of hit words as code point spans."""
    if not hit.any():
        return []
    spans: list[list[int]] = []
    previous = -2
    for k, m in enumerate(WORD_TEXT.finditer(text or "")):
        if hit[k]:
            if previous == k - 1:
                spans[-1][1] = m.end()
            else:
                spans.append([m.start(), m.end()])
            previous = k
    return [(a, b) for a, b in spans]


def without(text: str | None, spans: list[tuple[int, int]]) -> str | None:
    if not spans:
        return text
    at, out = 0, []
    for a, b in spans:
        out.append(text[at:a])
        at = b
    return "".join([*out, text[at:]])


def _shards(batches, blocks: list[Phrases], first: bool) -> Iterator[tuple]:
    """Slices of the batches (kept columns, text, and after the first pass the state) with texts, word flags and items."""
    for batch in slices(batches):
        at = batch.num_columns - (1 if first else 3)
        texts = batch.column(at).to_pylist()
        begin, words, total = 0, [], 0
        for i, text in enumerate(texts):
            words.append(words_of(text))
            total += len(words[-1])
            if total >= SHARD_WORDS or i == len(texts) - 1:
                hits, items = shard_hits(words, blocks)
                part = batch.slice(begin, i + 1 - begin)
                if not first:
                    before = [np.unpackbits(np.frombuffer(x, np.uint8))[: len(h)].astype(bool) for x, h in zip(part.column(at + 1).to_pylist(), hits)]
                    hits = [h | b for h, b in zip(hits, before)]
                    items = [sorted({*x, *y}) for x, y in zip(items, part.column(at + 2).to_pylist())]
                yield part.select(range(at + 1)), texts[begin : i + 1], hits, items
                begin, words, total = i + 1, [], 0


def _in_passes(src: DataFrame, groups: Iterator[list[Phrases]], finish, schema) -> DataFrame:
    """One pass over ``src`` (text last) a group of blocks; the last ends in ``finish``. Passes hand on flags and items by row."""
    state = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema) + ", __hit binary, __items array<string>"
    frame, first, group = src, True, next(groups)
    while group is not None:
        following = next(groups, None)
        held = src.sparkSession.sparkContext.broadcast(group)

        def run(batches, held=held, first=first, last=following is None):
            for part, texts, hits, items in _shards(batches, held.value, first):
                if last:
                    yield finish(part, texts, hits, items)
                else:
                    more = [pa.array([np.packbits(h).tobytes() for h in hits], pa.binary()), pa.array(items, pa.list_(pa.string()))]
                    yield pa.RecordBatch.from_arrays([*part.columns, *more], names=[*part.schema.names, "__hit", "__items"])

        frame = frame.mapInArrow(run, schema if following is None else state)
        first, group = False, following
    return frame


def find_contamination(df: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = WINDOW, block_words: int = BLOCK_WORDS, pass_words: int = PASS_WORDS) -> DataFrame:
    """Per row: doc_id, n_words, n_hit, items array<string>, spans array<struct<start,end>> (code points)."""
    src = df.select(df[doc_id].alias("doc_id"), df[text].cast("string").alias("text"))
    span = pa.struct([("start", pa.int32()), ("end", pa.int32())])

    def finish(part, texts, hits, items):
        spans = [[{"start": a, "end": b} for a, b in removal_spans(t, h)] for t, h in zip(texts, hits)]
        return pa.RecordBatch.from_arrays(
            [part.column(0), pa.array([len(h) for h in hits], pa.int64()), pa.array([int(h.sum()) for h in hits], pa.int64()), pa.array(items, pa.list_(pa.string())), pa.array(spans, pa.list_(span))],
            names=["doc_id", "n_words", "n_hit", "items", "spans"],
        )

    schema = f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n_words long, n_hit long, items array<string>, spans array<struct<start:int,end:int>>"
    return _in_passes(src, item_blocks(benchmark, item_id, item_text, window, block_words, pass_words), finish, schema)


def remove_contamination(df: DataFrame, benchmark: DataFrame, text: str = "text", item_id: str = "item_id", item_text: str = "text", window: int = WINDOW, block_words: int = BLOCK_WORDS, pass_words: int = PASS_WORDS) -> DataFrame:
    """The same rows and columns with every removal span cut out of the text."""
    src = df.select(*[c for c in df.columns if c != text], text)

    def finish(part, texts, hits, _):
        clean = [without(t, removal_spans(t, h)) for t, h in zip(texts, hits)]
        return pa.RecordBatch.from_arrays([*part.columns[:-1], pa.array(clean, pa.string())], schema=part.schema)

    return _in_passes(src, item_blocks(benchmark, item_id, item_text, window, block_words, pass_words), finish, src.schema).select(*df.columns)


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    items = F.array_join(F.array_sort("items"), ",")
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(items, 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


_CUT = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"
#: DuckDB: every window of every text as a string, joined with the items' windows.
ORACLE_SQL = f"""
with d as (select row_number() over () as row_id, doc_id, {_CUT} as w from documents),
b as (select cast(item_id as varchar) as item_id, {_CUT} as w, least({WINDOW}, len(w)) as n from benchmark),
known as (select distinct item_id, n, array_to_string(w[i : i + n - 1], ' ') as win from b, unnest(range(1, len(w) - n + 2)) t(i) where n > 0),
sizes as (select distinct n from known),
cut as (select row_id, n, i, array_to_string(w[i : i + n - 1], ' ') as win from d, sizes, unnest(range(1, len(w) - n + 2)) t(i)),
met as (select row_id, i, cut.n, item_id from cut join known on cut.win = known.win and cut.n = known.n),
hits as (select row_id, count(distinct p) as n_hit from (select distinct row_id, i, n from met) x, unnest(range(i, i + n)) u(p) group by row_id),
found as (select row_id, count(distinct item_id) as n_items, array_to_string(list_sort(list(distinct item_id)), ',') as ids from met group by row_id)
select doc_id, cast(len(w) as bigint) as n_words, coalesce(n_hit, 0) as n_hit, coalesce(n_items, 0) as n_items, sha256(coalesce(ids, '')) as items_sha256, coalesce(n_hit, 0) > 0 as contaminated
from d left join hits using (row_id) left join found using (row_id)
"""


def brute_force(text: str | None, items: list[tuple], window: int = WINDOW) -> tuple[int, int, list[str]]:
    """For tests: words, hit words and items found, by comparing every window."""
    words = [w for w in words_of(text)]
    hit, found = [False] * len(words), set()
    for i, t in items:
        want = words_of(t)
        n = min(window, len(want))
        windows = {tuple(want[k : k + n]) for k in range(len(want) - n + 1)} if want else set()
        for k in range(len(words) - n + 1) if want else ():
            if tuple(words[k : k + n]) in windows:
                hit[k : k + n] = [True] * n
                found.add(str(i))
    return len(words), sum(hit), sorted(found)


def items_digest(items: list[str]) -> str:
    return hashlib.sha256(",".join(items).encode()).hexdigest()
