"""N-gram Jaccard join by a blocked sparse product, and the components of its links.

A document's set holds the 64-bit hashes of its distinct five-word shingles. Equal
sets are one class from the start. The join multiplies the class-by-shingle incidence
matrix with its transpose, in blocks of columns (hash partitions of the shingles):
rows of a column meet, their products are summed by pair, and bounds that follow from
the two sizes discard pairs early:

* a class brings only ``n - ceil(0.8 n) + 1`` columns, the rarest by a corpus-wide
  order, since two sets that link must share one of these;
* sizes must allow the similarity;
* rarer columns that no other class brings leave so much less to share;
* the summed overlap plus what can still follow after the last shared column must
  reach the overlap that both sizes demand.

What remains is compared in full, on the whole sets.

The order needs no exact counts, any order of shingles that all tasks share is right.
It is the count of a hash bucket over the whole corpus, on a scale of logarithms (one byte
a bucket), so that passages which many documents share come last. The table has about as
many buckets as the corpus has rows, between two bounds.

A first pass pairs each class only with the leader of its column; the components of
those links are contracted, and the second pass compares only classes of different
components, so a large group of near copies costs a pair or two a member, and no link
between components is lost. What the second pass compares inside a column is the product
of its components beside the largest with all its classes; the bounds are part of that
join, so few of these are emitted. Columns, and classes with many partners, that hold a
large share of the rows are dealt over several tasks.

A set is known by 64 bits of one hash. A second hash shows where two sets share these;
both then get new ids from both hashes, so sets are told apart by 128 bits.

Defined cases: null, empty and wordless texts have an empty set (n_shingles 0), link
with nothing and are their own component; rows may repeat, each gives one row; a row
with null id takes part and gets the component of its set; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import batch_bounds, discard, hot_keys, materialise, salted_join, slices, table

WORDS, PERCENT = 5, 80
#: Bits of the least and the largest table of the corpus-wide order, of its blocks, and of the filter that spares sets without a candidate.
ORDER_BITS, BLOCK_BITS, FILTER_BITS = (18, 24), 14, 24
CHUNK = 1 << 20
#: White space bytes of the contract.
WHITE = [0x20, *range(0x09, 0x0E)]

_state: dict[str, np.ndarray] = {}


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _byte_tables(length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Value and white flag by byte (A-Z lowered), and powers of an odd base with their inverses."""
    if "value" not in _state:
        lowered = np.arange(256, dtype=np.uint64)
        lowered[65:91] += np.uint64(32)
        _state["value"] = _mix(lowered + np.uint64(0x51ED2701))
        white = np.zeros(256, bool)
        white[WHITE] = True
        _state["white"] = white
    if len(_state.get("power", ())) < length + 1:
        base = 0x9E3779B97F4A7C15
        for name, b in (("power", base), ("inverse", pow(base, -1, 1 << 64))):
            _state[name] = np.concatenate(([np.uint64(1)], np.cumprod(np.full(max(length, CHUNK), b, np.uint64))))
    return _state["value"], _state["white"], _state["power"], _state["inverse"]


def hash_words(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash and start of every word of a byte array, in chunks cut at white space."""
    hashes, starts, at = [], [], 0
    white_of = _byte_tables(0)[1]
    while at < len(data):
        stop = min(len(data), at + CHUNK)
        while stop < len(data):
            back = np.flatnonzero(white_of[data[at:stop]][::-1][: 1 << 16])
            if len(back):
                stop -= int(back[0])
                break
            more = np.flatnonzero(white_of[data[stop : stop + CHUNK]])
            stop = stop + int(more[0]) + 1 if len(more) else min(len(data), stop + CHUNK)
        part = data[at:stop]
        value, white, power, inverse = _byte_tables(len(part))
        blank = np.concatenate(([True], white[part], [True]))
        edge = np.flatnonzero(blank[1:] != blank[:-1])
        first, last = edge[::2], edge[1::2]
        sums = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(value[part] * power[: len(part)], out=sums[1:])
        hashes.append(_mix((sums[last] - sums[first]) * inverse[first] + (last - first).astype(np.uint64)))
        starts.append(first + at)
        at = stop
    if not hashes:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return np.concatenate(hashes), np.concatenate(starts)


def shingle_sets(column: pa.Array, words: int = WORDS) -> list[np.ndarray]:
    """Per text the sorted distinct shingle hashes, uint64."""
    column = column.cast(pa.large_string()) if column.type != pa.large_string() else column
    if column.null_count:
        column = column.fill_null("")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    out: list[np.ndarray] = []
    i = 0
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + CHUNK, "right")) - 1)
        j = min(j, len(column))
        size = int(offsets[j] - offsets[i])
        raw = np.frombuffer(column.buffers()[2], np.uint8, size, int(offsets[i])) if size else np.zeros(0, np.uint8)
        own = offsets[i : j + 1] - offsets[i]
        # one blank after each text, so that words end with it
        data = np.full(size + j - i, 32, np.uint8)
        keep = np.ones(len(data), bool)
        keep[own[1:] + np.arange(j - i)] = False
        data[keep] = raw
        hashes, starts = hash_words(data)
        bounds = np.searchsorted(starts, own + np.arange(j - i + 1))
        spread = np.uint64(0xD6E8FEB86659FD93)
        if len(hashes) >= words:
            rolled = hashes[: len(hashes) - words + 1].copy()
            for k in range(1, words):
                rolled = rolled * spread + hashes[k : len(hashes) - words + 1 + k]
            rolled = _mix(rolled)
        for a, b in zip(bounds.tolist(), bounds[1:].tolist()):
            if b - a >= words:
                out.append(np.unique(rolled[a : b - words + 1]))
            elif b > a:
                whole = np.uint64(b - a)
                for h in hashes[a:b]:
                    whole = np.uint64((int(whole) * int(spread) + int(h)) & (2**64 - 1))
                out.append(_mix(np.array([whole])))
            else:
                out.append(np.zeros(0, np.uint64))
        i = j
    return out


def _set_hash(s: np.ndarray, seed: int) -> int:
    with np.errstate(over="ignore"):
        total = _mix(s + np.uint64(seed)).sum(dtype=np.uint64) + np.uint64(len(s)) * np.uint64(0x9E3779B97F4A7C15)
    return int(_mix(np.array([total]))[0])


def set_id(s: np.ndarray, again: frozenset = frozenset(), bits: int = 64) -> tuple[int, int]:
    """Identity of a whole set, and a second hash (both signed). ``again``: ids that several sets had; they get others."""
    one, two = _set_hash(s, 0x2545F4914F6CDD1D) >> (64 - bits), _set_hash(s, 0x6C62272E07BB0142)
    if one in again:
        one = int(_mix(np.array([one ^ two], np.uint64))[0])
    return one - (one >> 63 << 64), two - (two >> 63 << 64)


def _summed_blocks(rows: DataFrame, dtype: str) -> list[tuple[int, bytes]]:
    """Sum (or or, for bits) the arrays of each block in two steps; the result has a fixed size."""

    def combine(pdf):
        arrays = [np.frombuffer(x, dtype) for x in pdf["data"]]
        total = np.bitwise_or.reduce(arrays) if dtype == "u1" else np.sum(arrays, axis=0, dtype=dtype)
        first = pdf.iloc[:1]
        return first.assign(data=[total.tobytes()])

    half = rows.groupBy("block", "lane").applyInPandas(combine, "block int, lane int, data binary")
    whole = half.groupBy("block").applyInPandas(combine, "block int, lane int, data binary")
    with batch_bounds(rows.sparkSession):
        return [(r["block"], bytes(r["data"])) for r in whole.collect()]


def order_bits(rows: int) -> int:
    """Bits of the order's table for a corpus of so many rows."""
    return min(max(int(rows).bit_length(), ORDER_BITS[0]), ORDER_BITS[1])


def corpus_order(texts: DataFrame, words: int, bits: int | None = None) -> np.ndarray:
    """How many shingles of the whole corpus fall into each hash bucket, as 8 times the logarithm to base 2."""
    bits = bits or order_bits(texts.count())
    width = 1 << BLOCK_BITS

    def count(batches):
        import pyspark

        total = np.zeros(1 << bits, np.uint32)
        for batch in slices(batches):
            for s in shingle_sets(batch.column(0), words):
                np.add.at(total, (s >> np.uint64(64 - bits)).astype(np.int64), np.uint32(1))
        lane = pyspark.TaskContext.get().partitionId() % 1024
        some = [b for b in range(len(total) // width) if total[b * width : (b + 1) * width].any()]
        yield pa.RecordBatch.from_arrays(
            [pa.array(some, pa.int32()), pa.array([lane] * len(some), pa.int32()), pa.array([total[b * width : (b + 1) * width].astype("u8").tobytes() for b in some], pa.binary())],
            names=["block", "lane", "data"],
        )

    out = np.zeros(1 << bits, np.uint8)
    for block, data in _summed_blocks(texts.mapInArrow(count, "block int, lane int, data binary"), "u8"):
        out[block * width : (block + 1) * width] = np.minimum(8 * np.log2(np.frombuffer(data, "u8") + 1.0), 255)
    return out


def _least(n: np.ndarray | int, percent: int):
    """Smallest overlap that a set of this size has with any partner it links to."""
    return -(-n * percent // 100)


def _sets_with_prefix(docs: DataFrame, order: np.ndarray, words: int, percent: int, again: frozenset, id_bits: int) -> DataFrame:
    """Per row: doc_id, n, sid (identity of the set), check (its second hash), prefix (its rarest shingles, in order), and its last one's place in the order."""
    held = docs.sparkSession.sparkContext.broadcast(order)
    bits = int(len(order)).bit_length() - 1

    def run(batches):
        counts = held.value
        for batch in slices(batches):
            sets = shingle_sets(batch.column(1), words)
            prefixes, ends = [], []
            for s in sets:
                keep = len(s) - _least(len(s), percent) + 1 if len(s) else 0
                rank = np.lexsort((s, counts[(s >> np.uint64(64 - bits)).astype(np.int64)]))[:keep]
                prefixes.append(s[rank].view(np.int64))
                last = s[rank[-1:]]
                ends.append((int(counts[(last >> np.uint64(64 - bits)).astype(np.int64)][0]), int((last ^ np.uint64(1 << 63)).view(np.int64)[0])) if keep else (0, 0))
            ids = [set_id(s, again, id_bits) for s in sets]
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array([len(s) for s in sets], pa.int32()), pa.array([i for i, _ in ids], pa.int64()), pa.array([c for _, c in ids], pa.int64()), pa.array(prefixes, pa.list_(pa.int64())), pa.array([e[0] for e in ends], pa.int64()), pa.array([e[1] for e in ends], pa.int64())],
                names=["doc_id", "n", "sid", "check", "prefix", "end_count", "end_hash"],
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n int, sid long, check long, prefix array<long>, end_count long, end_hash long")


def _identified(docs: DataFrame, words: int, percent: int, id_bits: int) -> tuple[DataFrame, frozenset]:
    """The rows with their sets' ids, written, and the ids that were not unique at first (none, or a few at 10**10 sets)."""
    order, again = corpus_order(docs.select("text"), words), frozenset()
    while True:
        rows = materialise(_sets_with_prefix(docs, order, words, percent, again, id_bits))
        shared = rows.filter("n > 0").groupBy("sid").agg(F.min("check").alias("low"), F.max("check").alias("high")).filter("low <> high")
        twice = [r["sid"] for r in shared.select("sid").collect()]
        if not twice:
            return rows.drop("check"), again
        again |= frozenset(i & (2**64 - 1) for i in twice)
        discard(rows)


def _possible(percent: int):
    """Whether the summed overlap c and the rest after the last shared column can reach the similarity."""
    rest = F.least(F.col("n_a") - F.col("pos_a") - 1, F.col("n_b") - F.col("pos_b") - 1)
    return (100 + percent) * (F.col("c") + rest) >= percent * (F.col("n_a") + F.col("n_b"))


def _sizes_fit(percent: int):
    return 100 * F.least("n_a", "n_b") >= percent * F.greatest("n_a", "n_b")


def _with_unshared(postings: DataFrame, percent: int) -> DataFrame:
    """Per class what bounds its overlap with any other.

    ``alone``: columns of its prefix that no other class brings. ``bits_k``: its shared
    columns, as 256 hash bits.
    """
    by_class = Window.partitionBy("sid")
    bit = lambda k: F.when(F.shiftrightunsigned("h", 6).bitwiseAND(3) == k, F.expr("shiftleft(1L, cast(h & 63 as int))")).otherwise(F.lit(0).cast("long"))
    columns = F.col("n") - F.ceil(F.col("n") * percent / 100) + 1
    return postings.select("h", "sid", "n", "pos", "comp", "end_count", "end_hash", (columns - F.count(F.lit(1)).over(by_class)).cast("int").alias("alone"), *[F.bit_or(bit(k)).over(by_class).alias(f"bits{k}") for k in range(4)])


def _unshared_allows(percent: int):
    """Whether the columns that one side cannot share leave enough overlap.

    It holds for the side whose prefix ends first in the corpus order: had the other set
    one of its columns, the other's prefix would have it too. A bit that only one side has
    is a column, or several, that only that side has.
    """

    def left(x: str, y: str):
        only = sum((F.bit_count(F.col(f"bits{k}_{x}").bitwiseAND(F.bitwise_not(f"bits{k}_{y}"))) for k in range(4)), F.lit(0))
        return F.col(f"n_{x}") - F.col(f"alone_{x}") - only

    ends_first = F.expr("end_count_a < end_count_b or (end_count_a = end_count_b and end_hash_a <= end_hash_b)")
    return (100 + percent) * F.when(ends_first, left("a", "b")).otherwise(left("b", "a")) >= percent * (F.col("n_a") + F.col("n_b"))


def _summed(products: DataFrame, percent: int) -> DataFrame:
    """Sum the products of each pair over the columns and discard by the bounds."""
    turned = F.col("a") > F.col("b")
    ordered = [F.when(turned, F.col(f"{c}{y}")).otherwise(F.col(f"{c}{x}")).alias(f"{c}{x}") for c in ("", "n_", "pos_") for x, y in (("a", "b"), ("b", "a"))]
    pairs = products.filter(_sizes_fit(percent)).select(*ordered).groupBy("a", "b", "n_a", "n_b").agg(F.count(F.lit(1)).alias("c"), F.max("pos_a").alias("pos_a"), F.max("pos_b").alias("pos_b"))
    return pairs.filter(_possible(percent)).select("a", "b")


def _wanted_filter(ids: DataFrame, bits: int = FILTER_BITS) -> np.ndarray:
    """Bit table of fixed size with a bit for each id; a stray bit only costs an unneeded set."""
    width = 1 << (bits - 9)

    def mark(pdf):
        out = np.zeros(width // 8, np.uint8)
        slot = pdf["slot"].to_numpy()
        np.bitwise_or.at(out, slot >> 3, (1 << (slot & 7)).astype(np.uint8))
        first = pdf.iloc[:1]
        return first.assign(data=[out.tobytes()])[["block", "lane", "data"]]

    slots = ids.select(F.shiftrightunsigned("id", 64 - bits).alias("at")).select((F.col("at") / width).cast("int").alias("block"), (F.col("at") % width).cast("int").alias("slot")).distinct()
    rows = slots.withColumn("lane", F.lit(0)).groupBy("block").applyInPandas(mark, "block int, lane int, data binary")
    out = np.zeros((1 << bits) // 8, np.uint8)
    for r in rows.collect():
        out[r["block"] * width // 8 : (r["block"] + 1) * width // 8] = np.frombuffer(r["data"], np.uint8)
    return out


def _full_sets(docs: DataFrame, pairs: DataFrame, words: int, again: frozenset, id_bits: int) -> DataFrame:
    """(sid, hashes) of the sets that occur in pairs, cut again from the texts."""
    ids = pairs.select(F.explode(F.array("a", "b")).alias("id"))
    held = docs.sparkSession.sparkContext.broadcast(_wanted_filter(ids))

    def run(batches):
        wanted, seen = held.value, set()
        for batch in slices(batches):
            ids, data = [], []
            for s in shingle_sets(batch.column(0), words):
                sid = set_id(s, again, id_bits)[0]
                slot = (sid & (2**64 - 1)) >> (64 - FILTER_BITS)
                if len(s) and wanted[slot >> 3] >> (slot & 7) & 1 and sid not in seen:
                    seen.add(sid)
                    ids.append(sid)
                    data.append(s.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(data, pa.binary())], names=["sid", "hashes"])

    found = docs.select("text").mapInArrow(run, "sid long, hashes binary")
    return found.groupBy("sid").agg(F.first("hashes").alias("hashes"))


def _links(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs whose whole sets are similar enough."""
    side = lambda x: sets.select(F.col("sid").alias(x), F.col("hashes").alias(f"set_{x}"))
    left = salted_join(pairs, side("a"), "a", ["b"], hot_keys(pairs, "a"))
    both = salted_join(left, side("b"), "b", ["a"], hot_keys(pairs, "b"))

    def run(batches):
        for batch in slices(batches):
            keep = []
            for x, y in zip(batch.column(2), batch.column(3)):
                s, t = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                at = np.searchsorted(t, s)
                at[at == len(t)] = 0
                shared = int(np.count_nonzero(t[at] == s))
                keep.append(100 * shared >= percent * (len(s) + len(t) - shared))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return both.select("a", "b", "set_a", "set_b").mapInArrow(run, "a long, b long")


def connected_components(edges: DataFrame) -> DataFrame:
    """(node, component = least node) of an undirected graph given as (a, b).

    Alternates the large-star and small-star steps until the edges stay the same; each
    round is written to the shared folder. Nodes without an edge do not appear.
    """
    now = materialise(edges.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    mark = None
    while True:
        new_mark = tuple(now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if new_mark == mark or not new_mark[0]:
            break
        mark = new_mark
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.first("u")).alias("m"))
        large = both.join(least, "u").filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.*").filter("u <> v").distinct()
        older, now = now, materialise(small)
        discard(older)
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def similar_components(df: DataFrame, doc_id: str = "doc_id", text: str = "text", words: int = WORDS, percent: int = PERCENT, id_bits: int = 64) -> DataFrame:
    """Per row: doc_id, n_shingles, component_id (least doc_id reachable by links). ``id_bits``: fewer only to try sets that share an id."""
    docs = df.select(df[doc_id].alias("doc_id"), df[text].cast("string").alias("text"))
    rows, again = _identified(docs, words, percent, id_bits)
    full = rows.filter("n > 0")
    classes = full.groupBy("sid", "n").agg(F.first("prefix").alias("prefix"))
    postings = classes.select("sid", "n", F.posexplode("prefix").alias("pos", "h"))

    # The leader of a column is the class in which the fewest rarer shingles stand before
    # it: the least edited of a group of near copies, which most others are close to.
    leaders = postings.groupBy("h").agg(F.count(F.lit(1)).alias("rows"), F.min(F.struct("pos", "sid", "n")).alias("lead")).filter("rows > 1").drop("rows")
    met = materialise(postings.join(leaders, "h").select("h", "sid", "n", "pos", "lead"))
    first = met.filter(F.col("sid") != F.col("lead.sid"))
    first = first.select(F.col("sid").alias("a"), F.col("lead.sid").alias("b"), F.col("n").alias("n_a"), F.col("lead.n").alias("n_b"), F.col("pos").alias("pos_a"), F.col("lead.pos").alias("pos_b"))
    pairs = materialise(_summed(first, percent))
    near = materialise(_links(pairs, _full_sets(docs, pairs, words, again, id_bits), percent))
    groups = connected_components(near)

    # Pairs across the components found so far: each column pairs the classes outside its
    # largest component with all others, and the bounds are part of the join's condition.
    ends = full.select("sid", "end_count", "end_hash").distinct()
    placed = _with_unshared(met.drop("lead").join(ends, "sid").join(groups.select(F.col("node").alias("sid"), "component"), "sid", "left").withColumn("comp", F.coalesce("component", "sid")), percent)
    counts = placed.groupBy("h", "comp").agg(F.count(F.lit(1)).alias("rows"))
    largest = counts.groupBy("h").agg(F.max(F.struct("rows", "comp")).alias("top"), F.count(F.lit(1)).alias("comps")).filter("comps > 1").select("h", F.col("top.comp").alias("top"))
    placed = materialise(placed.join(largest, "h"))
    outside = placed.filter("comp <> top")
    side = lambda df, x: df.select("h", *[F.col(c).alias(f"{c}_{x}") for c in df.columns if c not in ("h", "sid", "top")], F.col("sid").alias(x), *([F.col("top")] if x == "b" else []))
    across = salted_join(side(outside, "a"), side(placed, "b"), "h", ["a"], hot_keys(outside, "h")).filter("comp_a <> comp_b and (comp_b = top or comp_a < comp_b)").filter(_sizes_fit(percent)).filter(_unshared_allows(percent))
    pairs = materialise(_summed(across, percent))
    far = _links(pairs, _full_sets(docs, pairs, words, again, id_bits), percent)
    edges = groups.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(far)
    groups = connected_components(edges)

    named = full.groupBy("sid").agg(F.min("doc_id").alias("least")).join(groups.select(F.col("node").alias("sid"), "component"), "sid", "left").select("sid", "least", F.coalesce("component", "sid").alias("component"))
    named = materialise(named)
    ids = named.groupBy("component").agg(F.min("least").alias("component_id"))
    by_set = named.join(ids, "component").select("sid", "component_id")
    linked = full.join(by_set, "sid", "left").select("doc_id", F.col("n").cast("long").alias("n_shingles"), "component_id")
    alone = rows.filter("n = 0").select("doc_id", F.lit(0).cast("long").alias("n_shingles"), F.col("doc_id").alias("component_id"))
    return linked.unionByName(alone)


def op2_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return similar_components(table(spark, sf_dir, "documents"))


_CUT = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+')"
#: DuckDB: shingles as strings, all pairs that share one, and the reach of every row along links.
ORACLE_SQL = f"""
with recursive d as (select row_number() over () as r, doc_id, {_CUT} as w from documents),
s as (select distinct r, array_to_string(w[i : i + {WORDS - 1}], ' ') as g from d, unnest(range(1, greatest(len(w) - {WORDS - 1}, 1) + 1)) t(i) where len(w) > 0),
n as (select r, count(*) as n from s group by r),
p as (select x.r as a, y.r as b, count(*) as c from s x join s y on x.g = y.g and x.r < y.r group by 1, 2),
e as (select a, b from p join n na on na.r = a join n nb on nb.r = b where 100 * c >= {PERCENT} * (na.n + nb.n - c)),
linked as (select a, b from e union select b, a from e),
reach(a, b) as (select r, r from d union select reach.a, linked.b from reach join linked on reach.b = linked.a),
least_id as (select a, min(d.doc_id) as component_id from reach join d on d.r = reach.b group by a)
select doc_id, coalesce(n.n, 0) as n_shingles, component_id from d left join n using (r) join least_id on least_id.a = d.r
"""
