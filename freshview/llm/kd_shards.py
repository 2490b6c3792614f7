"""Sharding by a k-d tree over metadata: recursive splits at weighted medians.

Every row is a point: one long a dimension. A node splits along the dimension that is
widest there (spread over the node, relative to the spread over the corpus) at the
median by weight (bytes), until its leaves reach the target or the depth is met. All
nodes of a level split together. A weighted median is found without sorting: a
histogram by node of the next bits of the key, summed in Spark, narrows each node's
cut to one bin; a few rounds fix the cut. The key is the dimension's value, then
a hash of the whole row, so ties and repeated values split as evenly as any others.
Where the bin that holds a cut is one key and still too heavy, its rows are repeats of
one row (or share a hash): they are cut by a third part of the key, a hash of the place
where each copy was read, in the same rounds. What reaches the driver is one histogram
of a fixed number of bins a node.

The law is ``bytes``: shards are near equal in bytes (a row counts its UTF-8 bytes
plus 1, so empty rows weigh something too).

Defined cases: null text has size 1 and the CRC of the empty text; null metadata is a
value of its own; rows that are equal in every column are split like any others, and
which copy goes where cannot be told from the result; slots are numbered in pieces over
which copies spread too; other columns are not read; with fewer rows than shards some
stay empty.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import discard, materialise, table

SHARDS = 16
#: Bits of a key: value and tie; bits that one histogram resolves.
VALUE_BITS, TIE_BITS, COPY_BITS, ROUND_BITS = 32, 30, 44, 11
#: Share of the wanted weight that a cut may be off.
TOLERANCE = 1e-4
#: Rows numbered together in one task.
SLOT_ROWS = 1 << 13


def _ordinal(text: Column) -> Column:
    """A string as a value in 32 bits that keeps the order of the first four bytes; null is 0."""
    head = F.conv(F.rpad(F.hex(F.substring(F.encode(text, "UTF-8"), 1, 4)), 8, "0"), 16, 10).cast("long")
    return F.coalesce(head, F.lit(0).cast("long"))


def document_dimensions(df: DataFrame) -> list[Column]:
    """Metadata of documents: source, language, length, place by id."""
    bounded = lambda c: F.least(F.greatest(F.coalesce(c.cast("long"), F.lit(0)), F.lit(0)), F.lit(2**VALUE_BITS - 1))
    source = F.crc32(F.coalesce(df["source"], F.lit("")))
    return [source, _ordinal(df["lang"]), bounded(df["n_chars"]), F.pmod(F.coalesce(df["doc_id"].cast("long"), F.lit(0)), F.lit(2**VALUE_BITS))]


def _small(spark: SparkSession, names: str, rows: list[tuple]) -> DataFrame:
    """A local table of one row a leaf. Plans differ only in its rows, so generated code is reused."""
    return F.broadcast(spark.sql(f"SELECT * FROM VALUES {', '.join(str(r) for r in rows)} AS t({names})"))


def kd_leaves(points: DataFrame, dims: list[str], size: str, leaves: int = SHARDS, target_bytes: int | None = None, tie: str = "tie", copy: str = "copy") -> DataFrame:
    """``points`` plus ``leaf``: split until there are ``leaves`` leaves or all have at most ``target_bytes``.

    ``tie`` tells rows of one value apart, ``copy`` rows of one value and tie; both must be
    fixed, that is read from a written table. ``leaves`` need not be a power of two: a node that stands for m leaves splits its
    weight as m//2 to m - m//2.
    """
    spark, columns = points.sparkSession, points.columns
    overall = points.agg(*[f(d).alias(f"{f.__name__}_{d}") for d in dims for f in (F.min, F.max)]).first()
    width = {d: max(1, (overall[f"max_{d}"] or 0) - (overall[f"min_{d}"] or 0)) for d in dims}
    points = points.withColumn("leaf", F.lit(0).cast("int"))
    share, older = {0: leaves}, None
    while True:
        stats = points.groupBy("leaf").agg(F.sum(size).alias("bytes"), *[(F.max(d) - F.min(d)).alias(d) for d in dims]).collect()
        split = {r["leaf"]: r for r in stats if share[r["leaf"]] > 1 and (target_bytes is None or r["bytes"] > target_bytes)}
        if not split:
            return points
        axis = {leaf: max(range(len(dims)), key=lambda k: (r[dims[k]] / width[dims[k]], -k)) for leaf, r in split.items()}
        value = F.element_at(F.array(*dims), F.col("axis") + 1)
        key = F.shiftleft(value, TIE_BITS) + F.col(tie)
        keyed = materialise(points.join(_small(spark, "leaf, axis", list(axis.items())), "leaf", "left").select(*columns, "leaf", key.alias("key")))
        if older is not None:
            discard(older)
        older = keyed
        cut = _weighted_cuts(keyed, size, {leaf: r["bytes"] * (share[leaf] // 2) / share[leaf] for leaf, r in split.items()}, copy)
        parts, rows, fresh = dict(share), [], max(share) + 1
        for leaf in split:
            parts[fresh], parts[leaf] = share[leaf] - share[leaf] // 2, share[leaf] // 2
            rows.append((leaf, *cut[leaf], fresh))
            fresh += 1
        share = parts
        placed = keyed.join(_small(spark, "leaf, cut, copy_cut, fresh", rows), "leaf", "left")
        beyond = (F.col("key") > F.col("cut")) | (F.col("key") == F.col("cut")) & (F.col(copy) >= F.col("copy_cut"))
        points = placed.select(*columns, F.when(beyond, F.col("fresh")).otherwise(F.col("leaf")).alias("leaf"))


def _weighted_cuts(keyed: DataFrame, size: str, want: dict[int, float], copy: str = "copy") -> dict[int, tuple[int, int]]:
    """Per leaf the key, and the copy among rows of that key, below which lies the wanted weight."""
    before = dict.fromkeys(want, 0)
    cut, heavy = _narrow(keyed.select("leaf", "key", size), size, VALUE_BITS + TIE_BITS, want, before, set(want))
    copies = dict.fromkeys(want, 0)
    if heavy:
        one_key = keyed.join(_small(keyed.sparkSession, "leaf, key", [(leaf, cut[leaf]) for leaf in sorted(heavy)]), ["leaf", "key"])
        copies, _ = _narrow(one_key.select("leaf", F.col(copy).alias("key"), size), size, COPY_BITS, want, before, heavy)
    return {leaf: (cut[leaf], copies[leaf]) for leaf in want}


def _narrow(keyed: DataFrame, size: str, bits: int, want: dict[int, float], before: dict[int, int], leaves: set[int]) -> tuple[dict[int, int], set[int]]:
    """Fix the cut of each of ``leaves`` in rounds of ROUND_BITS of the key; also the leaves whose last bin is too heavy.

    ``before`` is the weight below the cut and grows with it. A leaf is done early when
    the bin that holds its cut weighs at most TOLERANCE of the weight wanted.
    """
    cut, shift = dict.fromkeys(want, 0), bits
    open_leaves = set(leaves)
    while shift > 0 and open_leaves:
        step = min(ROUND_BITS, shift)
        shift -= step
        state = _small(keyed.sparkSession, "leaf, known, high, low, mask", [(leaf, cut[leaf], shift + step, shift, (1 << step) - 1) for leaf in sorted(open_leaves)])
        inside = keyed.join(state, "leaf").filter("shiftright(key, high) = known")
        bins = inside.groupBy("leaf", F.expr("cast(shiftright(key, low) & mask as int)").alias("bin")).agg(F.sum(size).alias("bytes"))
        by_leaf: dict[int, list] = {}
        for r in bins.collect():
            by_leaf.setdefault(r["leaf"], []).append((r["bin"], r["bytes"]))
        for leaf in leaves:
            chosen = 0
            if leaf in open_leaves:
                for b, n in sorted(by_leaf.get(leaf, [])):
                    chosen = b
                    if before[leaf] + n > want[leaf]:
                        if n <= TOLERANCE * want[leaf]:
                            open_leaves.discard(leaf)
                        break
                    before[leaf] += n
                else:
                    chosen = (1 << step) - 1
            cut[leaf] = (cut[leaf] << step) | chosen
    return {leaf: c << shift for leaf, c in cut.items()}, open_leaves


def with_slots(placed: DataFrame, shard: str, order: list[str], slot_rows: int = SLOT_ROWS) -> DataFrame:
    """Number the rows of each shard from 0 without a gap, in pieces of about ``slot_rows`` rows.

    ``order`` must tell repeated rows apart, so that they do not meet in one piece.
    """
    rows = placed.count()
    pieces = max(1, rows // slot_rows)
    pieced = placed.withColumn("piece", F.pmod(F.xxhash64(*order), F.lit(pieces)).cast("int"))
    counts = pieced.groupBy(shard, "piece").agg(F.count(F.lit(1)).alias("n"))
    # one row a shard and piece: rows / slot_rows rows in all
    offset = counts.withColumn("offset", F.sum("n").over(Window.partitionBy(shard).orderBy("piece")) - F.col("n")).drop("n")
    numbered = pieced.withColumn("place", F.row_number().over(Window.partitionBy(shard, "piece").orderBy(*order)) - 1)
    return numbered.join(offset, [shard, "piece"]).withColumn("slot", (F.col("offset") + F.col("place")).cast("long")).drop("offset", "place", "piece")


def shard_documents(df: DataFrame, shards: int = SHARDS) -> DataFrame:
    """Per row: doc_id, size, text_crc32, shard, slot."""
    body = F.coalesce(df["text"].cast("string"), F.lit(""))
    dims = document_dimensions(df)
    names = [f"d{i}" for i in range(len(dims))]
    points = df.select(
        df["doc_id"].alias("doc_id"),
        (F.octet_length(body) + 1).cast("long").alias("size"),
        F.crc32(body).cast("long").alias("text_crc32"),
        *[d.cast("long").alias(n) for d, n in zip(dims, names)],
    )
    tie = F.pmod(F.xxhash64("doc_id", "size", "text_crc32"), F.lit(1 << TIE_BITS))
    copy = F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(1 << COPY_BITS))
    leaves = kd_leaves(materialise(points.withColumn("tie", tie).withColumn("copy", copy)), names, "size", shards)
    placed = leaves.select("doc_id", "size", "text_crc32", F.col("leaf").alias("shard"), "tie", "copy")
    return with_slots(placed, "shard", ["tie", "doc_id", "size", "text_crc32", "copy"]).drop("tie", "copy")


def op10_kd_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    placed = shard_documents(table(spark, sf_dir, "documents"))
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), "slot", F.lit(None).cast("int").alias("grown_shard"))
