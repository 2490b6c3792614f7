import zlib
from collections import defaultdict

from freshview.llm import kd_shards as K
from freshview.llm.common import table


def check(rows, texts, shards):
    by = defaultdict(list)
    for r in rows:
        text = (texts[r.doc_id] or "").encode()
        assert (r.size, r.text_crc32) == (len(text) + 1, zlib.crc32(text))
        by[r.shard].append(r)
    for part in by.values():
        assert sorted(r.slot for r in part) == list(range(len(part)))
    assert set(by) <= set(range(shards))
    return {s: sum(r.size for r in part) for s, part in by.items()}


def test_given_table(spark):
    texts = {r.doc_id: r.text for r in table(spark, "/root/testdata/sf0.01", "documents").collect()}
    rows = K.op10_kd_shards(spark, "/root/testdata/sf0.01").collect()
    assert len(rows) == len(texts) and {r.law for r in rows} == {"bytes"}
    sizes = check(rows, texts, 16)
    largest = max(len((t or "").encode()) + 1 for t in texts.values())
    assert len(sizes) == 16 and max(sizes.values()) - min(sizes.values()) <= 2 * largest


def test_edges(spark):
    rows = [(i, t, None, None, None, "x") for i, t in enumerate([None, "", "é", "same", "same", "same"])]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, slot string")
    sizes = check(K.shard_documents(df).collect(), {r[0]: r[1] for r in rows}, 16)
    assert sum(sizes.values()) == 6 + 2 + 12
    assert K.shard_documents(df.limit(0)).count() == 0
    assert K.shard_documents(df.withColumn("doc_id", K.F.lit(None).cast("long"))).count() == 6


def test_weighted_median_and_uneven_leaves(spark):
    df = spark.range(3000).select(K.F.col("id").alias("a"), (K.F.col("id") % 7).alias("b"), (K.F.col("id") % 5 + 1).alias("w"), K.F.pmod(K.F.xxhash64("id"), K.F.lit(1 << 30)).alias("tie"), K.F.lit(0).cast("long").alias("copy"))
    got = [r.s for r in K.kd_leaves(df, ["a", "b"], "w", 3).groupBy("leaf").agg(K.F.sum("w").alias("s")).collect()]
    assert len(got) == 3 and max(got) - min(got) <= 10
    small = K.kd_leaves(df, ["a", "b"], "w", 64, target_bytes=2000).groupBy("leaf").agg(K.F.sum("w").alias("s")).collect()
    assert all(r.s <= 2000 for r in small) and len(small) == 8


def test_repeated_rows_split(spark):
    """Equal rows are no lump: shards differ by a row at most, or by two where rows differ in size."""
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    for distinct in (1, 4):
        rows = [(k, "same words " * (k + 1), "en", "s", 5) for k in range(distinct) for _ in range(1600 // distinct)]
        got = K.shard_documents(spark.createDataFrame(rows, schema).repartition(5)).collect()
        sizes = check(got, {r[0]: r[1] for r in rows}, 16)
        assert len(sizes) == 16 and max(sizes.values()) - min(sizes.values()) <= distinct // 2 * max(r.size for r in got)


def brute_leaves(points, leaves):
    """Recursive split of (dims, tie, size) rows at the weighted median of the widest dimension."""
    widths = [max(1, max(p[0][k] for p in points) - min(p[0][k] for p in points)) for k in range(len(points[0][0]))]

    def split(part, n):
        if n == 1 or not part:
            return [part] * n
        axis = max(range(len(widths)), key=lambda k: ((max(p[0][k] for p in part) - min(p[0][k] for p in part)) / widths[k], -k))
        part = sorted(part, key=lambda p: (p[0][axis], p[1]))
        want, below, at = sum(p[2] for p in part) * (n // 2) / n, 0, 0
        while at < len(part) and below + part[at][2] <= want:
            below, at = below + part[at][2], at + 1
        return split(part[:at], n // 2) + split(part[at:], n - n // 2)

    return split(points, leaves)


def test_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr(K, "TOLERANCE", 0.0)
    df = spark.range(900).select(K.F.pmod(K.F.xxhash64("id"), K.F.lit(1000)).alias("a"), (K.F.col("id") % 11).alias("b"), (K.F.col("id") % 5 + 1).alias("w"), K.F.col("id").alias("tie"), K.F.lit(0).cast("long").alias("copy"))
    got = defaultdict(set)
    for r in K.kd_leaves(K.materialise(df), ["a", "b"], "w", 6).collect():
        got[r.leaf].add(r.tie)
    want = brute_leaves([((r.a, r.b), r.tie, r.w) for r in df.collect()], 6)
    assert sorted(map(sorted, got.values())) == sorted(sorted(p[1] for p in part) for part in want)
