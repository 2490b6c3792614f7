import hashlib

import corpus_pipeline
import numpy as np
import test_byte_bpe
import test_ngram_join
import test_secrets
from freshview.llm import decontaminate, language
from freshview.llm.common import table


def test_stages_against_brute_force(spark):
    d = "/root/testdata/sf0.01"
    docs = table(spark, d, "documents").filter("doc_id % 5 < 3").withColumn("rows", corpus_pipeline.F.lit(1))
    rows = {r.doc_id: r for r in docs.collect()}
    items = [(r.item_id, r.text) for r in table(spark, d, "benchmark").collect()]
    repeated = docs.filter("doc_id < 3")
    now = docs.unionByName(repeated)
    for name, stage in corpus_pipeline.STAGES:
        out = corpus_pipeline.materialise(stage(spark, now, d))
        if name != "tokens":
            assert out.columns == docs.columns
        got = {r.doc_id: r for r in out.collect()}
        if name == "language":
            assert set(got) == {i for i, r in rows.items() if any(c.isalpha() for c in r.text or "")}
            want = {i: rows[i].text for i in got}
        elif name == "near_copies":
            assert out.count() == len(got)
            want = {i: want[i] for i, _, c in test_ngram_join.brute(sorted(want.items())) if i == c}
        elif name == "benchmarks":
            clean = {}
            for i, t in want.items():
                spans = decontaminate.removal_spans(t, np.array(flags(t, items)))
                if decontaminate.WORD_TEXT.search(decontaminate.without(t, spans)):
                    clean[i] = decontaminate.without(t, spans)
            want = clean
        elif name == "secrets":
            want = {i: redacted(t) for i, t in want.items()}
        if name == "tokens":
            enc = test_byte_bpe.library()
            for i, t in want.items():
                assert got[i].n_tokens == len(enc.encode_ordinary(t)) and got[i].decoded_sha256 == hashlib.sha256(t.encode()).hexdigest()
        else:
            assert {i: r.text for i, r in got.items()} == want
            if name in ("benchmarks", "secrets"):
                assert all(r.n_chars == len(r.text) for r in got.values())
        now = out
    assert language.UNKNOWN == "und"


def test_near_copies_by_row(spark):
    text = lambda k, n=40: " ".join(f"w{k}x{i}" for i in range(n))
    near = text(0, 39) + " other"
    # null ids: three texts, one of them twice, and a near copy of a named one; id 5: two texts, one twice; id 7: own text and a near copy of id 1
    rows = [(None, text(1)), (None, text(2)), (None, text(3)), (None, text(3)), (None, near), (5, text(5)), (5, text(6)), (5, text(6)), (1, text(0)), (7, near), (7, text(7)), (8, "..."), (None, None), (None, None), (9, None), (9, None)]
    docs = spark.createDataFrame([(i, t, k) for k, (i, t) in enumerate(rows)], "doc_id long, text string, n int").repartition(3)
    out = corpus_pipeline.one_of_each_group(spark, docs, "")
    assert out.columns == docs.columns
    want = [(None, text(1)), (None, text(2)), (None, text(3)), (5, text(5)), (5, text(6)), (1, text(0)), (7, text(7)), (8, "..."), (None, None), (None, None), (9, None)]
    assert sorted(((r.doc_id, r.text) for r in out.collect()), key=str) == sorted(want, key=str)


def flags(text, items):
    words = decontaminate.words_of(text)
    windows = {}
    for _, t in items:
        w = decontaminate.words_of(t)
        n = min(10, len(w))
        for k in range(len(w) - n + 1 if w else 0):
            windows.setdefault(n, set()).add(tuple(w[k : k + n]))
    hit = [False] * len(words)
    for n, known in windows.items():
        for k in range(len(words) - n + 1):
            if tuple(words[k : k + n]) in known:
                hit[k : k + n] = [True] * n
    return hit


def redacted(text):
    spans = [tuple(map(int, s.split(":")[1:])) for s in test_secrets.brute(text)[-1].split(",") if s]
    out, at = [], 0
    for a, b in spans:
        if a < at:
            at = max(at, b)
            continue
        out += [text[at:a], "[SECRET]"]
        at = b
    return "".join([*out, text[at:]])
