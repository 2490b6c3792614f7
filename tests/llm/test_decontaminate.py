import random

import numpy as np
from freshview.llm import decontaminate as D


def test_index_against_scan():
    rng = np.random.default_rng(3)
    for n, k in ((1, 2), (50, 3), (400, 4), (3000, 30)):
        text = rng.integers(0, k, n)
        text[-1] = 0
        index = D.FMIndex(text, k, sample=5)
        lengths = rng.integers(1, 6, 60)
        phrases = np.zeros((60, 6), np.int64)
        for i, m in enumerate(lengths):
            phrases[i, :m] = rng.integers(1, k, m)
        low, high = index.search(phrases.ravel(), np.arange(60) * 6, lengths)
        for i, m in enumerate(lengths):
            want = [p for p in range(n - m + 1) if (text[p : p + m] == phrases[i, :m]).all()]
            assert sorted(index.locate(np.arange(low[i], high[i])).tolist()) == want


ITEMS = [(1, "one two three four five six seven eight nine ten eleven twelve"), (2, "short item"), (3, None), (4, "!!"), (5, "short item"), (10, "Ünï çödé " * 6), (None, "nobody owns this")]


def corpus():
    rng = random.Random(2)
    vocab = ["one", "two", "three", "short", "item", "x", "Ünï", "çödé", "é"]
    texts = [None, "", "...", ITEMS[0][1].upper(), "a " + ITEMS[0][1] + " b short, item", "Short... ITEM", "one two three four five six seven eight nine x ten", ITEMS[5][1] + "short", "nobody owns this"]
    texts += [" ".join(rng.choice(vocab) for _ in range(rng.randrange(80))) for _ in range(60)]
    return texts + [texts[4]] * 3 + [(ITEMS[0][1] + " , ") * 50]


def test_against_brute_force(spark):
    rows = [(i, t, "x") for i, t in enumerate(corpus())]
    docs = spark.createDataFrame(rows, "doc_id long, text string, items string")
    bench = spark.createDataFrame(ITEMS, "item_id long, text string")
    items = [x for x in ITEMS if x[0] is not None]
    for block_words, pass_words in ((D.BLOCK_WORDS, D.PASS_WORDS), (5, D.PASS_WORDS), (5, 1)):
        got = {r.doc_id: r for r in D.find_contamination(docs, bench, block_words=block_words, pass_words=pass_words).collect()}
        assert len(got) == len(rows)
        for i, t, _ in rows:
            n, hit, found = D.brute_force(t, ITEMS)
            assert (got[i].n_words, got[i].n_hit) == (n, hit), (t, got[i])
            assert sorted(got[i]["items"]) == D.brute_force(t, items)[2]
            if t:
                inside = [k for k, m in enumerate(D.WORD_TEXT.finditer(t)) if any(a <= m.start() < b for a, b in got[i].spans)]
                assert len(inside) == hit
    clean = {r.doc_id: r for r in D.remove_contamination(docs, bench).collect()}
    assert clean[4].text == "a  b " and clean[0].text is None and clean[4]["items"] == "x"
    again = {r.doc_id: r.text for r in D.remove_contamination(docs, bench, block_words=5, pass_words=1).collect()}
    assert again == {i: r.text for i, r in clean.items()}
    assert D.find_contamination(docs.limit(0), bench).count() == 0
    assert D.find_contamination(docs, bench.limit(0)).agg({"n_hit": "sum"}).first()[0] == 0


def test_given_tables(spark):
    from freshview.llm.common import table

    d = "/root/testdata/sf0.01"
    items = [(r.item_id, r.text) for r in table(spark, d, "benchmark").collect()]
    docs = {r.doc_id: r.text for r in table(spark, d, "documents").collect()}
    rows = D.op5_decontamination(spark, d).collect()
    assert len(rows) == len(docs) and any(r.contaminated for r in rows)
    flagged = [r for r in rows if r.contaminated] + rows[:60]
    for r in flagged:
        n, hit, found = D.brute_force(docs[r.doc_id], items)
        assert (r.n_words, r.n_hit, r.n_items, r.items_sha256) == (n, hit, len(found), D.items_digest(found))
