import random
import re

from freshview.llm import ngram_join as N

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def shingles(text):
    w = WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()


def brute(rows):
    sets = [shingles(t) for _, t in rows]
    up = list(range(len(rows)))

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for i, s in enumerate(sets):
        for j in range(i):
            both = len(s & sets[j])
            if s and sets[j] and 100 * both >= 80 * (len(s) + len(sets[j]) - both):
                up[root(i)] = root(j)
    least = {}
    for i, (d, _) in enumerate(rows):
        least[root(i)] = min(least.get(root(i), d), d)
    return sorted((d, len(sets[i]), least[root(i)] if sets[i] else d) for i, (d, _) in enumerate(rows))


def corpus():
    rng = random.Random(4)
    vocab = [f"w{i}é" for i in range(300)]
    passage = " ".join(rng.choice(vocab) for _ in range(60))
    rows = []
    base = [rng.choice(vocab) for _ in range(200)]
    for k in range(60):  # a group of near copies, chained further and further from the first
        w = base[:]
        for _ in range(k % 9):
            w[rng.randrange(200)] = rng.choice(vocab)
        rows.append(" ".join(w))
    chain = [rng.choice(vocab) for _ in range(120)]
    for _ in range(25):
        chain[rng.randrange(120)] = rng.choice(vocab)
        chain[rng.randrange(120)] = rng.choice(vocab)
        rows.append("\n".join(chain))
    rows += [passage + " " + " ".join(rng.choice(vocab) for _ in range(rng.randrange(3, 40))) for _ in range(60)]
    rows += [" ".join(rng.choice(vocab[:4]) for _ in range(rng.randrange(1, 9))) for _ in range(80)]
    rows += [None, "", "  \n", "One two", "one TWO", "one two three four five", "ONE two\tthree four five ", "x " * 5000, "x " * 4000, "y" * 100000]
    rows += rows[:10]
    order = list(range(len(rows)))
    rng.shuffle(order)
    return [(7 * d + 3, rows[i]) for d, i in enumerate(order)]


def test_against_brute_force(spark):
    rows = corpus()
    df = spark.createDataFrame([(d, t, "x", 1) for d, t in rows], "doc_id long, text string, sid string, n int").repartition(5)
    want = brute(rows)
    assert sorted(tuple(r) for r in N.similar_components(df).collect()) == want
    # ids of so few bits that most sets share one at first
    assert sorted(tuple(r) for r in N.similar_components(df, id_bits=5).collect()) == want


def test_components(spark):
    edges = [(i, i + 1) for i in range(1, 40)] + [(100, 90), (90, 95), (7, 7)]
    got = {r.node: r.component for r in N.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 1 for i in range(1, 41)}, 100: 90, 95: 90, 90: 90}


def test_empty_and_repeated(spark):
    df = spark.createDataFrame([(1, "a b c d e f"), (1, "a b c d e f"), (None, "a b c d e f"), (2, None)], "doc_id long, text string")
    got = sorted((tuple(r) for r in N.similar_components(df).collect()), key=str)
    assert got == sorted([(1, 2, 1), (1, 2, 1), (None, 2, 1), (2, 0, 2)], key=str)
    assert N.similar_components(df.limit(0)).count() == 0


def test_salted_join(spark):
    from freshview.llm.common import hot_keys, salted_join

    many = spark.createDataFrame([(k % 7 if k < 100 else 50, k) for k in range(900)] + [(None, 1000), (77, 1001)], "k long, v long")
    one = spark.createDataFrame([(k, f"n{k}") for k in (0, 1, 2, 50, 50)], "k long, name string")
    hot = hot_keys(many, "k", share=0.01)
    assert {k for k, _ in hot} == {*range(7), 50} and sum(n for _, n in hot) < 120
    for how in ("inner", "left"):
        want = sorted(map(str, many.join(one, "k", how).collect()))
        assert sorted(map(str, salted_join(many, one, "k", ["v"], hot, how).select("k", "v", "name").collect())) == want


def test_order_grows():
    assert [N.order_bits(n) for n in (0, 1000, 1 << 18, 1 << 20, 1 << 40)] == [18, 18, 19, 21, 24]
