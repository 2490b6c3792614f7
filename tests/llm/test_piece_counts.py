import random

from freshview.llm import piece_counts as P
from freshview.llm.common import table


def greedy(word, pieces):
    at = n = 0
    longest = max(map(len, pieces), default=1)
    while at < len(word):
        size = next((k for k in range(min(longest, len(word) - at), 0, -1) if word[at : at + k] in pieces), 1)
        at, n = at + size, n + 1
    return n


def test_random_vocabularies():
    rng = random.Random(6)
    for _ in range(300):
        letters = b"abc"[: rng.randrange(1, 4)]
        pieces = {bytes(rng.choice(letters) for _ in range(rng.randrange(1, 6))) for _ in range(rng.randrange(1, 12))} | {bytes([c]) for c in letters}
        tool = P.LongestMatch(pieces)
        for _ in range(30):
            word = bytes(rng.choice(letters) for _ in range(rng.randrange(0, 25)))
            assert tool.count(word) == greedy(word, pieces), (pieces, word)


def test_unknown_bytes():
    tool = P.LongestMatch([b"ab", b"abcd", b"c"])
    assert tool.count(b"zabz") == 3 and tool.count(b"") == 0 and tool.count(b"abcd") == 1 and tool.count(b"abc") == 2


def test_given_table_and_edges(spark):
    pieces = set(P.load_ranks(P.vocabulary()))
    docs = {r.doc_id: r.text for r in table(spark, "/root/testdata/sf0.01", "documents").limit(60).collect()}
    got = {r.doc_id: r for r in P.op3_token_counts(spark, "/root/testdata/sf0.01").collect()}
    for i, text in docs.items():
        counts = [greedy(b" " + w, pieces) for w in P.WORD.findall((text or "").encode())]
        assert (got[i].n_words, got[i].n_tokens) == (len(counts), sum(counts))
    odd = spark.createDataFrame([(0, None, 1), (1, "", 1), (2, " \n", 1), (3, "a" * 100_000, 1), (3, "é x", 1)], "doc_id long, text string, n_tokens int")
    rows = sorted(tuple(r) for r in P.count_tokens(odd).collect())
    assert [r[1] for r in rows] == [0, 0, 0, 1, 2] and rows[3][2] == greedy(b" " + b"a" * 100_000, pieces)
    assert P.count_tokens(odd.limit(0)).count() == 0
