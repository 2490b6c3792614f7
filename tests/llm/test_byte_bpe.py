import hashlib
import random

import numpy as np
import public_tokenizers
import tiktoken
from freshview.llm import byte_bpe as B


def library():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=B.load_ranks(B.vocabulary()), special_tokens={})


CASES = ["", "a", "it's we're I'll 'sa ''s !'s  's\n's 're1", "  a  \n\n b \t", "x   ", "   y", "　z", "1'd2'm", "don'tdon't'", "'", "'l", "'ll", "' s", "é'ß ünï 東京 १२३ ½²", "😀😀 😀a", "<|endoftext|>", "a" * 3000, "ab" * 5000, " " * 1000 + "b", "\r\n\r\n", "àb", "\x1c\x1d a\x85b", "᠎ ​ x", "'S'RE", "word'\n\n 'verb"]


def test_against_library():
    tool, enc = B.Codec(B.vocabulary()), library()
    rng = random.Random(5)
    alphabet = "ab'sdtrelmv  \n\t .!12éß 　東😀²́\r"
    texts = CASES + ["".join(rng.choice(alphabet) for _ in range(rng.randrange(60))) for _ in range(4000)]
    ids, bounds = tool.encode(texts)
    for i, t in enumerate(texts):
        mine = ids[bounds[i] : bounds[i + 1]].tolist()
        assert mine == enc.encode_ordinary(t), repr(t)
        assert tool.decode(mine) == t.encode()


def test_all_letters_cut_alike():
    tool, enc = B.Codec(B.vocabulary()), library()
    points = [i for i in range(0x30000) if not 0xD800 <= i < 0xE000]
    texts = ["".join(f"a{chr(i)} {chr(i)}1" for i in points[k : k + 64]) for k in range(0, len(points), 64)]
    ids, bounds = tool.encode(texts)
    odd = [k for k, t in enumerate(texts) if ids[bounds[k] : bounds[k + 1]].tolist() != enc.encode_ordinary(t)]
    assert len(odd) == 0, [hex(points[64 * k]) for k in odd]


def test_frames(spark):
    rows = [(i, t) for i, t in enumerate([None, *CASES, CASES[2]])]
    df = spark.createDataFrame([(i, t, "x", 1) for i, t in rows], "doc_id long, text string, ids string, n_tokens int")
    enc = library()
    got = {r.doc_id: r for r in B.encode_digests(df).collect()}
    listed = {r.doc_id: r for r in B.encode_documents(df).collect()}
    back = {r.doc_id: bytes(r.decoded) for r in B.decode_documents(B.encode_documents(df)).collect()}
    for i, t in rows:
        want = enc.encode_ordinary(t or "")
        assert listed[i].ids == want and back[i] == (t or "").encode()
        assert listed[i].offsets == [0, *np.cumsum([len(enc.decode_single_token_bytes(x)) for x in want])][: len(want)]
        assert got[i].n_tokens == len(want)
        assert got[i].ids_sha256 == hashlib.sha256(np.array(want, "<u4").tobytes()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    assert B.encode_digests(df.limit(0)).count() == 0
