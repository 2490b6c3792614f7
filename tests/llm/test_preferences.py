import random

from freshview.llm import preferences as P
from freshview.llm.common import table


def render(turns):
    return "".join(f"<|im_start|>{r or ''}\n{t or ''}<|im_end|>\n" for _, r, t in turns)


def masked(turns):
    at, out = 0, []
    for _, r, t in turns:
        begin = at + len(f"<|im_start|>{r or ''}\n")
        end = begin + len(t or "")
        if r == "assistant" and t:
            out.append((begin, end))
        at = end + len("<|im_end|>\n")
    return out


def formatted(c, r):
    n = 0
    while n < min(len(c), len(r)) and c[n][1:] == r[n][1:]:
        n += 1
    return n, render(c[:n]), render(c[n:]), masked(c[n:]), render(r[n:]), masked(r[n:])


def key(t):
    return tuple((x is not None, x) if x is not None else (False, 0 if i == 0 else "") for i, x in enumerate(t))


def brute(rows):
    conv = {}
    for i, *t in rows:
        conv.setdefault(i, []).append(tuple(t))
    conv = {i: sorted(t, key=key) for i, t in conv.items()}
    out = {}
    for i, turns in conv.items():
        later = [j for j in conv if i is not None and j is not None and j > i and conv[j][0][1:] == turns[0][1:]]
        if later:
            other = conv[min(later)]
        else:
            spoken = [k for k, t in enumerate(turns) if t[1] == "assistant"]
            other = list(turns)
            if spoken:
                k = spoken[-1]
                other[k] = (turns[k][0], "assistant", turns[spoken[-2]][2] if len(spoken) > 1 else "")
            else:
                other = other[:-1]
        out[i] = (min(later) if later else None, *formatted(turns, other))
    return out


def got(df):
    return {r.conv_id: (r.rejected_id, r.prompt_turns, r.prompt, r.chosen, [tuple(s) for s in r.chosen_mask], r.rejected, [tuple(s) for s in r.rejected_mask]) for r in df.collect()}


def test_against_brute_force(spark):
    rng = random.Random(9)
    rows = []
    for i in range(700):
        rows.append((i * 3, 0, "user", rng.choice(["hot"] * 6 + ["é😀", None, f"own {i}"])))
        for k in range(1, rng.randrange(1, 6)):
            rows.append((i * 3, k, rng.choice(["assistant", "user", None]), rng.choice(["yes", "no", None, ""])))
    rows += [(None, 0, "user", "hot"), (5000, None, "user", "a"), (5000, 1, "assistant", "b"), (5000, 1, "assistant", "b")]
    df = spark.createDataFrame([(*r, "x", 0) for r in rows], "conv_id long, turn long, role string, text string, chosen string, block int")
    assert got(P.neighbour_pairs(df)) == brute(rows)
    small = P.neighbours(P.gather_turns(df).filter("conv_id is not null"), blocks=7).collect()
    assert {r.conv_id: r.next_id for r in small} == {i: v[0] for i, v in brute(rows).items() if i is not None}
    assert P.neighbour_pairs(df.limit(0)).count() == 0


def test_given_pairs(spark):
    c = spark.createDataFrame([(1, 0, "user", "q"), (1, 1, "assistant", "good"), (2, 0, "user", "q")], "pair_id long, turn int, role string, text string")
    r = spark.createDataFrame([(1, 0, "user", "q"), (1, 1, "assistant", "bad"), (1, 2, "user", "?"), (3, 0, "user", "z")], "pair_id long, turn int, role string, text string")
    rows = {x.pair_id: x for x in P.preference_pairs(c, r).collect()}
    assert rows[1].prompt == render([(0, "user", "q")]) and rows[1].chosen == render([(1, "assistant", "good")])
    assert [tuple(s) for s in rows[1].rejected_mask] == masked([(1, "assistant", "bad"), (2, "user", "?")])
    assert rows[2].prompt_turns == 0 and rows[2].rejected == "" and rows[3].chosen == ""


def test_given_table(spark):
    rows = [tuple(r) for r in table(spark, "/root/testdata/sf0.01", "conversations").select("conv_id", "turn", "role", "text").collect()]
    assert got(P.op9_preference_pairs(spark, "/root/testdata/sf0.01")) == brute(rows)


def test_text_ids(spark):
    rows = [(f"conv-{i:04d}", 0, "user", "hot" if i % 3 else f"own {i}") for i in range(200)] + [(f"conv-{i:04d}", 1, "assistant", f"reply {i}") for i in range(200)]
    df = spark.createDataFrame(rows, "conv_id string, turn long, role string, text string")
    assert got(P.neighbour_pairs(df)) == brute(rows)
