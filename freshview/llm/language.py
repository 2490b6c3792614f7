"""Language identification of mixed-language text: word scores and a Viterbi path.

Training counts letter trigrams inside words, by language, on a bounded sample of
labelled rows (``TRAIN_ROWS``, whole texts, the same bound for every language, so a
language with few rows is learned from all of them), in Spark; the driver receives one hashed
table of fixed size a language. Prediction is array arithmetic over a batch: code
points are lowered by a table, trigrams hashed, their log probabilities summed word
by word. The script of a word (by code point ranges) narrows its candidates to the
languages that use this script in training. A Viterbi pass with a penalty for each
switch labels every word; neighbours with one label form a span. Each text is cut
into blocks of words: blocks of all texts run in step, and their max-plus transfer
matrices join them, so one very long text is no slower a word than many short ones.

The language of a text is the one with most letters; the score is its share of the
letters. Ties go to the language first in code point order.

Defined cases: null text or text without a letter is ``und`` with score 0; so is
every text when nothing was learned. Rows with null lang, or without an id that would
say whether they are held out, are not learned from.
Repeated rows give repeated results. Only the text is read in a prediction.
"""

from __future__ import annotations

import sys
import unicodedata

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import batch_bounds, slices, table

#: Bound of the training sample, in rows over all languages; and of the model, in hashed trigrams.
TRAIN_ROWS, BUCKETS = 20_000, 1 << 16
#: Loss, in nats, of going from one language to another between two words.
SWITCH = 12.0
#: A script counts as used by a language from this share of its words.
SCRIPT_SHARE = 0.02
BLOCK_WORDS, BLOCK_CHARS = 256, 1 << 19
UNKNOWN = "und"
#: First code points of script ranges (Unicode blocks) and the script from there on.
SCRIPT_RANGES = (
    (0x0, "latin"), (0x370, "greek"), (0x400, "cyrillic"), (0x530, "armenian"), (0x590, "hebrew"), (0x600, "arabic"), (0x900, "devanagari"),
    (0x980, "indic"), (0xE00, "thai"), (0xE80, "lao"), (0xF00, "tibetan"), (0x1000, "burmese"), (0x10A0, "georgian"), (0x1100, "hangul"),
    (0x1200, "ethiopic"), (0x13A0, "other"), (0x1780, "khmer"), (0x1800, "mongolian"), (0x1D00, "latin"), (0x1F00, "greek"), (0x2000, "latin"),
    (0x2C80, "other"), (0x2E80, "han"), (0x3040, "kana"), (0x3100, "han"), (0x3130, "hangul"), (0x31F0, "kana"), (0x3200, "han"),
    (0xA000, "other"), (0xA720, "latin"), (0xA800, "other"), (0xAB30, "latin"), (0xAB70, "other"), (0xAC00, "hangul"), (0xD800, "other"),
    (0xF900, "han"), (0xFB00, "latin"), (0xFB1D, "hebrew"), (0xFB50, "arabic"), (0xFF00, "latin"), (0xFF66, "kana"), (0x10000, "other"),
    (0x20000, "han"),
)
SCRIPTS = sorted({s for _, s in SCRIPT_RANGES})
_RANGE_STARTS = np.array([a for a, _ in SCRIPT_RANGES], np.uint32)
_RANGE_SCRIPT = np.array([SCRIPTS.index(s) for _, s in SCRIPT_RANGES])
_tables: dict[str, np.ndarray] = {}


def _lowered() -> np.ndarray:
    """Lower case of every letter as one code point, 0 for anything else."""
    if "low" not in _tables:
        out = np.zeros(sys.maxunicode + 1, np.uint32)
        for i in range(sys.maxunicode + 1):
            c = chr(i)
            if unicodedata.category(c)[0] == "L":
                low = c.lower()
                out[i] = ord(low) if len(low) == 1 else i
        _tables["low"] = out
    return _tables["low"]


def cut_words(texts: list[str]) -> dict[str, np.ndarray]:
    """Words (runs of letters) of all texts: trigram buckets, word bounds in them, owner, place, letters and script."""
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    # one blank before, between and after the texts, so that no word crosses from one to the next
    points = np.frombuffer((" " + " ".join(texts) + " ").encode("utf-32-le", "surrogatepass"), np.uint32)
    low = _lowered()[points]
    letter = low > 0
    edge = np.flatnonzero(letter[1:] != letter[:-1]) + 1
    start, stop = edge[::2], edge[1::2]
    where = np.flatnonzero(letter)
    mixed = low[where - 1] * np.uint32(0x9E3779B1) ^ low[where] * np.uint32(0x85EBCA6B) ^ low[where + 1] * np.uint32(0xC2B2AE35)
    mixed ^= mixed >> np.uint32(15)
    mixed *= np.uint32(0x2C1B3C6D)
    bucket = mixed >> np.uint32(32 - (BUCKETS - 1).bit_length())
    first = np.concatenate(([0], np.cumsum(lengths + 1)))[:-1] + 1
    owner = np.searchsorted(first, start, "right") - 1
    size = stop - start
    return {
        "bucket": bucket,
        "at": np.cumsum(size) - size,
        "size": size,
        "owner": owner,
        "start": start - first[owner],
        "script": _RANGE_SCRIPT[np.searchsorted(_RANGE_STARTS, points[start], "right") - 1],
    }


class Model:
    """Log probabilities by bucket and language, and which scripts a language uses."""

    def __init__(self, langs: list[str], counts: np.ndarray, scripts: np.ndarray) -> None:
        self.langs = langs
        total = counts.sum(0, keepdims=True)
        self.logp = np.log((counts + 0.5) / (total + 0.5 * BUCKETS)).astype(np.float32)
        allowed = scripts / np.maximum(scripts.sum(0, keepdims=True), 1) >= SCRIPT_SHARE
        #: A script that no language uses tells nothing; one that others use rules a language out.
        self.used = allowed.any(1)
        self.barred = np.where(allowed | ~self.used[:, None], 0.0, -60.0).astype(np.float32)

    def word_scores(self, words: dict[str, np.ndarray]) -> np.ndarray:
        if not len(words["at"]):
            return np.zeros((0, len(self.langs)), np.float32)
        scores = np.add.reduceat(self.logp[words["bucket"]], words["at"], axis=0)
        scores[~self.used[words["script"]]] = 0
        return scores + self.barred[words["script"]]


def viterbi(scores: np.ndarray, bounds: np.ndarray, penalty: float = SWITCH, block: int = BLOCK_WORDS) -> np.ndarray:
    """Best label of each word; ``bounds`` are the first words of the sequences and the end. Blocks run in step."""
    n, k = scores.shape
    if not n or k == 1:
        return np.zeros(n, np.int64)
    sizes = np.diff(bounds)
    per = -(-sizes // block)
    seq = np.repeat(np.arange(len(sizes)), per)
    place = np.arange(len(seq)) - np.repeat(np.cumsum(per) - per, per)
    begin = bounds[seq] + place * block
    size = np.minimum(block, bounds[seq + 1] - begin)
    order = np.argsort(-size, kind="stable")
    begin_o, size_o = begin[order], size[order]
    active = [int(np.searchsorted(-size_o, -t, "left")) for t in range(int(size_o[0]))]

    # one block as a max-plus matrix: from the label before it to the label of its last word
    matrix = np.full((len(order), k, k), -1e30, np.float32)
    matrix[:, np.arange(k), np.arange(k)] = 0
    long_ones = int((per[seq[order]] > 1).any())
    if long_ones:
        for t, m in enumerate(active):
            v = matrix[:m]
            matrix[:m] = np.maximum(v, v.max(2, keepdims=True) - penalty) + scores[begin_o[:m] + t][:, None, :]
    back_to = np.empty(len(order), np.int64)
    back_to[order] = np.arange(len(order))
    entry = np.zeros((len(order), k), np.float32)  # by sorted block
    first = np.cumsum(per) - per
    for step in range(1, int(per.max(initial=0))):
        has = np.flatnonzero(per > step)
        was, now = back_to[first[has] + step - 1], back_to[first[has] + step]
        entry[now] = (entry[was][:, :, None] + matrix[was]).max(1)
        entry[now] -= entry[now].max(1, keepdims=True)

    value = entry.copy()
    back = np.zeros((n, k), np.uint8 if k < 256 else np.int32)
    for t, m in enumerate(active):
        v = value[:m]
        top = v.argmax(1)
        best = v[np.arange(m), top][:, None] - penalty
        stay = v >= best
        at = begin_o[:m] + t
        back[at] = np.where(stay, np.arange(k), top[:, None])
        value[:m] = np.where(stay, v, best) + scores[at]

    # from each possible last label of a block to the label before the block
    to = np.tile(np.arange(k), (len(order), 1))
    for t in range(len(active) - 1, -1, -1):
        m = active[t]
        to[:m] = np.take_along_axis(back[begin_o[:m] + t], to[:m], 1)
    last = np.zeros(len(order), np.int64)
    for step in range(int(per.max(initial=0)) - 1, -1, -1):
        ends = back_to[(first + step)[per == step + 1]]
        last[ends] = value[ends].argmax(1)
        has = np.flatnonzero(per > step + 1)
        now, nxt = back_to[first[has] + step], back_to[first[has] + step + 1]
        last[now] = to[nxt, last[nxt]]
    label = np.zeros(n, np.int64)
    state = last
    for t in range(len(active) - 1, -1, -1):
        m = active[t]
        at = begin_o[:m] + t
        label[at] = state[:m]
        state[:m] = back[at, state[:m]]
    return label


def label_texts(model: Model, texts: list[str]) -> tuple[list[str], list[float], dict[str, np.ndarray], np.ndarray]:
    """Language and score of each text, with the words and their labels."""
    words = cut_words(texts)
    bounds = np.searchsorted(words["owner"], np.arange(len(texts) + 1))
    k = max(1, len(model.langs))
    label = viterbi(model.word_scores(words), bounds) if model.langs else np.zeros(len(words["at"]), np.int64)
    letters = np.bincount(words["owner"] * k + label, words["size"], len(texts) * k).reshape(len(texts), k)
    total, top = letters.sum(1), letters.argmax(1)
    known = (total > 0) & bool(model.langs)
    score = np.where(known, letters.max(1) / np.maximum(total, 1), 0.0)
    return [model.langs[t] if ok else UNKNOWN for t, ok in zip(top, known)], score.tolist(), words, label


def spans_of(model: Model, n: int, words: dict[str, np.ndarray], label: np.ndarray) -> list[list[dict]]:
    """Per text, runs of words with one label: start, end (code points), lang."""
    out: list[list[dict]] = [[] for _ in range(n)]
    if not len(label) or not model.langs:
        return out
    owner = words["owner"]
    new = np.flatnonzero(np.concatenate(([True], (owner[1:] != owner[:-1]) | (label[1:] != label[:-1]))))
    end = words["start"] + words["size"]
    for a, b in zip(new, [*new[1:], len(label)]):
        out[owner[a]].append({"start": int(words["start"][a]), "end": int(end[b - 1]), "lang": model.langs[label[a]]})
    return out


def train(labelled: DataFrame, text: str = "text", lang: str = "lang", key: str = "doc_id", rows: int = TRAIN_ROWS) -> Model:
    """Learn from about ``rows`` labelled rows at most, shared evenly by the languages, chosen by a hash of key and text; whole texts."""
    src = labelled.filter(labelled[lang].isNotNull() & labelled[text].isNotNull()).select(labelled[lang].alias("lang"), labelled[text].alias("text"), F.xxhash64(labelled[key], labelled[text]).alias("h"))
    counts = src.groupBy("lang").count().collect()
    # one row a language, of each of which the model holds a whole table: the texts stay where they are
    rates = [(r["lang"], float(1 << 30) * rows / len(counts) / r["count"]) for r in counts]
    rates = F.broadcast(src.sparkSession.createDataFrame(rates, "lang string, rate double"))
    src = src.join(rates, "lang").filter(F.pmod(F.col("h"), F.lit(1 << 30)) < F.col("rate"))

    def run(batches):
        sums: dict[str, np.ndarray] = {}
        for batch in slices(batches):
            langs, texts = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for code in set(langs):
                mine = [t for t, c in zip(texts, langs) if c == code]
                for a, b in _blocks(mine):
                    words = cut_words(mine[a:b])
                    counts = np.bincount(words["bucket"], minlength=BUCKETS)
                    scripts = np.bincount(words["script"], minlength=len(SCRIPTS))
                    row = np.concatenate((counts, scripts))
                    sums[code] = sums[code] + row if code in sums else row
        for code, row in sums.items():
            at = np.flatnonzero(row)
            yield pa.RecordBatch.from_arrays([pa.array([code] * len(at), pa.string()), pa.array(at, pa.int32()), pa.array(row[at], pa.int64())], names=["lang", "slot", "n"])

    # a language has at most BUCKETS + len(SCRIPTS) rows here
    with batch_bounds(src.sparkSession):
        got = src.select("lang", "text").mapInArrow(run, "lang string, slot int, n long").groupBy("lang", "slot").agg(F.sum("n").alias("n")).toPandas()
    langs = sorted(got["lang"].unique())
    full = np.zeros((BUCKETS + len(SCRIPTS), len(langs)))
    full[got["slot"].to_numpy(int), np.searchsorted(langs, got["lang"].to_numpy(str)) if langs else []] = got["n"]
    return Model(langs, full[:BUCKETS], full[BUCKETS:])


def _blocks(texts: list[str]):
    begin = chars = 0
    for i, t in enumerate(texts):
        if i > begin and chars + len(t) > BLOCK_CHARS:
            yield begin, i
            begin, chars = i, 0
        chars += len(t)
    if begin < len(texts):
        yield begin, len(texts)


def identify(df: DataFrame, model: Model, text: str = "text", spans: bool = False) -> DataFrame:
    """All columns of ``df`` plus ``lang_pred``, ``score`` and, if asked for, ``lang_spans``.

    The columns other than the text do not pass through Python unless they are in ``df``;
    give it only the columns needed. A column named like an output is replaced.
    """
    outputs = ("lang_pred", "score", "lang_spans")
    kept = [c for c in df.columns if c not in outputs and c != text]
    held = df.sparkSession.sparkContext.broadcast(model)
    src = df.select(*kept, df[text].cast("string").alias(text))
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in src.schema) + ", lang_pred string, score double" + ", lang_spans array<struct<start:int,end:int,lang:string>>" * spans
    span = pa.struct([("start", pa.int32()), ("end", pa.int32()), ("lang", pa.string())])

    def run(batches):
        tool = held.value
        for batch in slices(batches):
            texts = [t or "" for t in batch.column(batch.num_columns - 1).to_pylist()]
            for a, b in _blocks(texts):
                langs, score, words, label = label_texts(tool, texts[a:b])
                part = batch.slice(a, b - a)
                more = [pa.array(langs, pa.string()), pa.array(score, pa.float64())]
                if spans:
                    more.append(pa.array(spans_of(tool, b - a, words, label), pa.list_(span)))
                yield pa.RecordBatch.from_arrays([*part.columns, *more], names=[*part.schema.names, "lang_pred", "score", *["lang_spans"] * spans])

    return src.mapInArrow(run, schema)


def held_out(doc_id: str = "doc_id"):
    """Rows that are never learned from: crc32 of the id as text, mod 5, is 0."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string")), F.lit(5)) == 0, F.lit(False))


def train_on_documents(docs: DataFrame) -> Model:
    return train(docs.filter(F.col("doc_id").isNotNull() & ~held_out()))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    named = identify(docs.select("doc_id", held_out().alias("held_out"), "text"), train_on_documents(docs))
    return named.select("doc_id", "held_out", "lang_pred", "score")
