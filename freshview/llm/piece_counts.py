"""Token counts by a linear longest-match automaton over a word-piece vocabulary.

Greedy longest match cuts a word piece by piece, each the longest vocabulary entry
that fits. Doing it literally rescans after each piece. Here the vocabulary is a trie
whose nodes have a failure link and a precomputed number of popped tokens: when the
next character has no edge, the node's pieces are popped (counted, not built) and the
walk goes on at the failure node, which stands for the same characters without the
popped pieces. Every character is read once, so a word costs time in its length.

The vocabulary is the byte-level one: a word (a run of characters other than ASCII
white space, as bytes) is read with one blank before it, so pieces that begin with a
blank start words and the others continue them. All single bytes are pieces, so every
word can be cut. Words are counted first; a word's length is looked up once per worker.

Defined cases: null, empty and white texts count 0 tokens and 0 words; each input row
gives one row; words of any length are cut; a vocabulary that misses a byte counts the
byte as one unknown token; other columns are not read.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .byte_bpe import load_ranks, vocabulary
from .common import slices, table

WORD = re.compile(rb"[^\x20\x09-\x0D]+")
CACHE_WORDS, CACHE_BYTES = 400_000, 64


class LongestMatch:
    """Trie with failure links and popped-token counts."""

    def __init__(self, pieces) -> None:
        self.next: list[dict[int, int]] = [{}]
        whole = [False]
        for piece in pieces:
            node = 0
            for byte in piece:
                child = self.next[node].get(byte)
                if child is None:
                    child = self.next[node][byte] = len(self.next)
                    self.next.append({})
                    whole.append(False)
                node = child
            whole[node] = node > 0
        n = len(self.next)
        #: Where to go on when no edge fits, and the tokens popped by that; -1 where nothing can be popped.
        self.fail, self.popped = [-1] * n, [0] * n
        layer = [0]
        while layer:
            below = []
            for node in layer:
                for byte, child in self.next[node].items():
                    below.append(child)
                    if whole[child]:
                        self.fail[child], self.popped[child] = 0, 1
                        continue
                    at, popped = self.fail[node], self.popped[node]
                    while at >= 0 and byte not in self.next[at]:
                        popped += self.popped[at]
                        at = self.fail[at]
                    if at >= 0:
                        self.fail[child], self.popped[child] = self.next[at][byte], popped
            layer = below
        #: Bytes from the root; a child is always numbered after its parent.
        self.depth = [0] * n
        for node, edges in enumerate(self.next):
            for child in edges.values():
                self.depth[child] = self.depth[node] + 1

    def count(self, word: bytes) -> int:
        """Pieces of the greedy longest-match cut of a word."""
        following, fail, popped = self.next, self.fail, self.popped
        node = total = 0
        for byte in word:
            while True:
                child = following[node].get(byte)
                if child is not None:
                    node = child
                    break
                if fail[node] < 0:
                    # no piece ends here: at the root the byte itself is unknown, below it the held bytes are
                    total += self.depth[node] + (node == 0)
                    if node == 0:
                        break
                    node = 0
                    continue
                total += popped[node]
                node = fail[node]
        while node > 0:
            if fail[node] < 0:
                return total + self.depth[node]
            total += popped[node]
            node = fail[node]
        return total


class _Lengths(dict):
    def __init__(self, automaton: LongestMatch) -> None:
        self.automaton = automaton

    def __missing__(self, word: bytes) -> int:
        n = self.automaton.count(b" " + word)
        if len(word) <= CACHE_BYTES:
            if len(self) >= CACHE_WORDS:
                self.clear()
            self[word] = n
        return n


_lengths: dict[str, _Lengths] = {}


def _tool(path: str) -> _Lengths:
    if path not in _lengths:
        _lengths[path] = _Lengths(LongestMatch(load_ranks(path)))
    return _lengths[path]


def count_tokens(df: DataFrame, doc_id: str = "doc_id", text: str = "text", path: str | None = None) -> DataFrame:
    """Per row: doc_id, n_words, n_tokens, longest (most tokens of one word)."""
    path = path or vocabulary()
    src = df.select(df[doc_id].alias("doc_id"), df[text].cast("string").alias("text"))

    def run(batches):
        tool = _tool(path)
        for batch in slices(batches):
            rows = []
            for text in batch.column(1).cast(pa.binary()).to_pylist():
                words = WORD.findall(text or b"")
                counts = np.fromiter(map(tool.__getitem__, words), np.int64, len(words))
                rows.append((len(words), int(counts.sum()), int(counts.max(initial=0))))
            columns = list(zip(*rows)) or [()] * 3
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, pa.int64()) for c in columns)], names=["doc_id", "n_words", "n_tokens", "longest"])

    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n_words long, n_tokens long, longest long")


def op3_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"))
