"""Token counts: greedy longest-match word pieces, counted by an automaton in linear time.

A vocabulary trie has, for each node, a failure link and the number of pieces popped when it is
followed: what greedy matching would have emitted before going on with the rest. A word is read
once, byte by byte, and only popped counts are added; no piece is built. A word starts with the
byte for a blank, as in vocabularies whose word-initial pieces carry it. A word that can't be
segmented counts as one unknown token.

Defined results: null and empty texts have no tokens; repeated rows give a row each; any other
columns are ignored.
"""

from __future__ import annotations

import base64
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
WORD = re.compile(rb"[^\x20\x09-\x0D]+")
#: Words whose counts a task remembers at a time.
REMEMBERED = 200_000


def read_vocabulary(path: str) -> list[bytes]:
    """Pieces of a rank file: base64 and rank on each line."""
    with open(path, "rb") as f:
        return [base64.b64decode(line.split()[0]) for line in f if line.strip()]


class Automaton:
    """Trie over the pieces; node 0 is the root. ``fail`` is -1 where no piece can be popped."""

    def __init__(self, vocabulary: list[bytes]):
        self.next: list[dict[int, int]] = [{}]
        self.fail: list[int] = [-1]
        self.pops: list[int] = [0]
        ends = [False]
        for piece in vocabulary:
            node = 0
            for byte in piece:
                to = self.next[node].get(byte)
                if to is None:
                    to = len(ends)
                    self.next[node][byte] = to
                    self.next.append({})
                    self.fail.append(-1)
                    self.pops.append(0)
                    ends.append(False)
                node = to
            ends[node] = node != 0
        level = [0]
        while level:  # by depth, so that shorter prefixes are known
            after = []
            for node in level:
                for byte, child in self.next[node].items():
                    after.append(child)
                    if ends[child]:
                        self.fail[child], self.pops[child] = 0, 1
                        continue
                    at, popped = self.fail[node], self.pops[node]
                    while at >= 0 and byte not in self.next[at]:
                        popped += self.pops[at]
                        at = self.fail[at]
                    if at >= 0:
                        self.fail[child], self.pops[child] = self.next[at][byte], popped
            level = after

    def count(self, word: bytes) -> int:
        """Pieces of ``word`` under greedy longest match; 1 if it can't be segmented."""
        node, total = 0, 0
        step, fail, pops = self.next, self.fail, self.pops
        for byte in word:
            while byte not in step[node]:
                total += pops[node]
                node = fail[node]
                if node < 0:
                    return 1
            node = step[node][byte]
        while node > 0:
            total += pops[node]
            node = fail[node]
        return total if node == 0 else 1


class _Counts(dict):
    def __init__(self, automaton: Automaton):
        self.automaton = automaton

    def __missing__(self, word: bytes) -> int:
        if len(self) >= REMEMBERED:
            self.clear()
        found = self.automaton.count(b" " + word)
        if len(word) <= 64:
            self[word] = found
        return found


def token_counts(docs: DataFrame, vocabulary: str = VOCABULARY, text: str = "text") -> DataFrame:
    """(doc_id, n_words, n_tokens, n_bytes) of every row; the vocabulary file must be on each node
    or its pieces are read once here and broadcast (they are, as the file is fixed and small)."""
    pieces = docs.sparkSession.sparkContext.broadcast(read_vocabulary(vocabulary))

    def counted(batches):
        counts = _Counts(Automaton(pieces.value))
        for batch in batches:
            rows = []
            for value in batch.column("text"):
                raw = value.as_py()
                raw = raw.encode() if raw else b""
                words = WORD.findall(raw)
                rows.append((len(words), sum(map(counts.__getitem__, words)), len(raw)))
            cols = [pa.array(c, pa.int64()) for c in zip(*rows, strict=True)] if rows else [pa.array([], pa.int64())] * 3
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), *cols], ["doc_id", "n_words", "n_tokens", "n_bytes"]
            )

    rows = docs.select("doc_id", F.col(text).alias("text"))
    return rows.mapInArrow(
        counted, f"doc_id {dict(rows.dtypes)['doc_id']}, n_words bigint, n_tokens bigint, n_bytes bigint"
    )


def query(spark, sf_dir: str) -> DataFrame:
    from bucketseed.tables import load

    return token_counts(load(spark, sf_dir, "documents"))
