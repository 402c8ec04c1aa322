"""Word-piece lengths by a linear longest-match automaton.

The vocabulary is a trie over bytes.  A failure link leads from a state to the state reached after
the greedy matches that end there are taken off, and the number of those matches is stored with the link, so a
word's number of greedy pieces is found in one pass without making the pieces.

Word-initial pieces begin with the mark, the others continue a word.  Words are split at ASCII white space.

Defined results: null and empty texts have no words and no pieces; a word that no sequence of pieces spells
counts as one unknown piece; an empty table gives an empty result.
"""

from __future__ import annotations

import json
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import ship
from .subwords import BYTE_CHARS, default_path
from .units import Memo

MARK = 0x20


class LongestMatch:
    """Counts greedy longest-match pieces of a word (bytes), the mark put before it."""

    def __init__(self, vocabulary: list[bytes]):
        self.child: dict[int, int] = {}
        ends = [False]
        for piece in vocabulary:
            node = 0
            for b in piece:
                key = node << 8 | b
                node = self.child.get(key, -1)
                if node < 0:
                    node = self.child[key] = len(ends)
                    ends.append(False)
            ends[node] = bool(piece)
        self.fail, self.popped = [-1] * len(ends), [0] * len(ends)
        edges: dict[int, list[tuple[int, int]]] = {}
        for key, node in self.child.items():
            edges.setdefault(key >> 8, []).append((key & 255, node))
        level = [0]
        while level:
            below = []
            for node in level:
                for b, v in edges.get(node, ()):
                    below.append(v)
                    if ends[v]:
                        self.fail[v], self.popped[v] = 0, 1
                        continue
                    back, taken = self.fail[node], self.popped[node]
                    while back >= 0 and (back << 8 | b) not in self.child:
                        taken += self.popped[back]
                        back = self.fail[back]
                    if back >= 0:
                        self.fail[v], self.popped[v] = self.child[back << 8 | b], taken
            level = below

    def count(self, word: bytes, mark: int | None = MARK) -> int:
        """Number of pieces, or 1 where the pieces can't spell the word."""
        child, fail, popped = self.child, self.fail, self.popped
        node = taken = 0
        for b in word if mark is None else bytes([mark]) + word:
            while (step := child.get(node << 8 | b, -1)) < 0:
                taken += popped[node]
                node = fail[node]
                if node < 0:
                    return 1
            node = step
        while node:
            taken += popped[node]
            node = fail[node]
            if node < 0:
                return 1
        return taken


def vocabulary_of(path: str) -> list[bytes]:
    """Byte strings of a byte-level vocabulary file; its word mark is a space."""
    back = {c: b for b, c in enumerate(BYTE_CHARS)}
    with open(path, encoding="utf-8") as f:
        pieces = json.load(f)["model"]["vocab"]
    spelled = (bytes(back[c] for c in p) for p in pieces if all(c in back for c in p))
    return [p for p in spelled if b" " not in p[1:]]


@lru_cache(maxsize=2)
def automaton(path: str) -> LongestMatch:
    return LongestMatch(vocabulary_of(path))


def piece_counts(docs: DataFrame, vocabulary: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, n_pieces of every document."""
    ship(docs.sparkSession)
    path = vocabulary or default_path()

    def run(batches):
        get = Memo(automaton(path).count).__getitem__
        for batch in batches:
            words = [(t.as_py() or "").encode().split() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([len(w) for w in words], pa.int64()), pa.array([sum(map(get, w)) for w in words], pa.int64())], names=["doc_id", "n_words", "n_pieces"])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, "doc_id long, n_words long, n_pieces long")
