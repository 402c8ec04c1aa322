"""Byte-level BPE by longest matches and backtracking, equal to merging by rank.

Bytes are taken as Latin-1 characters, so one Aho-Corasick automaton over the whole vocabulary finds every token
in a piece in one pass.  A sequence of tokens is what merging gives just if each two neighbours are
compatible: merging their joined bytes gives them back.  From the left the longest compatible
token is taken; a position from which no way leads on is marked dead and left for good, so each position is tried
once.  Compatibility of two tokens is decided by undoing merges from their seam and is memoised.

Defined results: null text is an empty text; an empty text has no tokens; text without any known byte
can't occur, since every byte is a token; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import hashlib
from functools import lru_cache

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import ship
from .units import Memo, cut_at_spaces

SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


def load_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, f) if token}


class ByteBPE:
    def __init__(self, ranks: dict[bytes, int]):
        import ahocorasick

        self.size = max(ranks.values()) + 1
        self.token = [b""] * self.size
        self.found = ahocorasick.Automaton()
        for token, rank in ranks.items():
            self.token[rank] = token
            if len(token) > 1:  # single bytes match everywhere; a table serves them
                self.found.add_word(token.decode("latin-1"), (rank, len(token) - 1))
        self.single = [ranks.get(bytes([b]), -1) for b in range(256)].__getitem__
        #: The longest other token that a token begins with.
        self.shorter = [next((ranks[t[:k]] for k in range(len(t) - 1, 0, -1) if t[:k] in ranks), -1) for t in self.token]
        if len(self.found):
            self.found.make_automaton()
        self.seam = Memo(self._seam, 1_000_000)
        self.joined: dict[int, int] = {}
        self.halves: list[tuple[int, int] | None] = [None] * self.size
        for rank in sorted(ranks.values()):
            token = self.token[rank]
            for cut in range(len(token) - 1, 0, -1):
                left, right = ranks.get(token[:cut], rank), ranks.get(token[cut:], rank)
                if left < rank and right < rank and self._holds(left, right):
                    self.halves[rank], self.joined[left * self.size + right] = (left, right), rank
                    break

    def _holds(self, left: int, right: int) -> bool:
        """Does merging the bytes of both tokens leave the seam between them?

        Merges are undone from the last to the first on the side whose token is younger; a merge over the seam
        that comes before the last one undone would have been made.
        """
        bound, halves, joined, size = self.size, self.halves, self.joined, self.size
        while True:
            if joined.get(left * size + right, bound) < bound:
                return False
            if halves[left] and (left > right or not halves[right]):
                bound, left = left, halves[left][1]
            elif halves[right]:
                bound, right = right + 1, halves[right][0]
            else:
                return True

    def _seam(self, key: int) -> bool:
        return self._holds(*divmod(key, self.size))

    def encode_piece(self, piece: bytes) -> list[int]:
        """Token ids of one piece of the pre-tokeniser."""
        n = len(piece)
        longest = list(map(self.single, piece))
        for end, (rank, before) in self.found.iter(piece.decode("latin-1")) if len(self.found) else ():
            longest[end - before] = rank  # the ends ascend, so the longest stays
        token, shorter, seam, size = self.token, self.shorter, self.seam, self.size
        if n and longest[0] >= 0 and len(token[longest[0]]) == n:
            return [longest[0]]
        dead, ids, pos, last = set(), [], 0, -1
        while pos < n:
            rank = longest[pos]
            while rank >= 0 and (last >= 0 and not seam[last * size + rank] or pos + len(token[rank]) in dead):
                rank = shorter[rank]
            if rank >= 0:
                ids.append(rank)
                pos += len(token[rank])
            else:
                dead.add(pos)
                if not ids:
                    raise ValueError("the vocabulary lacks a byte")
                pos -= len(token[ids.pop()])
            last = ids[-1] if ids else -1
        return ids


class TextCodec:
    """Encodes whole texts by memoised units, each piece of the pattern separately."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.bpe = ByteBPE(ranks)
        self.find = regex.compile(pattern).findall
        self.by_text = {str(r): t for r, t in enumerate(self.bpe.token)}
        self.piece = Memo(lambda p: " ".join(map(str, self.bpe.encode_piece(p.encode())))).__getitem__
        self.later = Memo(self._later).__getitem__
        self.bytes_of = Memo(lambda ids: b"".join(map(self.by_text.__getitem__, ids.split()))).__getitem__

    def _alone(self, text: str) -> str:
        return " ".join(map(self.piece, self.find(text)))

    def _later(self, unit: str) -> str | None:
        """Ids of a space and the unit; None if more white space follows, so that the unit has no end of its own."""
        if not unit or unit[-1].isspace():
            return None
        if unit.isascii():
            if unit.isalpha():
                return self.piece(" " + unit)
            if unit[-1] in ".,;:!?" and unit[:-1].isalpha():
                return f"{self.piece(' ' + unit[:-1])} {self.piece(unit[-1])}"
        return self._alone(" " + unit)

    def encode_units(self, text: str | None) -> list[str]:
        """Decimal ids of each unit, joined by spaces."""
        if not text:
            return []
        first, *rest = text.split(" ")
        if rest and first and not first[-1].isspace():
            last = self._alone(" " + rest.pop())
            units = [self._alone(first), *map(self.later, rest), last]
            if None not in units:  # a None: white space before a space
                return units
        return list(map(self._alone, cut_at_spaces(text)))

    def encode(self, text: str | None) -> list[int]:
        return [int(x) for unit in self.encode_units(text) for x in unit.split()]

    def decode_units(self, units: list[str]) -> bytes:
        return b"".join(map(self.bytes_of, units))


@lru_cache(maxsize=2)
def codec(path: str, pattern: str) -> TextCodec:
    return TextCodec(load_ranks(path), pattern)


def encode_table(docs: DataFrame, ranks: str | None = None, pattern: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids of every document."""
    ship(docs.sparkSession)
    path, pattern = _defaults(ranks, pattern)

    def run(batches):
        c = codec(path, pattern)
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([c.encode(t.as_py()) for t in batch.column(1)], pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, "doc_id long, ids array<int>")


def _defaults(ranks: str | None, pattern: str | None) -> tuple[str, str]:
    import public_tokenizers

    return ranks or public_tokenizers.path("byte_bpe_50k.tiktoken"), pattern or public_tokenizers.PATTERN


def round_trip(docs: DataFrame, ranks: str | None = None, pattern: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Encode every text, decode the ids, and give digests of both."""
    ship(docs.sparkSession)
    path, pattern = _defaults(ranks, pattern)

    def run(batches):
        c = codec(path, pattern)
        for batch in batches:
            n, enc, dec = [], [], []
            for t in batch.column(1):
                units = c.encode_units(t.as_py())
                ids = " ".join(units)
                n.append(ids.count(" ") + bool(ids))
                enc.append(hashlib.sha256(ids.encode()).hexdigest())
                dec.append(hashlib.sha256(c.decode_units(units)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(enc, pa.string()), pa.array(dec, pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, SCHEMA)
