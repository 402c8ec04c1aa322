"""Whole-text encoding with the tokenizers library, by units that recur."""

from __future__ import annotations

import os
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from .units import cut_at_spaces

END_ID = 0
_SHOWN = {*range(33, 127), *range(161, 173), *range(174, 256)}
#: Byte-level vocabularies write a byte that can be shown as itself, the others as the characters from 256 on.
_HIDDEN = [b for b in range(256) if b not in _SHOWN]
BYTE_CHARS = [chr(b) if b in _SHOWN else chr(256 + _HIDDEN.index(b)) for b in range(256)]
#: Units that a worker remembers besides those of the texts at hand; with some 200 bytes each that is 100 MB in all.
REMEMBERED = 500_000
#: Latin letters, which no version of the pre-tokeniser's pattern sees otherwise, and marks.
_LETTERS, _MARKS = "A-Za-zÀ-ÖØ-öø-ɏ", r"!-/:-@\[-`{-~"
#: Each byte's character, as its code point; a line end stays, as it stands between words.
_CODES = np.array([10 if b == 10 else ord(c) for b, c in enumerate(BYTE_CHARS)], "<u4")
#: Bytes of texts that are looked up together.
LOT_BYTES = 4_000_000


def default_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


@lru_cache(maxsize=2)
def unit_encoder(path: str, added: bool = False):
    """encode(text) -> ids as little-endian unsigned 32-bit bytes; equal to the library's encoding of the whole text."""
    lot = lot_encoder(path, added)
    return lambda text: lot([text])[0]


def lot_encoder(path: str, added: bool = False, remembered: int = REMEMBERED):
    """encode(texts) -> the ids of each text as little-endian unsigned 32-bit bytes; equal to the library's encoding of the whole text."""
    arrays = array_encoder(path, added, remembered)

    def encode(texts: list[str | None]) -> list[bytes]:
        flat, sizes = arrays(pa.array(texts, pa.string()))
        ends = np.cumsum(sizes).tolist()
        return [flat[a:b].tobytes() for a, b in zip([0, *ends], ends)]

    return encode


class _Pool:
    """Ids of the pieces that a worker met, end to end; `at` has a piece's place, first and size its ids."""

    def __init__(self):
        self.at: dict[str, int] = {}
        self.flat, self.first, self.size = np.zeros(0, "<u4"), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def add(self, pieces: list[str], flat: np.ndarray, size: np.ndarray) -> None:
        more = self.joined(flat, size)
        self.at.update(zip(pieces, range(len(self.at), len(self.at) + len(pieces))))
        self.flat, self.first, self.size = more.flat, more.first, more.size

    def joined(self, flat: np.ndarray, size: np.ndarray) -> _Pool:
        """With more pieces, which have the next places."""
        out = _Pool()
        out.first = np.concatenate([self.first, len(self.flat) + np.cumsum(size) - size])
        out.size, out.flat = np.concatenate([self.size, size]), np.concatenate([self.flat, flat])
        return out

    def places(self, pieces: list[str]) -> np.ndarray:
        return np.fromiter(map(self.at.__getitem__, pieces), np.int64, len(pieces))

    def ids(self, places: np.ndarray) -> np.ndarray:
        size = self.size[places]
        shift = self.first[places] - (np.cumsum(size) - size)
        return self.flat[np.repeat(shift, size) + np.arange(size.sum())]


@lru_cache(maxsize=2)
def array_encoder(path: str, added: bool = False, remembered: int = REMEMBERED):
    """encode(string array) -> all ids end to end as unsigned 32-bit integers, and how many each text has (null: none).

    Equal to the library's encoding of the whole texts.  Texts are cut before single spaces.  Units that were met before come from memory; new ones are cut again, between a
    Latin letter and a mark or line end and behind a line end between two others, where the pre-tokeniser cuts too.  What is then one word, with its space, goes
    through the library's model, all of a lot together; the rest through the whole library.  Texts in which white space stands before a
    space are cut by a pattern instead.  With `added`, strings of added tokens get their ids, as the library's own setting has it, by
    the library's encoding of the whole text that holds one; otherwise they are ordinary text.
    """
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer, pre_tokenizers

    library = Tokenizer.from_file(path)
    special = [t.content for t in library.get_added_tokens_decoder().values() if t.content] if added else []
    library.encode_special_tokens = not added  # else their strings in a text are ordinary text
    plain = library.normalizer is None
    words_only = Tokenizer(library.model)
    words_only.pre_tokenizer = pre_tokenizers.CharDelimiterSplit("\n")
    vocabulary = library.get_vocab()
    width = np.zeros(1 + max(vocabulary.values()), np.int64)  # bytes of each token
    width[list(vocabulary.values())] = list(map(len, vocabulary))
    pool = _Pool()

    def one_by_one(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        ids = [e.ids for e in library.encode_batch_fast(texts, add_special_tokens=False)]
        size = np.fromiter(map(len, ids), np.int64, len(ids))
        return np.fromiter((i for x in ids for i in x), "<u4", size.sum()), size

    def words(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of words, by the model alone."""
        shown = _CODES[np.frombuffer("\n".join(texts).encode(), np.uint8)].tobytes().decode("utf-32-le")
        flat = np.array(words_only.encode_batch_fast([shown], add_special_tokens=False)[0].ids, "<u4")
        upto, ends = np.cumsum(width[flat]), np.cumsum(np.fromiter((len(x.encode()) for x in texts), np.int64, len(texts)))
        last = np.searchsorted(upto, ends)
        if last[-1] >= len(upto) or (upto[last] != ends).any():  # a vocabulary without some byte
            return one_by_one(texts)
        return flat, np.diff(last, prepend=-1)

    def learn(pieces: list[str], encoder) -> None:
        new = [x for x in pieces if x not in pool.at]
        if new:
            got = [encoder(new[i : i + 5000]) for i in range(0, len(new), 5000)]
            pool.add(new, *map(np.concatenate, zip(*got)))

    def learn_units(units: list[str]) -> None:
        """Units with one space, at their begin, and no white space at their end."""
        units = [x for x in units if x not in pool.at]
        learn([x for x in units if "\0" in x], one_by_one)  # what marks cuts below
        units = [x for x in units if "\0" not in x]
        marked = pc.replace_substring_regex(pa.array(units, pa.string()), f"([{_LETTERS}])([{_MARKS}\n])", "\\1\0\\2")
        marked = pc.replace_substring_regex(marked, f"([{_LETTERS}{_MARKS}])\n([{_LETTERS}])", "\\1\n\0\\2")
        split = pc.split_pattern(marked, "\0")
        coded, first = split.flatten().dictionary_encode(), split.offsets.to_numpy()[:-1]
        names, word = coded.dictionary.to_numpy(zero_copy_only=False), pc.match_substring_regex(coded.dictionary, f"^ ?[{_LETTERS}]+$").to_numpy(zero_copy_only=False)
        learn(names[word].tolist(), words)
        learn(names[~word].tolist(), one_by_one)
        at = pool.places(names.tolist())[coded.indices.to_numpy()]
        several = np.diff(first, append=len(at)) > 1
        if several.any():
            at, count = at[np.repeat(several, np.diff(first, append=len(at)))], np.diff(first, append=len(at))[several]
            pool.add([x for x, more in zip(units, several.tolist()) if more], pool.ids(at), np.add.reduceat(pool.size[at], np.cumsum(count) - count))

    def encode_lot(texts: pa.Array, whole: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Texts that are not empty; the whole ones are not cut."""
        nonlocal pool
        split = pc.split_pattern(texts, " ")
        coded, bounds = split.flatten().dictionary_encode(), split.offsets.to_numpy().astype(np.int64)
        unit, names = coded.indices.to_numpy(), coded.dictionary.to_numpy(zero_copy_only=False).tolist()
        begin, last = bounds[:-1] - bounds[0], bounds[1:] - bounds[0] - 1
        length = pc.binary_length(coded.dictionary).to_numpy()
        open_end = (length == 0) | (pc.binary_length(pc.utf8_rtrim_whitespace(coded.dictionary)).to_numpy() < length)
        inner = open_end[unit]
        inner[last] = False  # the last unit of a text may end in white space
        odd = np.flatnonzero(np.logical_or.reduceat(inner, begin) | whole).tolist()
        spaced = [" " + x for x in names]
        closed = [x for x, is_open in zip(spaced, open_end.tolist()) if not is_open]
        if len(pool.at) > remembered:
            old, keep = pool, [x for x in closed if x in pool.at]
            pool, places = _Pool(), old.places(keep)
            pool.add(keep, old.ids(places), old.size[places])
        learn_units(closed)
        # texts' first units, those that end in white space, and what is cut otherwise, are not remembered: they can be as long as texts
        cut = {i: [texts[i].as_py()] if whole[i] else cut_at_spaces(texts[i].as_py()) for i in odd}
        starts, ends = [names[i] for i in unit[begin].tolist()], [spaced[i] for i in unit[last].tolist()]
        others = list(dict.fromkeys([*starts, *(x for x in ends if x not in pool.at), *(x for xs in cut.values() for x in xs)]))
        here = dict(zip(others, range(len(pool.at), len(pool.at) + len(others))))
        known = pool.joined(*one_by_one(others))
        place = np.zeros(len(names), np.int64)
        place[~open_end] = pool.places(closed)
        at = place[unit]
        at[last] = [here[x] if x in here else pool.at[x] for x in ends]
        at[begin] = [here[x] for x in starts]
        counts, parts, done = last + 1 - begin, [], 0
        for i, xs in cut.items():
            parts += [at[done : begin[i]], np.array([here[x] for x in xs], np.int64)]
            counts[i], done = len(xs), last[i] + 1
        at = np.concatenate([*parts, at[done:]])
        return known.ids(at), np.add.reduceat(known.size[at], np.cumsum(counts) - counts)

    def encode(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        size = np.zeros(len(texts), np.int64)
        length = pc.fill_null(pc.binary_length(texts), 0).to_numpy()
        whole = np.zeros(len(texts), bool)
        for x in special:
            whole |= pc.fill_null(pc.match_substring(texts, x), False).to_numpy(zero_copy_only=False)
        rows = np.flatnonzero(length)
        out = [np.zeros(0, "<u4")]
        for own in np.split(rows, np.flatnonzero(np.diff(np.cumsum(length[rows]) // LOT_BYTES)) + 1):
            if len(own):
                part = texts.take(pa.array(own))
                flat, size[own] = encode_lot(part, whole[own]) if plain else one_by_one(part.to_pylist())
                out.append(flat)
        return np.concatenate(out), size

    return encode
