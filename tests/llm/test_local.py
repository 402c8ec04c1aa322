"""Operators' cores without Spark: brute force, round trips, exact libraries."""

import base64
import random
import re
from collections import Counter

import numpy as np
import public_tokenizers as P
import pytest

from provgraph.llm import ann, bpe, jaccard, langid, packing, quality, subwords, toxicity, wordpieces

ODD = ["", " ", "  ", "a", " a", "a ", "a  b", "a \n b", "\n  x\t y  ", "don't we'll 's", "x<|endoftext|> y", "日本 語 　 x", " é  ü.\n", "aaaaaaaaaaaaaa", "tab\tend ", "a\x1c b", "1234567 89", "😀 😀😀", "word,word .word"]


def texts(n=200, seed=3):
    rnd = random.Random(seed)
    parts = ["th", "er", "ing", "Ö", "ñ", "é", " ", "  ", "\n", ".", ", ", "'s", "12", "###", "😀", "\t", "ion"]
    return ODD + ["".join(rnd.choice(parts) for _ in range(rnd.randrange(60))) for _ in range(n)]


def test_bpe_equals_library():
    import tiktoken

    path = P.path("byte_bpe_50k.tiktoken")
    ranks = bpe.load_ranks(path)
    library = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    codec = bpe.codec(path, P.PATTERN)
    for t in texts():
        assert codec.encode(t) == library.encode_ordinary(t), t
        assert codec.decode_units(codec.encode_units(t)) == t.encode()
    rnd = random.Random(5)
    known = list(ranks)
    for _ in range(2000):
        piece = b"".join(rnd.choice(known) for _ in range(rnd.randrange(1, 6)))
        assert codec.bpe.encode_piece(piece) == library._core_bpe.encode_single_piece(piece)


def test_unit_encoder_equals_library():
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(subwords.default_path())
    library.encode_special_tokens = True
    encode = subwords.unit_encoder(subwords.default_path())
    for t in texts():
        assert np.frombuffer(encode(t), "<u4").tolist() == library.encode(t, add_special_tokens=False).ids, t
    assert encode(None) == b""


@pytest.mark.parametrize("added", [True, False])
@pytest.mark.parametrize("remembered", [5, 500_000])
def test_array_encoder_equals_library(added, remembered):
    """All texts of a column at once: words cut at marks and line ends, what is forgotten meanwhile, nulls, slices, texts that are not cut."""
    import pyarrow as pa
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(subwords.default_path())
    library.encode_special_tokens = not added
    rows = [None, *texts(600, 7), "Ende.\nNeu,\n\nZwei é.\n(Drei) l'été''s x's\0y a\0.b", " \0", "ein <|endoftext|>, zwei", "ǅ ɐ.b Ⅷ. ª.º 'stab don't."]
    encode = subwords.array_encoder(subwords.default_path(), added, remembered)
    for _ in range(2):
        flat, sizes = encode(pa.array([None, *rows], pa.string()).slice(1))
        ends = np.cumsum(sizes).tolist()
        for t, a, b in zip(rows, [0, *ends], ends):
            assert flat[a:b].tolist() == library.encode(t or "", add_special_tokens=False).ids, t
    assert encode(pa.array([], pa.string()))[0].tolist() == encode(pa.array([None, ""]))[0].tolist() == []


def greedy(word, vocabulary):
    n, at = 0, 0
    while at < len(word):
        k = next((k for k in range(len(word), at, -1) if word[at:k] in vocabulary), None)
        if k is None:
            return 1
        at, n = k, n + 1
    return n


def test_word_piece_automaton():
    rnd = random.Random(1)
    for _ in range(60):
        vocabulary = {bytes(rnd.choice(b"abc") for _ in range(rnd.randrange(1, 5))) for _ in range(rnd.randrange(3, 14))}
        own = wordpieces.LongestMatch(sorted(vocabulary))
        for _ in range(60):
            word = bytes(rnd.choice(b"abcd"[: rnd.choice((3, 4))]) for _ in range(rnd.randrange(0, 9)))
            assert own.count(word, None) == greedy(word, vocabulary), (word, vocabulary)
    real = wordpieces.automaton(subwords.default_path())
    pieces = set(wordpieces.vocabulary_of(subwords.default_path()))
    for t in texts(80):
        for w in t.encode().split():
            assert real.count(w) == greedy(b" " + w, pieces)


def test_packing_plan():
    rnd = random.Random(2)
    for capacity in (8, 30, 2048):
        for _ in range(12):
            lengths = Counter(min(capacity, 1 + int(rnd.expovariate(1 / (capacity / 3)))) for _ in range(400))
            runs = packing.plan(dict(lengths), capacity)
            used, placed = {}, Counter()
            for n, a, b, seq, at in runs:
                placed[n] += b - a
                for k in range(b - a):
                    used.setdefault(seq + k, []).append((at, n))
            assert placed == lengths
            for items in used.values():
                at = 0
                for start, n in sorted(items):
                    assert start == at
                    at += n
                assert at <= capacity
                assert sum(3 * n > capacity for _, n in items) <= 2
            total = sum(n * c for n, c in lengths.items())
            assert len(used) <= 1.25 * -(-total // capacity) + 2
    assert packing.cut_points(5000, 2048) == [(0, 904), (904, 2048), (2952, 2048)]
    assert packing.cut_points(2048, 2048) == [(0, 2048)] and packing.cut_points(1, 2048) == [(0, 1)]
    assert packing.plan({}, 2048) == []


def brute_repeat(words):
    c = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    hit = set()
    for i in range(len(words) - 2):
        if c[tuple(words[i : i + 3])] > 1:
            hit |= {i, i + 1, i + 2}
    return len(hit)


def test_quality_counts():
    rnd = random.Random(4)
    for _ in range(300):
        t = "".join(rnd.choice(["a ", "b ", "c\n", "\n", " \n", "#", "$x ", "\t"]) for _ in range(rnd.randrange(40)))
        words = re.findall(r"[^\x20\x09-\x0D]+", t)
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        want = (len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), sum(x in lines[:i] for i, x in enumerate(lines)), brute_repeat(words))
        assert quality.base_counts(t) == want
    assert quality.base_counts(None) == (0, 0, 0, 0, 0)
    assert quality.verdict(100, 1.0, 0, 0) == "incompressible" and quality.verdict(5000, 50.0, 0, 0) == "repetitive" and quality.verdict(9000, 2.0, 2, 2) == "chunks" and quality.verdict(9000, 2.0, 1, 2) == "ok"


def test_compression_bands_reject_planted_junk():
    import zstandard

    compress = zstandard.ZstdCompressor(level=3, write_content_size=False, write_checksum=False).compress
    rnd = random.Random(8)
    syllables = [a + b for a in "bcdfglmnprst" for b in ("a", "e", "i", "o", "an", "er")]
    known = ["".join(rnd.choice(syllables) for _ in range(rnd.randrange(1, 4))) for _ in range(700)]
    prose = lambda n: " ".join(known[min(int(rnd.expovariate(1 / 120)), 699)] for _ in range(n))[:n]
    noise = lambda n: " ".join("".join(rnd.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rnd.randrange(3, 10))) for _ in range(n))[:n]

    def coded(n):
        b = base64.b64encode(rnd.randbytes(n)).decode()
        return " ".join(b[i : i + 8] for i in range(0, len(b), 8))[:n]

    def band(t):
        raw = t.encode()
        return quality.verdict(len(raw), *quality.compression(raw, compress))

    for n in (400, 700, 1500, 3000, 6000, 12000, 60000):
        assert band(prose(n)) == "ok" and band(coded(n)) == "incompressible"
        assert band(prose(n // 2) + " " + "the same line again\n" * (n // 40)) != "ok"
        if n > 1024:
            assert band(noise(n)) == "incompressible"
    for junk in (coded, noise):  # a third of a long text, in the middle and at its end
        assert band(prose(20000) + junk(10000) + prose(3000)) != "ok" and band(prose(20000) + junk(10000)) != "ok"
    one = prose(4096)
    assert quality.compression((one + one + coded(3000)).encode(), compress)[1:] == (1, 3)


def test_jaccard_core():
    cut = jaccard.Shingler()
    assert len(cut("")) == len(cut(None)) == len(cut(" \n\t ")) == 0 and len(cut("a b")) == 1 and len(cut("a b c d e f")) == 2
    assert (cut("A B c d e") == cut("a b C d e")).all() and len(cut("É b c d e")) == 1 and (cut("É b c d e") != cut("é b c d e")).all()
    rnd = np.random.default_rng(0)
    order = jaccard.Order([np.ones(1 << jaccard.SKETCH_BITS, np.int64)] * 2)
    for _ in range(400):
        base = rnd.integers(0, 1 << 63, 40, dtype=np.uint64)
        x = np.unique(rnd.choice(base, rnd.integers(1, 40), replace=False))
        y = np.unique(np.r_[rnd.choice(x, max(1, int(len(x) * rnd.uniform(0.6, 1))), replace=False), rnd.choice(base, rnd.integers(0, 5))])
        both = len(np.intersect1d(x, y))
        holds = 100 * both >= 80 * (len(x) + len(y) - both)
        assert jaccard.linked(x, y, 80) == (both if holds else 0)
        if holds:
            shared = set(order.prefix(x, 80).tolist()) & set(order.prefix(y, 80).tolist())
            assert len(shared) >= max(1, jaccard.shared_needed(len(x), len(y), 80))


def test_viterbi_against_all_paths():
    from itertools import product

    model = langid.LanguageModel.fit([("x", "abc", 5), ("y", "bcd", 5), ("z", "cde", 3)], [("x", "Latin", 9), ("y", "Latin", 9), ("z", "Latin", 9)])
    own = langid.Labeller(model, 2.0)
    rnd = np.random.default_rng(1)
    for _ in range(80):
        s = -rnd.exponential(2, (6, 3))
        value = lambda p: sum(s[i, k] for i, k in enumerate(p)) - 2.0 * sum(a != b for a, b in zip(p, p[1:]))
        best = max(product(range(3), repeat=6), key=value)
        assert abs(value(own.path(s)) - value(best)) < 1e-9
    assert own.label(None) == (langid.UNKNOWN, 0.0, []) and own.label("12 ..")[0] == langid.UNKNOWN
    assert langid.Labeller(langid.LanguageModel()).label("abc")[0] == langid.UNKNOWN


def test_path_without_the_best_single_language():
    from itertools import product

    model = langid.LanguageModel.fit([("x", "abc", 5), ("y", "bcd", 5), ("z", "cde", 3)], [("x", "Latin", 9), ("y", "Latin", 9), ("z", "Latin", 9)])
    own = langid.Labeller(model, 8.0)
    s = np.array([[0, -3.5, -14]] * 2 + [[-14, -3.5, 0]] * 2)
    assert own.path(s).tolist() == [0, 0, 2, 2]
    rnd = np.random.default_rng(2)
    for _ in range(150):
        s = -rnd.exponential(5, (5, 3)) * rnd.integers(0, 2, (5, 3))
        s[:, 1] = -rnd.uniform(1, 4)
        value = lambda p: sum(s[i, k] for i, k in enumerate(p)) - 8.0 * sum(a != b for a, b in zip(p, p[1:]))
        assert abs(value(own.path(s)) - max(map(value, product(range(3), repeat=5)))) < 1e-9


def test_kneser_ney_probabilities_sum_to_one():
    counts: dict = {}
    for word, n in (("abca", (3, 1)), ("abd", (1, 4)), ("ca", (0, 2))):
        for g in toxicity.grams(word, 3):
            a, b = counts.get(g, (0, 0))
            counts[g] = (a + n[0], b + n[1])
    shared = toxicity._shared_backoff(counts, 0.75)
    alphabet = {g[-1] for g in counts}
    for h in ("", "a", "b", "zz"):
        assert abs(sum(shared(h + c) for c in alphabet) - 1) < 1e-9
    model = toxicity.KneserNeyRatio.fit(counts, 3)
    assert model.word("abd") > model.word("abca")
    assert toxicity.Scorer(toxicity.KneserNeyRatio()).score("x") == 0.0


def test_adaptive_scan_keeps_the_nearest():
    rnd = np.random.default_rng(3)
    x = rnd.standard_normal((1500, 64))
    turned = x @ ann.rotation(64)
    missed = 0
    for i in range(40):
        d = ((x - x[i]) ** 2).sum(1)
        found = ann.scan(turned[i], np.ascontiguousarray(turned.T), 11, 2.1)
        assert len(found) < len(x)
        missed += len(set(np.argsort(d)[:11]) - set(found.tolist()))
    assert missed <= 4


def test_ranks_file_round_trip(tmp_path):
    p = tmp_path / "r"
    p.write_bytes(b"\n".join(base64.b64encode(bytes([b])) + b" " + str(b).encode() for b in range(256)))
    own = bpe.ByteBPE(bpe.load_ranks(str(p)))
    assert own.encode_piece(b"abc") == [97, 98, 99]
    with pytest.raises(ValueError):
        bpe.ByteBPE({b"a": 0}).encode_piece(b"b")
