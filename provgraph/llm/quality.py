"""Quality rules with compression bands.

A text is compressed whole and in fixed chunks with zstandard.  The ratio raw / compressed of
repetitive text is high, that of random strings is near one; each length class has its own limits,
since short texts compress less.  Base rules on words come first.

Defined results: null text counts as no text (no words, base_failed, not kept); an empty table
gives an empty result; ties and repeated rows give one result a row.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import ship
from .units import WHITE

SYMBOLS = "#*$%&|<>"
#: Limits (bytes up to, least ratio, most ratio) of whole texts; the last holds for all longer ones.
#: They lie between the ratios of texts that pass the base rules (on sf0.1, by length: from 1.35, 1.44, 1.69, 1.92, 2.09, 2.21, 2.33
#: up to 1.85, 2.16, 2.41, 2.61, 2.65, 2.76, 2.90) and those of base64 in words (at most 1.21 to 1.36), of random
#: letters (at most 1.67 to 1.72 above 1,024 bytes; below, they compress like prose and pass) and of repetitive texts (3.26 at least).
BANDS = ((512, 1.3, 2.3), (1024, 1.4, 2.6), (2048, 1.68, 2.9), (4096, 1.8, 3.2), (8192, 1.95, 3.5), (16384, 2.0, 3.5), (1 << 62, 2.1, 4.0))
CHUNK = 4096
#: The same for one chunk (clean ones on sf0.1: 2.07 to 2.63): a text fails when over a fifth of its chunks lie outside, or both of two.
CHUNK_BAND = (1.9, 3.5)
SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, ratio double, bad_chunks long, n_chunks long, band string, kept boolean"


def repeat_words(words: list, window: int = 3) -> int:
    """Words that stand in a window found at least twice."""
    n = len(words)
    if n <= window:
        return 0
    h = np.fromiter(map(hash, words), np.int64, n).view(np.uint64)
    with np.errstate(over="ignore"):
        g = np.zeros(n - window + 1, np.uint64)
        for k in range(window):
            g = (g ^ (g >> np.uint64(29))) * np.uint64(0x9E3779B97F4A7C15) + h[k : n - window + 1 + k]
    order = np.argsort(g, kind="stable")
    same = g[order][1:] == g[order][:-1]
    twice = np.zeros(len(g), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(n, bool)
    for k in range(window):
        covered[k : len(g) + k] |= twice
    return int(covered.sum())


def base_counts(text: str | None) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    if not text:
        return 0, 0, 0, 0, 0
    words = text.encode().split()
    lines = [x for x in text.split("\n") if x.strip(WHITE)]
    return len(words), len(text) - sum(map(text.count, WHITE)), sum(map(text.count, SYMBOLS)), len(lines) - len(set(lines)), repeat_words(words)


def compression(raw: bytes, compress) -> tuple[float, int, int]:
    """Ratio of the whole text, chunks outside their band, number of chunks; the last one ends with the text and may overlap the one before."""
    whole = len(raw) / len(compress(raw)) if raw else 1.0
    chunks = [raw[min(i, len(raw) - CHUNK) :][:CHUNK] for i in range(0, len(raw), CHUNK)] if len(raw) > CHUNK else []
    low, high = CHUNK_BAND
    return whole, sum(not low <= len(c) / len(compress(c)) <= high for c in chunks), len(chunks)


def verdict(size: int, ratio: float, bad: int, chunks: int, bands=BANDS) -> str:
    low, high = next((low, high) for most, low, high in bands if size <= most)
    if ratio < low:
        return "incompressible"
    if ratio > high:
        return "repetitive"
    return "chunks" if bad > (1 if chunks == 2 else chunks // 5) else "ok"


def judged(text: str | None, compress, bands=BANDS) -> tuple:
    """Base counts, base_failed, ratio, chunks outside their band, chunks, band and kept of a text."""
    counts = base_counts(text)
    raw = (text or "").encode()
    failed = counts[0] < 50 or 100 * counts[4] > 50 * counts[0]
    ratio, bad, chunks = compression(raw, compress)
    band = verdict(len(raw), ratio, bad, chunks, bands)
    return (*counts, failed, ratio, bad, chunks, band, not failed and band == "ok")


def _compressor(level: int):
    import zstandard

    return zstandard.ZstdCompressor(level=level, write_content_size=False, write_checksum=False).compress


def keep(docs: DataFrame, text_col: str = "text", level: int = 3, bands=BANDS) -> DataFrame:
    """The rows that the rules keep, with all their columns, whatever their ids; no row is joined or moved."""
    ship(docs.sparkSession)

    def run(batches):
        compress = _compressor(level)
        for batch in batches:
            at = batch.schema.get_field_index(text_col)
            yield batch.filter(pa.array([judged(t.as_py(), compress, bands)[-1] for t in batch.column(at)], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def quality(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", level: int = 3, bands=BANDS) -> DataFrame:
    """Base counts, compression ratios, the band's verdict and `kept` for every document."""
    ship(docs.sparkSession)

    def run(batches):
        compress = _compressor(level)
        for batch in batches:
            rows = [(i, *judged(text.as_py(), compress, bands)) for i, text in zip(batch.column(0).to_pylist(), batch.column(1))]
            names = [f.split()[0] for f in SCHEMA.split(", ")]
            kinds = {"long": pa.int64(), "double": pa.float64(), "boolean": pa.bool_(), "string": pa.string()}
            columns = list(zip(*rows)) or [()] * len(names)
            yield pa.RecordBatch.from_arrays([pa.array(c, kinds[f.split()[1]]) for c, f in zip(columns, SCHEMA.split(", "))], names=names)

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, SCHEMA)
