"""Cross-entropy difference of documents under two matched n-gram models.

The target model counts the documents chosen as target, the background model the whole corpus.  Both share the words of the whole corpus as
vocabulary, the order and the smoothing: p(w | v) = (c(v, w) + MASS p(w)) / (c(v) + MASS) with p(w) = (c(w) + 1) / (N + V), a
distribution over the vocabulary and the end of a text.  Background counts are scaled to the target's number of words, so that
both back off alike at like evidence.  A document's own words are left out of every count that it is scored with.  Its score
is the mean over its words (and its end) of the target loss minus the background loss: the lower, the closer it is to the target.

Every word and every bigram of the corpus is counted by its 56-bit key; nothing is capped or thinned.  Documents are taken in chunks.  A
chunk asks for the counts of its distinct keys, sorted and cut into ranges of keys (packed, some 5 bytes a key); each range is summed
over all chunks in one task, and each chunk gets its counts back in the order of its request.  So a key costs each chunk one entry,
however often it occurs, and no task holds more than a range of keys or a chunk.  Chunks keep their texts as word numbers, so texts
are read once.  All that is gathered grows with the corpus.

Defined results: null and empty texts have no words, losses and score 0; if no document is target, its model is uniform; a null
id is never target; repeated rows count as often as they occur (a copy's counts remain when a row's own are left out); labels
repeated for a document count once.
"""

from __future__ import annotations

from array import array

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import Stage, ship, shuffle_partitions

#: Words that the unigram distribution is worth in each context.
MASS = 4.0
#: Words of a chunk (a longer text is a chunk by itself).
CHUNK_WORDS = 1_000_000
#: Rows of a chunk, however short.
CHUNK_ROWS = 100_000
#: Keys keep their upper 56 bits, which travel; of 10^13 different bigrams one in 10,000 then shares its key with another.
KEPT = np.uint64(0xFFFFFFFFFFFFFF00)
#: Keys of the start and the end of a text.
START, END = np.uint64(1 << 8), np.uint64(2 << 8)
_K = np.uint64(0x9E3779B97F4A7C15)
_K2 = np.uint64(0xBF58476D1CE4E5B9)

CHUNKS = "chunk long, range int, keys binary, n binary, target binary, ids array<long>, sizes array<int>, chosen array<boolean>, words binary, text binary"


def words_of(text: str | None) -> list[str]:
    return (text or "").lower().split()


def pair_keys(v: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Keys of bigrams from those of their words."""
    with np.errstate(over="ignore"):
        k = (v ^ (v >> np.uint64(29))) * _K + w
        k = (k ^ (k >> np.uint64(32))) * _K2
        return (k ^ (k >> np.uint64(31))) & KEPT


def _squeezed(raw: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=1).compress(raw)


def _whole(raw: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdDecompressor().decompress(raw)


def planes(x: np.ndarray) -> bytes:
    """Numbers byte by byte of their width, so that the empty bytes of all stand together, compressed."""
    width = x.dtype.itemsize
    return _squeezed(np.ascontiguousarray(np.ascontiguousarray(x).view(np.uint8).reshape(-1, width).T).tobytes())


def numbers(raw: bytes, kind: str) -> np.ndarray:
    width = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(_whole(raw), np.uint8).reshape(width, -1).T).view(kind).ravel()


def pack(keys: np.ndarray) -> bytes:
    """Sorted keys as differences."""
    return planes(np.diff(keys, prepend=np.uint64(0)).astype("<u8"))


def unpack(raw: bytes) -> np.ndarray:
    with np.errstate(over="ignore"):
        return np.cumsum(numbers(raw, "<u8"), dtype=np.uint64)


def pack_counts(n: np.ndarray) -> bytes:
    most = int(n.max()) if len(n) else 0
    width = next(w for w in (1, 2, 4, 8) if most < 1 << (8 * w))
    return bytes([width]) + planes(n.astype(f"<u{width}"))


def unpack_counts(raw: bytes) -> np.ndarray:
    return numbers(raw[1:], f"<u{raw[0]}").astype(np.int64)


class Chunk:
    """Texts as numbers of words; number 0 is the start and 1 the end of a text, the others follow the order of the words' keys."""

    def __init__(self, texts: list[list[str]]):
        number: dict[str, int] = {}
        flat = array("I", (number.setdefault(w, len(number)) for t in texts for w in t))
        self._set(number, flat, [len(t) for t in texts])

    def _set(self, number: dict[str, int], flat: array, sizes: list[int]) -> None:
        self.sizes = np.array(sizes, np.int64)
        keys = np.fromiter(map(xxhash.xxh64_intdigest, number), np.uint64, len(number))
        self.words, at = np.unique(keys & KEPT, return_inverse=True)
        self.text = (at[np.frombuffer(flat, np.uint32)] + 2).astype("<u4") if len(flat) else np.zeros(0, "<u4")

    @classmethod
    def numbered(cls, number: dict[str, int], flat: array, sizes: list[int]) -> Chunk:
        """From words numbered as they came, so that no list of all words is held."""
        out = cls.__new__(cls)
        out._set(number, flat, sizes)
        return out

    @classmethod
    def stored(cls, sizes: np.ndarray, words: bytes, text: bytes) -> Chunk:
        out = cls.__new__(cls)
        out.sizes, out.words, out.text = sizes, unpack(words), numbers(text, "<u4")
        return out

    def store(self) -> tuple[bytes, bytes]:
        return pack(self.words), planes(self.text)

    def steps(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(document, word before, word) of each word and each end of the texts that hold a word."""
        has = np.flatnonzero(self.sizes)
        sizes = self.sizes[has] + 1
        doc, ends = np.repeat(has, sizes), np.cumsum(sizes) - 1
        w = np.ones(len(doc), np.int64)
        inner = np.ones(len(doc), bool)
        inner[ends] = False
        w[inner] = self.text
        v = np.empty_like(w)
        v[:1], v[1:] = 0, w[:-1]
        v[ends - sizes + 1] = 0
        return doc, v, w

    @property
    def keys(self) -> np.ndarray:
        return np.concatenate([[START, END], self.words])


def _ranges(keys: np.ndarray, many: int) -> np.ndarray:
    return ((keys >> np.uint64(32)) * np.uint64(many) >> np.uint64(32)).astype(np.int64)


def _chunks(texts: DataFrame, many: int) -> DataFrame:
    """A row of each chunk with its texts, and its requests: distinct keys of a range with their counts in all and in target documents.

    texts: (id, text, target).  Ranges from 0 on hold words, those from `many` on bigrams.
    """
    names = [f.split()[0] for f in CHUNKS.split(", ")]
    kinds = [pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.list_(pa.int64()), pa.list_(pa.int32()), pa.list_(pa.bool_()), pa.binary(), pa.binary()]

    def rows(name, ids, chosen, number, flat, sizes):
        chunk = Chunk.numbered(number, flat, sizes)
        mark = np.array(chosen, bool)
        doc, v, w = chunk.steps()
        keys, yes = chunk.keys, mark[doc]
        starts = w == 1
        # the start counts as a word that stands before, the end as one that follows
        single = np.concatenate([w, np.zeros(int(starts.sum()), np.int64)])
        of = np.concatenate([yes, yes[starts]])
        n = np.bincount(single, minlength=len(keys))
        t = np.bincount(single[of], minlength=len(keys))
        pairs, at = np.unique(pair_keys(keys[v], keys[w]), return_inverse=True)
        out = []
        order = np.argsort(keys, kind="stable")
        for first, k, a, b in ((0, keys[order], n[order], t[order]), (many, pairs, np.bincount(at, minlength=len(pairs)), np.bincount(at[yes], minlength=len(pairs)))):
            cuts = np.searchsorted(_ranges(k, many), np.arange(many + 1))
            for r in np.flatnonzero(np.diff(cuts)).tolist():
                i, j = cuts[r], cuts[r + 1]
                out.append((name, first + r, pack(k[i:j]), pack_counts(a[i:j]), pack_counts(b[i:j]), None, None, None, None, None))
        out.append((name, None, None, None, None, ids, chunk.sizes.tolist(), mark.tolist(), *chunk.store()))
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out), kinds)], names=names)

    def run(batches):
        from pyspark import TaskContext

        name = TaskContext.get().partitionId() << 32
        ids, chosen, number, flat, sizes = [], [], {}, array("I"), []
        for batch in batches:
            for i, text, y in zip(batch.column(0).to_pylist(), batch.column(1), batch.column(2).to_pylist()):
                words = words_of(text.as_py())
                if ids and (len(flat) + len(words) > CHUNK_WORDS or len(ids) >= CHUNK_ROWS):
                    yield rows(name, ids, chosen, number, flat, sizes)
                    name, ids, chosen, number, flat, sizes = name + 1, [], [], {}, array("I"), []
                ids.append(i)
                chosen.append(y)
                sizes.append(len(words))
                flat.extend([number.setdefault(w, len(number)) for w in words])
        if ids:
            yield rows(name, ids, chosen, number, flat, sizes)

    return texts.mapInArrow(run, CHUNKS)


def _answers(requests: DataFrame) -> DataFrame:
    """(chunk, range, n, target): the corpus's counts of each request's keys; a row without chunk holds a range's keys and their sums."""
    names = ["chunk", "range", "n", "target", "size", "sum_n", "sum_target"]

    def run(key, table):
        chunks, raw = table.column("chunk").to_pylist(), [unpack(x.as_py()) for x in table.column("keys")]
        sizes = [len(x) for x in raw]
        keys, at = np.unique(np.concatenate(raw), return_inverse=True)
        sums = []
        for c in ("n", "target"):
            # whole numbers, exact far beyond any count
            total = np.bincount(at, np.concatenate([unpack_counts(x.as_py()) for x in table.column(c)]), len(keys)).astype(np.int64)
            sums.append(total)
        cuts = np.cumsum(sizes)[:-1]
        per = [[pack_counts(x) for x in np.split(s[at], cuts)] for s in sums]
        r, m = key[0].as_py(), len(chunks)
        # the start is no word that could follow
        real = keys != START
        stats = [[None] * m + [x] for x in (int(real.sum()), int(sums[0][real].sum()), int(sums[1][real].sum()))]
        return pa.table([pa.array([*chunks, None], pa.int64()), pa.array([r] * (m + 1), pa.int32()), *(pa.array([*x, None], pa.binary()) for x in per), *(pa.array(x, pa.int64()) for x in stats)], names=names)

    return requests.groupBy("range").applyInArrow(run, "chunk long, range int, n binary, target binary, size long, sum_n long, sum_target long")


def losses(chunk: Chunk, chosen: np.ndarray, single: tuple, pairs: tuple, at: np.ndarray, size: int, sums: tuple) -> tuple[np.ndarray, np.ndarray]:
    """Mean losses of the chunk's documents under the target's and the background's model, without their own counts.

    single, pairs: (target, background) counts by word number and by bigram; at: the bigram of each step; sums: words of either side.
    """
    docs, (doc, v, w) = len(chunk.sizes), chunk.steps()
    many = np.maximum(chunk.sizes + 1, 1)
    n_words, n_pairs = len(single[0]), len(pairs[0])

    def own(item: np.ndarray, width: int) -> np.ndarray:
        """How often a step's item occurs in its own document."""
        _, inverse, count = np.unique(doc * width + item, return_inverse=True, return_counts=True)
        return count[inverse]

    own_w, own_pair = own(w, n_words), own(at, n_pairs)
    own_v = np.ones(len(v), np.int64)
    inner = v != 0
    if inner.any():
        _, inverse, count = np.unique(doc[inner] * n_words + v[inner], return_inverse=True, return_counts=True)
        own_v[inner] = count[inverse]
    out = []
    scales = (1.0, min(1.0, max(sums[0], 1) / max(sums[1], 1)))
    for k, scale in enumerate(scales):
        mine = chosen[doc].astype(np.int64) if k == 0 else np.ones(len(doc), np.int64)
        base = (single[k][w] - mine * own_w + 1.0) / (sums[k] - mine * many[doc] + size)
        p = (scale * (pairs[k][at] - mine * own_pair) + MASS * base) / (scale * (single[k][v] - mine * own_v) + MASS)
        out.append(np.bincount(doc, -np.log(p), docs) / many)
    return out[0], out[1]


def difference(docs: DataFrame, target: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_words, loss_target, loss_background, score of every document; target: ids of the target documents."""
    spark = docs.sparkSession
    ship(spark)
    stage = Stage(spark)
    chosen = target.select(F.col(id_col).alias("_t")).where(F.col("_t").isNotNull()).distinct()
    # sorted and merged at every size: labels grow with the documents, so they are never broadcast
    marked = docs.select(F.col(id_col).cast("long").alias("_d"), F.col(text_col).alias("_text")).join(chosen.hint("merge"), F.col("_d") == F.col("_t"), "left")
    many = shuffle_partitions(spark)
    chunks = stage.table(_chunks(marked.select("_d", "_text", F.col("_t").isNotNull().alias("_y")), many), "chunks")
    counts = stage.table(_answers(chunks.where("range is not null").select("chunk", "range", "keys", "n", "target")), "counts")
    total = counts.where("chunk is null").agg(*(F.coalesce(F.sum(F.when(F.col("range") < many, F.col(c))), F.lit(0)).alias(c) for c in ("size", "sum_n", "sum_target"))).first()
    size, sums = total["size"], (total["sum_target"], total["sum_n"])

    def run(key, left, right):
        if not left.num_rows:
            return pa.table({"doc_id": pa.array([], pa.int64()), "n_words": pa.array([], pa.int64()), **{c: pa.array([], pa.float64()) for c in ("loss_target", "loss_background", "score")}})
        row = {c: left.column(c)[0].as_py() for c in ("ids", "sizes", "chosen", "words", "text")}
        chunk = Chunk.stored(np.array(row["sizes"], np.int64), row["words"], row["text"])
        got = sorted(zip(right.column("range").to_pylist(), right.column("n").to_pylist(), right.column("target").to_pylist()))
        # requests were sorted by key, words first
        counted = [np.concatenate([np.zeros(0, np.int64), *(unpack_counts(x[k]) for x in got)]) for k in (2, 1)]
        keys = chunk.keys
        order, m = np.argsort(keys, kind="stable"), len(keys)
        single, pairs = [], []
        for c in counted:
            s = np.zeros(m, np.int64)
            if len(c):
                s[order] = c[:m]
            single.append(s)
            pairs.append(c[m:])
        _, v, w = chunk.steps()
        at = np.unique(pair_keys(keys[v], keys[w]), return_inverse=True)[1]
        lt, lb = losses(chunk, np.array(row["chosen"], bool), tuple(single), tuple(pairs), at, size, sums)
        return pa.table({"doc_id": pa.array(row["ids"], pa.int64()), "n_words": pa.array(chunk.sizes), "loss_target": pa.array(lt), "loss_background": pa.array(lb), "score": pa.array(lt - lb)})

    texts = chunks.where("range is null").select("chunk", "ids", "sizes", "chosen", "words", "text")
    asked = counts.where("chunk is not null").select("chunk", "range", "n", "target")
    return texts.groupBy("chunk").cogroup(asked.groupBy("chunk")).applyInArrow(run, "doc_id long, n_words long, loss_target double, loss_background double, score double")
