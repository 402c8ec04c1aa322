"""Exact n-gram Jaccard join by vertical partitioning, with components of linked documents.

A document is its set of distinct word 5-grams (64-bit hashes, which also give the global order).  The order is cut into fragments, so many
that two sets which link agree wholly on one at least:

* Linked sets of n and m n-grams differ in at most (n + m)(100 - t) / (100 + t) of them, each of which spoils one fragment.  Sets are banded by size
  (each band 100 / t times the one before), a pair lies in one band or two neighbours, and a band's number of fragments exceeds that bound by a quarter.
* A set's fragments are its elements.  Taken from the rarest on (a fragment that a single set has is rarest), as many as the set may have spoilt
  and one more are enough to meet each partner.  Sets that share a common passage only need no fragment of it and so never meet.
* Buckets (sets with one needed fragment) of the same members are one.  For each fragment a set has a byte: how many n-grams it holds
  there and a checksum.  Partial differences of a pair, summed over the fragments, bound its overlap; what the bound leaves is
  counted on whole sets, fragment by fragment, until the rest can't reach the threshold.
* Links of a few partners for each set merge components first; then every pair of a bucket that is still in two components is compared.

links() compares all pairs of a bucket, also those within a component, so every link between different sets comes out with its overlap.

A fragment that many sets of one part of a task have is dealt out by the set as well, and a large bucket is compared in
blocks, so neither lands in one task.  Sets with fewer fragments than they may have spoilt (very few, short ones)
meet in addition by the n-grams of a prefix.

Defined results: texts without words, empty or null have an empty set, n_shingles 0 and their own id as component; fewer
words than n give one n-gram of the whole sequence; repeated rows are one class; rows with a null id get n_shingles and
a null component and link nothing; an empty table gives an empty result.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .graph import components
from .runtime import Stage, ship, shuffle_partitions
from .units import Memo

N = 5
PERCENT = 80
#: Fragments above those that linked sets may have spoilt, as a share of them.
SLACK = 0.25
#: Parts of an n-gram set that a comparison counts one after the other.
FRAGMENT_BITS = 3
#: Members of one set that one task compares.
MEMBERS = 512
#: Sets of a bucket that are compared in one go.
BLOCK = 1024
#: Documents whose fragments are looked over for frequent ones together, and how often a fragment has to occur there.
LOT, OFTEN, SALTS = 1024, 64, 1024
#: Rows of one fragment that are held to be counted; with more it counts as larger than any.
HELD, LARGE = 100_000, 1 << 40
#: Rounds in which each set is compared with one partner, and partners looked at for it in a bucket.
ROUNDS, LOOKS = 3, 8
#: Words whose hashes a worker remembers in each of two generations, some 40 MB in all.
REMEMBERED = 100_000
_K = np.uint64(0x9E3779B97F4A7C15)
_K2 = np.uint64(0xBF58476D1CE4E5B9)


class Shingler:
    def __init__(self, n: int = N):
        self.n = n
        self.get = Memo(xxhash.xxh64_intdigest, REMEMBERED).__getitem__

    def __call__(self, text: str | None) -> np.ndarray:
        """Sorted distinct n-gram hashes; bytes.lower and bytes.split know ASCII only, as the contract has it."""
        words = (text or "").encode().lower().split()
        if not words:
            return np.zeros(0, np.uint64)
        h = np.fromiter(map(self.get, words), np.uint64, len(words))
        n = min(self.n, len(words))
        with np.errstate(over="ignore"):
            g = np.full(len(words) - n + 1, n, np.uint64)
            for k in range(n):
                g = (g ^ (g >> np.uint64(29))) * _K + h[k : len(words) - n + 1 + k]
            g = (g ^ (g >> np.uint64(32))) * _K2
            g ^= g >> np.uint64(31)
        return np.unique(g)


def set_key(g: np.ndarray) -> int:
    return xxhash.xxh3_64_intdigest(g.tobytes()) - (1 << 63)


def needed(n: int, percent: int) -> int:
    return -(-percent * n // 100)


def spoilt(total: int, percent: int) -> int:
    """Most n-grams in which two linking sets of `total` n-grams together can differ."""
    return total * (100 - percent) // (100 + percent)


@lru_cache(maxsize=8)
def bands(percent: int) -> tuple[list[int], list[int]]:
    """Largest size of each band, and the fragments of the pairs within it or between it and the next."""
    top, fragments, size = [], [], 1.0
    while size < 1 << 40:
        r = int(size + 1e-9)
        top.append(r)
        most = spoilt(r + 100 * r // percent, percent)
        fragments.append(int(np.ceil((1 + SLACK) * (most + 1))) + 2)
        size *= 100 / percent
    return top, fragments


def places(g: np.ndarray, many: int) -> np.ndarray:
    """Fragment of each n-gram: the order is cut at equal distances."""
    return ((g >> np.uint64(32)) * np.uint64(many) >> np.uint64(32)).astype(np.int64)


class Cutter:
    """Signatures of a set's fragments, in the pairs of bands that it takes part in."""

    def __init__(self, percent: int):
        self.percent = percent
        self.top, self.fragments = bands(percent)
        self.tops = np.array(self.top)

    def pairs_of_bands(self, n: int) -> list[tuple[int, int, int]]:
        """(side, band, n-grams that may be spoilt): as the larger of two bands (side 0) and as the smaller or only one (side 1)."""
        b = int(np.searchsorted(self.tops, n))
        out = [(1, b, spoilt(n + 100 * n // self.percent, self.percent))]
        return out if b == 0 else [(0, b - 1, spoilt(n + min(n, self.top[b - 1]), self.percent)), *out]

    def __call__(self, g: np.ndarray):
        """(side, signatures, how many more are needed than fragments that no other set has) of a set."""
        mixed = None
        for side, band, most in self.pairs_of_bands(len(g)):
            if not most:
                continue  # only equal sets link
            if mixed is None:
                with np.errstate(over="ignore"):
                    mixed = g * _K ^ (g >> np.uint64(31))
            at = places(g, self.fragments[band])
            cuts = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
            yield side, self.signed(np.add.reduceat(mixed, cuts), band), most + 1 - len(cuts)
            if len(cuts) <= most:
                yield side + 2, self.signed(mixed[: len(g) - needed(len(g), self.percent) + 1], band + 512), 1 << 26

    @staticmethod
    def signed(s: np.ndarray, band: int) -> np.ndarray:
        with np.errstate(over="ignore"):
            s = (s ^ (s >> np.uint64(29))) * _K2 + np.uint64(band)
        return s.view(np.int64)

    def digest(self, g: np.ndarray, band: int) -> bytes:
        """A byte for each fragment: n-grams there (15 at most) and four bits of their sum."""
        many = self.fragments[band]
        at = places(g, many)
        count = np.minimum(np.bincount(at, minlength=many), 15).astype(np.uint8)
        cuts = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
        check = np.zeros(many, np.uint8)
        with np.errstate(over="ignore"):
            check[at[cuts]] = (np.add.reduceat(g * _K, cuts) >> np.uint64(60)).astype(np.uint8)
        return (count << np.uint8(4) | check).tobytes()


def least_difference(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Lower bound of the n-grams in which pairs differ, from digests (pairs x fragments): partial differences, summed."""
    a, b = (x >> 4).astype(np.int8), (y >> 4).astype(np.int8)
    d = np.abs(a - b)
    # as many n-grams, but others: two at least
    d[(d == 0) & (x != y)] = 2
    return d.sum(1, dtype=np.int64)


def linked(x: np.ndarray, y: np.ndarray, percent: int) -> int:
    """Overlap if the sets link, else 0: partial overlaps of the fragments, summed."""
    want = -(-percent * (len(x) + len(y)) // (100 + percent))
    cuts = np.arange(1, 1 << FRAGMENT_BITS, dtype=np.uint64) << np.uint64(64 - FRAGMENT_BITS)
    a, b = np.r_[0, np.searchsorted(x, cuts), len(x)], np.r_[0, np.searchsorted(y, cuts), len(y)]
    most = np.minimum(np.diff(a), np.diff(b))
    left, overlap = int(most.sum()), 0
    for k in range(len(most)):
        if overlap + left < want:
            return 0
        u, v = x[a[k] : a[k + 1]], y[b[k] : b[k + 1]]
        if len(u) and len(v):
            at = np.searchsorted(u, v)
            at[at == len(u)] = 0
            overlap += int((u[at] == v).sum())
        left -= int(most[k])
    return overlap if 100 * overlap >= percent * (len(x) + len(y) - overlap) and overlap else 0


# A row of the first shuffle is (sig, salt, key, meta).  meta >= 0: a signature of the set `key`, with its size, side and need; -1: a mark that the
# signature is frequent; below: a document (sig holds its id), with its size, and whether it has an id and a set.
_SIDE, _NEED, _SIZE, _ZERO = 28, (1 << 28) - 1, 30, 1 << 27


def _fragments(docs: DataFrame, percent: int) -> DataFrame:
    names = ["sig", "salt", "key", "meta"]
    lot_rows, least = LOT, OFTEN

    def run(batches):
        cut, parts = Shingler(), Cutter(percent)
        seen = Memo(lambda key: True, 200_000)
        for batch in batches:
            for start in range(0, batch.num_rows, lot_rows):
                lot = batch.slice(start, lot_rows)
                sigs, keys, metas = [], [], []
                ids, own, told = np.zeros(lot.num_rows, np.int64), np.zeros(lot.num_rows, np.int64), np.zeros(lot.num_rows, np.int64)
                for i, (doc, text) in enumerate(zip(lot.column(0).to_pylist(), lot.column(1))):
                    g = cut(text.as_py())
                    n = len(g)
                    key = set_key(g) if n else 0
                    ids[i], own[i], told[i] = doc or 0, key, -2 - (n * 4 + (doc is not None) * 2 + (n > 0))
                    if doc is None or not n or key in seen or key in seen.old:
                        continue
                    seen[key]
                    for side, s, need in parts(g):
                        sigs.append(s)
                        keys.append((key, len(s)))
                        metas.append((n << _SIZE) + (side << _SIDE) + max(need + _ZERO, 0))
                none = np.zeros(0, np.int64)
                sig = np.concatenate(sigs) if sigs else none
                sizes = [m for _, m in keys]
                key, meta = np.repeat(np.array([k for k, _ in keys], np.int64), sizes), np.repeat(np.array(metas, np.int64), sizes)
                salt = np.zeros(len(sig), np.int64)
                order = np.sort(sig)
                often = np.unique(order[: 1 - least][order[least - 1 :] == order[: 1 - least]]) if len(sig) >= least else none
                if len(often):
                    hot = np.isin(sig, often)
                    salt[hot] = 1 + key[hot] % SALTS
                many = len(often)
                columns = [np.concatenate(x) for x in ((sig, often, ids), (salt, np.zeros(many + len(ids), np.int64)), (key, np.zeros(many, np.int64), own), (meta, np.full(many, -1), told))]
                whole = pa.RecordBatch.from_arrays([pa.array(x) for x in columns], names=names)
                for i in range(0, whole.num_rows, 50_000):
                    yield whole.slice(i, 50_000)

    return docs.mapInArrow(run, "sig long, salt long, key long, meta long")


def _met(rows: DataFrame) -> DataFrame:
    """Documents (doc, n, key; size null) and signatures that several sets have (sig, key, n, side, need, size), streamed over sorted rows."""
    names = ["doc", "sig", "key", "n", "side", "need", "size"]
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.int64()]
    most_held = HELD

    def shared(sig, key, meta, size):
        none = pa.nulls(len(sig), pa.int64())
        side, need, n = meta >> _SIDE & 3, (meta & _NEED) - _ZERO, meta >> _SIZE
        return pa.RecordBatch.from_arrays([none, *(pa.array(x, k, safe=False) for x, k in zip((sig, key, n, side, need, size), kinds[1:]))], names=names)

    def documents(sig, key, meta):
        told = -2 - meta
        none = pa.nulls(len(sig), pa.int32())
        return pa.RecordBatch.from_arrays([
            pa.array(sig, mask=(told & 2) == 0), pa.nulls(len(sig), pa.int64()), pa.array(key, mask=(told & 1) == 0), pa.array((told >> 2).astype(np.int32)), none, none, pa.nulls(len(sig), pa.int64()),
        ], names=names)

    def run(batches):
        held, large = None, None  # rows of the last signature so far; the signature that is already larger than HELD
        for batch in batches:
            sig, salt, key, meta = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
            doc = meta < -1
            if doc.any():
                yield documents(sig[doc], key[doc], meta[doc])
                sig, salt, key, meta = (x[~doc] for x in (sig, salt, key, meta))
            rows = np.stack([sig, salt, key, meta])
            if held is not None:
                rows = np.concatenate([held, rows], 1)
            if not rows.shape[1]:
                continue
            # a set comes from each task that has it
            again = np.r_[False, (rows[:, 1:] == rows[:, :-1]).all(0)]
            rows = rows[:, ~again]
            first = np.r_[True, (rows[:2, 1:] != rows[:2, :-1]).any(0)]
            at = np.flatnonzero(first)
            held, rows, first, at = rows[:, at[-1] :], rows[:, : at[-1]], first[: at[-1]], at[:-1]
            if len(at):
                yield from groups(rows, at, large)
                large = None
            if held.shape[1] > most_held:
                large = tuple(held[:2, 0].tolist())
                out = held[:, held[3] >= 0]
                yield from sliced(out[0, :-1], out[2, :-1], out[3, :-1], np.full(max(out.shape[1] - 1, 0), LARGE))
                held = held[:, -1:]
        if held is not None and held.shape[1]:
            yield from groups(held, np.zeros(1, np.int64), large)

    def groups(rows, at, large):
        sizes = np.diff(np.r_[at, rows.shape[1]])
        marked = np.bincount(np.repeat(np.arange(len(at)), sizes), rows[3] == -1) > 0
        most = np.where(marked | (rows[1, at] > 0), LARGE, sizes)
        if large is not None and tuple(rows[:2, 0].tolist()) == large:
            most[0] = LARGE
        size = np.repeat(most, sizes)
        keep = (size > 1) & (rows[3] >= 0)
        if keep.any():
            yield from sliced(rows[0, keep], rows[2, keep], rows[3, keep], size[keep])

    def sliced(sig, key, meta, size):
        for i in range(0, len(sig), 50_000):
            yield shared(*(x[i : i + 50_000] for x in (sig, key, meta, size)))

    n = shuffle_partitions(rows.sparkSession)
    return rows.repartition(n, "sig", "salt").sortWithinPartitions("sig", "salt", "key", "meta").mapInArrow(run, "doc long, sig long, key long, n int, side int, need int, size long")


def _buckets(met: DataFrame) -> DataFrame:
    """(sig, key, n, side, size): sets that meet in a fragment which they need, one bucket of those with the same members."""
    own = Window.partitionBy("key", "side")
    ranked = met.withColumn("_more", F.count("*").over(own)).withColumn("_rank", F.row_number().over(own.orderBy("size", "sig")))
    wanted = ranked.where(F.col("_rank") <= F.col("need") + F.col("_more")).select("sig", "key", "n", F.pmod("side", F.lit(2)).alias("side"))
    wanted = wanted.dropDuplicates(["sig", "key"])  # a set may come with and without a salt
    groups = wanted.groupBy("sig").agg(F.count("*").alias("size"), F.bit_xor(F.xxhash64("key")).alias("_x"), F.bit_xor(F.xxhash64("key", F.lit(1))).alias("_y")).where("size > 1")
    chosen = groups.groupBy("size", "_x", "_y").agg(F.min("sig").alias("_sig")).select("_sig", "size")
    return wanted.join(chosen, F.col("sig") == F.col("_sig")).select("sig", "key", "n", "side", "size")


def _sets(docs: DataFrame, alike: DataFrame, percent: int) -> DataFrame:
    """(key, grams, d0, d1): the n-grams and digests of sets that meet another; alike: (key, _id of a document)."""
    texts = docs.join(alike, F.col("doc_id") == F.col("_id")).select("key", "text")

    def run(batches):
        cut, parts = Shingler(), Cutter(percent)
        for batch in batches:
            out: tuple[list, ...] = ([], [], [], [])
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                g = cut(text.as_py())
                if len(g) and set_key(g) == key:  # rows that repeat an id may hold other texts
                    of = {side: parts.digest(g, band) for side, band, _ in parts.pairs_of_bands(len(g))}
                    for column, value in zip(out, (key, g.tobytes(), of.get(0), of.get(1))):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), *(pa.array(c, pa.binary()) for c in out[1:])], names=["key", "grams", "d0", "d1"])

    return texts.mapInArrow(run, "key long, grams binary, d0 binary, d1 binary").dropDuplicates(["key"])


def _in_blocks(members: DataFrame, all_pairs: bool) -> DataFrame:
    """Members with the block (of BLOCK sets, or two such for the pairs between them) in which they are compared."""
    many = F.ceil(F.col("size") / BLOCK).cast("int")
    blocks = members.withColumn("_many", many).withColumn("_own", F.pmod(F.xxhash64("key"), F.col("_many")).cast("int"))
    if not all_pairs:
        return blocks.withColumn("block", F.col("_own")).withColumn("half", F.lit(0))
    others = F.sequence(F.lit(0), F.col("_many") - 1)
    blocks = blocks.withColumn("_with", F.explode(others))
    return blocks.withColumn("block", F.least("_own", "_with") * F.col("_many") + F.greatest("_own", "_with")).withColumn("half", (F.col("_own") > F.col("_with")).cast("int") + F.lit(2) * (F.col("_own") == F.col("_with")).cast("int"))


def _candidates(members: DataFrame, percent: int, looks: int | None) -> DataFrame:
    """Pairs (a, b) of one bucket in different components whose digests allow a link; `looks` partners of each set, or all.

    members: (sig, key, n, digest, size, root), in blocks.  Where a block stands for two, pairs lie across its halves.
    """

    def pairs(key, n, root, half, digest):
        many = len(key)
        x = np.frombuffer(b"".join(digest), np.uint8).reshape(many, -1)
        order = np.argsort(n, kind="stable") if looks is None else np.random.default_rng(many).permutation(many)
        key, n, root, half, x = key[order], n[order], root[order], half[order], x[order]
        if looks is None:
            reach = np.searchsorted(n, 100 * n // percent, "right")
            for i in range(many):
                j = np.arange(i + 1, reach[i])
                j = j[(root[j] != root[i]) & ((half[j] == 2) | (half[j] != half[i]))]
                for k in range(0, len(j), 4096):
                    yield np.full(len(j[k : k + 4096]), i), j[k : k + 4096], x, key, n, root
        else:
            for step in range(1, min(looks, many - 1) + 1):
                i = np.arange(many)
                j = (i + step) % many
                ok = (root[i] != root[j]) & (100 * np.minimum(n[i], n[j]) >= percent * np.maximum(n[i], n[j]))
                yield i[ok], j[ok], x, key, n, root

    def found(rows):
        for i, j, x, key, n, _ in pairs(*rows):
            if len(i):
                ok = np.concatenate([least_difference(x[i[k : k + 512]], x[j[k : k + 512]]) for k in range(0, len(i), 512)]) <= spoilt(n[i] + n[j], percent)
                if ok.any():
                    yield np.minimum(key[i[ok]], key[j[ok]]), np.maximum(key[i[ok]], key[j[ok]])

    def run(batches):
        name, held = None, []
        for batch in batches:
            sig, block, key, n, root, half = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(6))
            digest = batch.column(6).to_pylist()
            cuts = np.flatnonzero(np.r_[True, (sig[1:] != sig[:-1]) | (block[1:] != block[:-1])]) if len(sig) else []
            out = []
            for a, b in zip(cuts, [*cuts[1:], len(sig)]):
                if (sig[a], block[a]) != name:
                    out += finish(held)
                    name, held = (sig[a], block[a]), []
                held.append((key[a:b], n[a:b].astype(np.int64), root[a:b], half[a:b], digest[a:b]))
            yield from told(out)
        yield from told(finish(held))

    def finish(held):
        if not held:
            return []
        rows = [np.concatenate([h[k] for h in held]) for k in range(4)]
        return list(found((*rows, [d for h in held for d in h[4]]))) if len(rows[0]) > 1 else []

    def told(out):
        if out:
            a, b = (np.concatenate([x[k] for x in out]) for k in (0, 1))
            for i in range(0, len(a), 50_000):
                yield pa.RecordBatch.from_arrays([pa.array(a[i : i + 50_000]), pa.array(b[i : i + 50_000])], names=["a", "b"])

    rows = _in_blocks(members, looks is None).select("sig", "block", "key", "n", "root", "half", "digest")
    count = shuffle_partitions(members.sparkSession)
    return rows.repartition(count, "sig", "block").sortWithinPartitions("sig", "block", "key").mapInArrow(run, "a long, b long").distinct()


def _verify(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) that link, with their overlap; members of a set are dealt in lots of MEMBERS."""
    lots = pairs.groupBy("a").agg(F.ceil(F.count("*") / MEMBERS).cast("int").alias("lots"))
    members = pairs.join(lots, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.col("lots")).cast("int").alias("lot"))
    members = members.join(sets.select(F.col("key").alias("b"), "grams"), "b").select(F.col("a").alias("of"), F.col("lot").alias("part"), "b", F.col("grams").alias("other"))
    leaders = lots.select(F.col("a").alias("la"), "lots").join(sets.select(F.col("key").alias("la"), "grams"), "la").select("la", "grams", F.explode(F.sequence(F.lit(0), F.col("lots") - 1)).alias("lot"))

    def run(key, left, right):
        a, b, overlap = [], [], []
        if left.num_rows and right.num_rows:
            x = np.frombuffer(left.column("grams")[0].as_py(), np.uint64)
            for i, name in enumerate(right.column("b").to_pylist()):
                if n := linked(x, np.frombuffer(right.column("other")[i].as_py(), np.uint64), percent):
                    a.append(key[0].as_py())
                    b.append(name)
                    overlap.append(n)
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64()), "overlap": pa.array(overlap, pa.int64())})

    return leaders.groupBy("la", "lot").cogroup(members.groupBy("of", "part")).applyInArrow(run, "a long, b long, overlap long")


def _distinct(docs: DataFrame, percent: int, stage: Stage) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """(rows, classes, members, sets): each document's set, the distinct sets, the buckets in which they meet, and the sets that meet another."""
    met = stage.table(_met(_fragments(docs, percent)), "met")
    rows = met.where("sig is null").select(F.col("doc").alias("doc_id"), "n", "key")
    classes = stage.table(rows.where("key is not null and doc_id is not null").groupBy("key").agg(F.min("doc_id").alias("least")), "classes")
    buckets = stage.table(_buckets(met.where("sig is not null")), "buckets")
    alike = buckets.select("key").distinct().join(classes, "key").select("key", F.col("least").alias("_id"))
    sets = stage.table(_sets(docs, alike, percent), "sets")
    members = buckets.join(sets.select(F.col("key").alias("_key"), "d0", "d1"), F.col("key") == F.col("_key"))
    members = stage.table(members.select("sig", "key", "n", "size", F.when(F.col("side") == 0, F.col("d0")).otherwise(F.col("d1")).alias("digest")), "members")
    return rows, classes, members, sets


def _named(members: DataFrame, roots: DataFrame | None) -> DataFrame:
    """Members of buckets that hold several components, with their component."""
    if roots is None:
        return members.withColumn("root", F.col("key"))
    named = members.join(roots, F.col("key") == F.col("node"), "left").withColumn("root", F.coalesce("root", "key")).drop("node")
    mixed = named.groupBy("sig").agg(F.min("root").alias("_lo"), F.max("root").alias("_hi")).where("_lo <> _hi").select(F.col("sig").alias("_sig"))
    return named.join(mixed, F.col("sig") == F.col("_sig"), "left_semi")



def links(docs: DataFrame, percent: int = PERCENT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_a, doc_b, overlap of every two distinct sets that link, each named by the least id of its class, doc_a < doc_b.

    The result itself grows with the square of a group of near copies.
    """
    spark = docs.sparkSession
    ship(spark)
    stage = Stage(spark)
    _, classes, members, sets = _distinct(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")), percent, stage)
    pairs = stage.table(_candidates(_named(members, None), percent, None), "pairs")
    found = _verify(pairs, sets, percent)
    for side in ("a", "b"):
        found = found.join(classes.select(F.col("key").alias(side), F.col("least").alias(f"_{side}")), side)
    return found.select(F.least("_a", "_b").alias("doc_a"), F.greatest("_a", "_b").alias("doc_b"), "overlap")


def join(docs: DataFrame, percent: int = PERCENT, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id of every document."""
    spark = docs.sparkSession
    ship(spark)
    stage = Stage(spark)
    docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    rows, classes, members, sets = _distinct(docs, percent, stage)
    edges, tested, roots = None, None, None
    for k in range(ROUNDS + 1):
        open_ = _candidates(_named(members, roots), percent, LOOKS if k < ROUNDS else None)
        if k < ROUNDS:  # one partner each
            both = open_.select("a", "b").unionByName(open_.select(F.col("b").alias("a"), F.col("a").alias("b")))
            one = both.groupBy("a").agg(F.min_by("b", F.xxhash64("b", F.lit(k))).alias("b"))
            open_ = one.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        if tested is not None:
            open_ = open_.join(tested, ["a", "b"], "left_anti")
        open_ = stage.table(open_, "open")
        found = stage.table(_verify(open_, sets, percent).select("a", "b"), "links")
        tested = open_ if tested is None else tested.unionByName(open_)
        edges = found if edges is None else edges.unionByName(found)
        roots = components(edges, stage)
    owned = classes.join(roots, F.col("key") == F.col("node"), "left").select("key", "least", F.coalesce("root", "key").alias("root"))
    least = owned.groupBy("root").agg(F.min("least").alias("component_id"))
    names = owned.join(least, "root").select(F.col("key").alias("_key"), "component_id")
    out = rows.join(names, F.col("key") == F.col("_key"), "left")
    return out.select("doc_id", F.col("n").cast("long").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("component_id", "doc_id")).alias("component_id"))
