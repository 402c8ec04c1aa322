"""Best-fit packing of token pieces into sequences by large-item matching.

Lengths are whole numbers up to the capacity, so the plan is made on their histogram (one row for
each length) in the driver, whatever the number of documents.  Items above a third of the capacity
stand at most twice in a bin: they are matched greedily, the longest with the longest partner that
fits.  Shorter items then fill the tightest gap that takes them.  The plan maps runs of ranks
within a length to runs of sequences, and a join on length gives each piece its place.

Defined results: null or empty text is one piece holding the end id only; documents longer than
the capacity are cut from the back, so only the first piece is short; repeated rows are packed as often as
they occur; an empty table gives an empty result; a null id stays null.
"""

from __future__ import annotations

import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .runtime import Stage, ship, shuffle_partitions
from .subwords import END_ID, array_encoder, default_path

PIECE_SCHEMA = "doc_id long, piece int, start long, length int, ids_crc32 long"
PLAN_SCHEMA = "length int, rank_from long, rank_to long, seq_from long, at int"
#: A plan of up to this many runs is broadcast; a longer one is joined by shuffle.
BROADCAST_RUNS = 200_000


def cut_points(n: int, capacity: int) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n tokens."""
    first = n % capacity or capacity
    return [(0, min(first, n))] + [(s, capacity) for s in range(first, n, capacity)]


def pieces(docs: DataFrame, capacity: int = 2048, tokenizer: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Token pieces of each document (ids and end id), with the checksum of each piece's ids."""
    ship(docs.sparkSession)
    path = tokenizer or default_path()

    def run(batches):
        encode = array_encoder(path, added=True)
        for batch in (b.slice(i, 2048) for b in batches for i in range(0, b.num_rows, 2048)):
            out: tuple[list, ...] = ([], [], [], [], [])
            flat, sizes = encode(batch.column(1))
            ids, begin = np.insert(flat, np.cumsum(sizes), END_ID).astype("<u4", copy=False), 0
            for i, n in zip(batch.column(0).to_pylist(), (sizes + 1).tolist()):
                own, begin = ids[begin : begin + n], begin + n
                for k, (start, length) in enumerate(cut_points(n, capacity)):
                    for column, value in zip(out, (i, k, start, length, zlib.crc32(own[start : start + length]))):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.int64()))], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select(F.col(id_col).cast("long"), F.col(text_col)).mapInArrow(run, PIECE_SCHEMA)


class _Bins:
    """Runs of bins (first sequence id, how many) kept by their gap."""

    def __init__(self, capacity: int):
        self.capacity, self.next, self.by_gap = capacity, 0, defaultdict(list)

    def open(self, many: int, gap: int) -> int:
        first, self.next = self.next, self.next + many
        self.put(first, many, gap)
        return first

    def put(self, first: int, many: int, gap: int) -> None:
        if many and gap:
            self.by_gap[gap].append((first, many))

    def tightest(self, length: int) -> int | None:
        return next((g for g in range(length, self.capacity + 1) if self.by_gap.get(g)), None)


def plan(histogram: dict[int, int], capacity: int) -> list[tuple[int, int, int, int, int]]:
    """Runs (length, rank from, rank to, first sequence, offset) that place every item of the histogram."""
    left = {n: c for n, c in histogram.items() if c}
    given, bins, runs = defaultdict(int), _Bins(capacity), []

    def place(length: int, many: int, first: int, at: int) -> None:
        runs.append((length, given[length], given[length] + many, first, at))
        given[length] += many
        left[length] -= many

    large = sorted((n for n in left if 3 * n > capacity), reverse=True)
    for n in large:
        while left[n]:
            mate = next((m for m in large if m <= min(n, capacity - n) and left[m] > (m == n)), None)
            many = left[n] if mate is None else left[n] // 2 if mate == n else min(left[n], left[mate])
            first = bins.next
            bins.open(many, capacity - n - (mate or 0))
            place(n, many, first, 0)
            if mate is not None:
                place(mate, many, first, n)
    for n in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        while left[n]:
            gap = bins.tightest(n)
            if gap is None:
                each, gap = capacity // n, capacity
                bins.open(-(-left[n] // each), capacity)
            first, many = bins.by_gap[gap].pop()
            each, at = gap // n, capacity - gap
            full = min(many, left[n] // each)
            if full:
                for k in range(each):
                    place(n, full, first, at + k * n)
                bins.put(first, full, gap - each * n)
            if full < many:
                rest = left[n] if left[n] < each else 0
                for k in range(rest):
                    place(n, 1, first + full, at + k * n)
                if rest:
                    bins.put(first + full, 1, gap - rest * n)
                bins.put(first + full + (rest > 0), many - full - (rest > 0), gap)
    return runs


def pack(items: DataFrame, capacity: int = 2048) -> DataFrame:
    """Give each row of `items` (doc_id, piece, start, length, ...) a sequence_id and offset.

    `items` has to be stored (a table), as it is read for the histogram and for the ranks.
    """
    spark = items.sparkSession
    shards = min(4096, max(64, shuffle_partitions(spark)))
    dealt = items.withColumn("_shard", F.pmod(F.xxhash64("doc_id", "piece"), F.lit(shards)).cast("int"))
    counts = dealt.groupBy("length", "_shard").agg(F.count("*").alias("_n"))
    histogram = {r["length"]: r["n"] for r in items.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    runs = plan(histogram, capacity)
    runs_df = spark.createDataFrame(runs, PLAN_SCHEMA)
    if len(runs) <= BROADCAST_RUNS:
        runs_df = F.broadcast(runs_df)
    before = Window.partitionBy("length").orderBy("_shard").rowsBetween(Window.unboundedPreceding, -1)
    base = counts.withColumn("_base", F.coalesce(F.sum("_n").over(before), F.lit(0))).drop("_n")
    within = Window.partitionBy("length", "_shard").orderBy("doc_id", "piece")
    ranked = dealt.withColumn("_r", F.row_number().over(within)).join(base.hint("merge"), ["length", "_shard"])  # both sides are dealt by these already
    ranked = ranked.withColumn("_rank", F.col("_base") + F.col("_r") - 1)
    r = runs_df.select(F.col("length").alias("_l"), "rank_from", "rank_to", "seq_from", "at")
    placed = ranked.join(r, (F.col("length") == F.col("_l")) & (F.col("_rank") >= F.col("rank_from")) & (F.col("_rank") < F.col("rank_to")))
    return placed.select(*items.columns, (F.col("seq_from") + F.col("_rank") - F.col("rank_from")).alias("sequence_id"), F.col("at").cast("long").alias("offset"))


def pack_documents(docs: DataFrame, capacity: int = 2048, tokenizer: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece of every document."""
    stage = Stage(docs.sparkSession)
    stored = stage.table(pieces(docs, capacity, tokenizer, id_col, text_col), "pieces")
    return pack(stored, capacity).withColumn("length", F.col("length").cast("long"))
