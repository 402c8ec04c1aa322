"""Count tables of a size fixed beforehand: tasks fill them, blocks are summed by streaming."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import shuffle_partitions

BLOCK = 1 << 13
SCHEMA = "model int, block int, counts binary"


def blocks(tables: list[np.ndarray]):
    """Record batches of the blocks that hold a count."""
    got = [(k, b, t[b * BLOCK : (b + 1) * BLOCK]) for k, t in enumerate(tables) for b in np.flatnonzero(t.reshape(-1, BLOCK).any(1)).tolist()]
    yield from _batches(got)


def _batches(got: list):
    for i in range(0, len(got), 16):
        k, b, v = zip(*got[i : i + 16])
        raw = [x.astype("<i8" if x.max() > 0xFFFFFFFF else "<u4").tobytes() for x in v]
        yield pa.RecordBatch.from_arrays([pa.array(k, pa.int32()), pa.array(b, pa.int32()), pa.array(raw, pa.binary())], names=["model", "block", "counts"])


def _numbers(raw: bytes) -> np.ndarray:
    return np.frombuffer(raw, "<u4" if len(raw) == 4 * BLOCK else "<i8").astype(np.int64)


def total(parts: DataFrame, sizes: tuple[int, ...]) -> list[np.ndarray]:
    """Sum the tables of all tasks; their size, not the input's, bounds what any task or the driver holds."""

    def summed(batches):
        held: dict[tuple[int, int], np.ndarray] = {}
        for batch in batches:
            for k, b, raw in zip(*(c.to_pylist() for c in batch.columns)):
                held[k, b] = held.get((k, b), 0) + _numbers(raw)
        yield from _batches([(k, b, v) for (k, b), v in sorted(held.items(), key=lambda x: x[0])])

    n = shuffle_partitions(parts.sparkSession)
    # two rounds, so that no task takes in a block of every task
    parts = parts.repartition(n, "model", "block", F.pmod(F.monotonically_increasing_id(), F.lit(16))).mapInArrow(summed, SCHEMA)
    parts = parts.repartition(n, "model", "block").mapInArrow(summed, SCHEMA)
    out = [np.zeros(size, np.int64) for size in sizes]
    for r in parts.toLocalIterator():
        out[r["model"]][r["block"] * BLOCK : (r["block"] + 1) * BLOCK] += _numbers(bytes(r["counts"]))
    return out
