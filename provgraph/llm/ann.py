"""Approximate nearest neighbours by an adaptive dimension scan in inverted lists.

Vectors are rotated by a fixed random orthogonal matrix, so each block of columns carries its share of a distance.
Within a probed list the columns are scanned block by block; after each block a hypothesis test on
the partial distance abandons candidates that are unlikely to be among the nearest.  What is left gets
its exact distance on the original vectors.

Equal vectors are searched once: a distinct vector carries its smallest ids (as many as a result can hold), and equal queries
share one search, so a vector that a third of all rows hold is no hot spot.  Lists are cut into blocks by a hash, and a query
goes to each block of its probed lists, so no task takes in a whole list.

Fit: rotation from a seed; centroids by k-means over at most `sample` distinct vectors (smallest hashes).
Every vector is indexed.

Defined results: vectors that are null, empty, zero, of another length than most of the sample's, or hold null or
non-finite components take no part, as query or candidate; rows with a null id neither; ties go to the smaller id; with
fewer candidates than k all found are given; equal rows (same id and vector) count once.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .runtime import Stage, ship

BLOCK_ROWS = 4096
COLUMNS = 16


@dataclass
class Index:
    """Fixed-size part of the index: rotation and centroids (of rotated vectors)."""

    rotation: np.ndarray
    centroids: np.ndarray
    epsilon: float = 2.1

    def nearest_lists(self, rotated: np.ndarray, n: int) -> np.ndarray:
        d = (self.centroids**2).sum(1) - 2 * rotated @ self.centroids.T
        n = min(n, d.shape[1])
        part = np.argpartition(d, n - 1, 1)[:, :n]
        return np.take_along_axis(part, np.argsort(np.take_along_axis(d, part, 1), 1, kind="stable"), 1)


def rotation(width: int, seed: int = 17) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).standard_normal((width, width)))
    return q * np.sign(np.diag(r))


def k_means(x: np.ndarray, k: int, rounds: int = 12, seed: int = 17) -> np.ndarray:
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = np.concatenate([((c**2).sum(1) - 2 * x[i : i + 4096] @ c.T).argmin(1) for i in range(0, len(x), 4096)])
        size = np.bincount(near, minlength=len(c))
        total = np.zeros_like(c)
        np.add.at(total, near, x)
        c[size > 0] = total[size > 0] / size[size > 0, None]
    return c


def scan(query: np.ndarray, columns: np.ndarray, keep: int, epsilon: float) -> np.ndarray:
    """Rows of a list (columns x rows, rotated) that survive the test: a superset, with high probability, of the `keep` nearest."""
    width, n = columns.shape
    if n <= 2 * keep:
        return np.arange(n)
    # the first rows get whole distances and set the bound
    first = np.arange(min(n, max(4 * keep, 64)))
    bound = np.partition(((columns[:, first] - query[:, None]) ** 2).sum(0), keep - 1)[keep - 1]
    alive, partial = np.arange(len(first), n), np.zeros(n - len(first))
    for a in range(0, width, COLUMNS):
        b = min(a + COLUMNS, width)
        partial += ((columns[a:b, alive] - query[a:b, None]) ** 2).sum(0)
        if b < width:
            ok = partial * width / b <= bound * (1 + epsilon / np.sqrt(b)) ** 2
        else:
            ok = partial <= bound * (1 + 1e-9)
        alive, partial = alive[ok], partial[ok]
        if not len(alive):
            break
    return np.concatenate([first, alive])


def clean(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """vec_id, v of rows that take part."""
    v = F.col(vec_col).cast("array<double>")
    finite = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return vectors.select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v")).where(F.col("vec_id").isNotNull() & (F.size("v") > 0) & finite & F.exists("v", lambda x: x != 0))


def distinct_vectors(rows: DataFrame, keep: int) -> DataFrame:
    """v, ids: each vector once with its `keep` smallest ids; a hot vector is cut down in two rounds."""
    def smallest(by: list) -> DataFrame:
        w = Window.partitionBy(*by).orderBy("vec_id")
        return F.row_number().over(w)

    rows = rows.withColumn("_h", F.xxhash64("v")).withColumn("_s", F.pmod(F.xxhash64("vec_id"), F.lit(64)))
    once = rows.dropDuplicates(["_h", "_s", "vec_id", "v"])
    few = once.withColumn("_r", smallest(["_h", "_s", "v"])).where(F.col("_r") <= keep)
    few = few.withColumn("_r", smallest(["_h", "v"])).where(F.col("_r") <= keep)
    return few.groupBy("_h", "v").agg(F.array_sort(F.collect_list("vec_id")).alias("ids")).drop("_h")


def build(distinct: DataFrame, lists: int = 64, sample: int = 20_000, epsilon: float = 2.1) -> Index | None:
    got = distinct.select("v", F.xxhash64("v").alias("_h")).orderBy("_h").limit(sample).select("v").toArrow().column(0).to_pylist()
    if not got:
        return None
    width = Counter(map(len, got)).most_common(1)[0][0]
    r = rotation(width)
    x = np.array([v for v in got if len(v) == width]) @ r
    return Index(r, k_means(x, max(1, min(lists, len(x) // 40))), epsilon)


def search(vectors: DataFrame, k: int = 10, every: int = 100, probes: int = 44, lists: int = 64, sample: int = 20_000, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest found for each row whose id is divisible by `every`."""
    spark = vectors.sparkSession
    ship(spark)
    stage = Stage(spark)
    rows = clean(vectors, id_col, vec_col)
    distinct = stage.table(distinct_vectors(rows, k + 1), "distinct")
    index = build(distinct, lists, sample)
    if index is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    width = len(index.rotation)
    shared = spark.sparkContext.broadcast(index)
    blocks = max(1, distinct.count() // (BLOCK_ROWS * len(index.centroids)) + 1)

    def listed(n_lists: int):
        def run(batches):
            ix = shared.value
            for batch in batches:
                v = batch.column(batch.schema.get_field_index("v"))
                x = v.values.to_numpy(zero_copy_only=False)[v.offsets[0].as_py() : v.offsets[-1].as_py()].reshape(-1, width)
                near = ix.nearest_lists(x @ ix.rotation, n_lists).astype(np.int32)
                lists_column = pa.ListArray.from_arrays(np.arange(0, near.size + 1, near.shape[1], dtype=np.int32), pa.array(near.ravel()))
                yield pa.RecordBatch.from_arrays([*batch.columns, lists_column], names=[*batch.schema.names, "lists"])
        return run

    fits = distinct.where(F.size("v") == width)
    base = fits.mapInArrow(listed(1), "v array<double>, ids array<long>, lists array<int>").select("v", "ids", F.col("lists")[0].alias("list"), F.pmod(F.xxhash64("v"), F.lit(blocks)).alias("block"))
    asked = rows.where((F.pmod(F.col("vec_id"), F.lit(every)) == 0) & (F.size("v") == width)).distinct()
    asked = stage.table(asked.withColumn("q", F.xxhash64("v")), "queries")
    probes_df = asked.select("q", "v").dropDuplicates(["q"]).mapInArrow(listed(probes), "q long, v array<double>, lists array<int>")
    probes_df = probes_df.select("q", "v", F.explode("lists").alias("list")).select("q", "v", "list", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("block"))

    def within(key, left, right):
        ix = shared.value
        if not left.num_rows or not right.num_rows:
            return pa.table({"q": pa.array([], pa.int64()), "ids": pa.array([], pa.list_(pa.int64())), "score": pa.array([], pa.float64())})
        matrix = lambda t: np.array(t.column("v").to_pylist())
        x, queries = matrix(left), matrix(right)
        columns, rotated, ids = np.ascontiguousarray((x @ ix.rotation).T), queries @ ix.rotation, left.column("ids").to_pylist()
        q, found, score = [], [], []
        for name, own, turned in zip(right.column("q").to_pylist(), queries, rotated):
            rows = scan(turned, columns, k + 1, ix.epsilon)
            d = np.sqrt(((x[rows] - own) ** 2).sum(1))
            for r in np.argsort(d, kind="stable")[: k + 1] if len(d) <= k + 1 else np.flatnonzero(d <= np.partition(d, k)[k]):
                q.append(name)
                found.append(ids[rows[r]])
                score.append(float(d[r]))
        return pa.table({"q": pa.array(q, pa.int64()), "ids": pa.array(found, pa.list_(pa.int64())), "score": pa.array(score, pa.float64())})

    found = base.groupBy("list", "block").cogroup(probes_df.groupBy("list", "block")).applyInArrow(within, "q long, ids array<long>, score double")
    # distinct vectors first: k + 1 of them hold the k nearest ids, whatever their ties
    near = found.select("q", "score", F.explode("ids").alias("vec_id")).withColumn("_r", F.row_number().over(Window.partitionBy("q").orderBy("score", "vec_id"))).where(F.col("_r") <= k + 1)
    named = asked.select(F.col("vec_id").alias("query_id"), "q").join(near, "q").where(F.col("query_id") != F.col("vec_id"))
    ranked = named.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id")).cast("int"))
    return ranked.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
