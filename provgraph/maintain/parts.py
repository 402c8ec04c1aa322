"""State as parts: a batch appends, a delete only notes edge ids, compaction writes what is left.

A part belongs to the version that wrote it.  A row is gone if an edge in it was deleted in a later version, so an id that is deleted and
inserted again is told apart.  Few deleted ids (SMALL) are a filter on the scan; more are applied by a join at once.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Deleted ids that are kept as a filter.
SMALL = 10_000
#: Parts of a table before it is compacted.
MOST_PARTS = 32


class Deleted:
    """Edge ids by the version in which they were deleted."""

    def __init__(self):
        self.ids: list[tuple[int, list[int]]] = []

    def add(self, version: int, ids: list[int]) -> None:
        self.ids.append((version, ids))

    def after(self, version: int) -> list[int]:
        return sorted({i for v, ids in self.ids if v > version for i in ids})

    @property
    def count(self) -> int:
        return sum(len(ids) for _, ids in self.ids)


class Parts:
    def __init__(self, spark: SparkSession, root: str, name: str, schema: str, edges: str, deleted: Deleted, array: bool = True, by: list[str] | None = None):
        self.spark, self.root, self.name, self.schema, self.edges, self.array, self.deleted, self.by = spark, root, name, schema, edges, array, deleted, by
        self.parts: list[tuple[int, str]] = []

    def append(self, rows: DataFrame, version: int) -> DataFrame:
        at = f"{self.root}/v{version:06d}_{self.name}_{uuid.uuid4().hex[:6]}"
        (rows.sortWithinPartitions(*self.by) if self.by else rows).write.parquet(at)
        self.parts.append((version, at))
        return self.spark.read.schema(rows.schema).parquet(at)

    def _alive(self, version: int) -> Column | None:
        ids = self.deleted.after(version)
        if not ids:
            return None
        listed = ", ".join(map(str, ids))
        return F.expr(f"NOT exists({self.edges}, e -> e IN ({listed}))" if self.array else f"{self.edges} NOT IN ({listed})")

    def read(self, where: Column | None = None) -> DataFrame:
        """Rows of all parts that are not gone."""
        by_version: dict[int, list[str]] = {}
        marks = sorted({v for v, _ in self.deleted.ids})
        for v, at in self.parts:
            by_version.setdefault(next((m for m in marks if m > v), -1), []).append(at)  # parts between two deletes are read alike
        out = None
        for mark, paths in sorted(by_version.items()):
            df = self.spark.read.schema(self.schema).parquet(*paths)
            alive = self._alive(mark - 1) if mark >= 0 else None
            df = df if where is None else df.where(where)
            df = df if alive is None else df.where(alive)
            out = df if out is None else out.unionByName(df)
        return out if out is not None else self.spark.createDataFrame([], self.schema)

    def rewrite(self, rows: DataFrame, version: int) -> None:
        """Replace all parts; old ones stay on disk until the state is closed, as frames may still read them."""
        old = self.parts
        self.parts = []
        try:
            self.append(rows, version)
        except Exception:
            self.parts = old
            raise

    def without(self, ids: DataFrame) -> DataFrame:
        """Rows that hold none of many ids, by a join."""
        rows = self.read()
        if not self.array:
            return rows.join(ids, self.edges == ids["edge_id"] if not isinstance(self.edges, str) else rows[self.edges] == ids["edge_id"], "left_anti")
        key = rows.columns
        hit = rows.select(*key, F.explode(F.array_distinct(self.edges)).alias("_e")).join(ids.select(F.col("edge_id").alias("_e")), "_e", "left_semi").select(*key).distinct()
        return rows.join(hit, key, "left_anti")

    @property
    def bytes(self) -> int:
        """Size of the table's files."""
        sc = self.spark.sparkContext
        path, total = sc._jvm.org.apache.hadoop.fs.Path, 0
        for _, at in self.parts:
            p = path(at)
            total += p.getFileSystem(sc._jsc.hadoopConfiguration()).getContentSummary(p).getLength()
        return total
