"""Versioned state: base and delta folders named by a manifest, tombstones, compaction."""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


class StateStore:
    """Tables of base, inserts and tombstones.

    A version is what its manifest lists; the manifest is written last, so a version is there as a whole or not at
    all.  Folders are never overwritten.  One writer at a time.
    """

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")
        jvm = spark.sparkContext._jvm
        self._path = jvm.org.apache.hadoop.fs.Path
        self._fs = self._path(self.root).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
        self._fs.mkdirs(self._path(f"{self.root}/manifests"))

    def versions(self) -> list[int]:
        found = self._fs.listStatus(self._path(f"{self.root}/manifests"))
        return sorted(int(f.getPath().getName().split(".")[0]) for f in found if f.getPath().getName().endswith(".json"))

    def manifest(self, version: int | None = None) -> dict:
        have = self.versions()
        if not have:
            return {"version": -1, "tables": {}, "batch": -1}
        at = have[-1] if version is None else version
        return json.loads("\n".join(r["value"] for r in self.spark.read.text(f"{self.root}/manifests/{at:08d}.json").collect()))

    def _folder(self, df: DataFrame, name: str, by: str | None) -> str:
        at = f"{self.root}/data/{name}-{uuid.uuid4().hex}"
        w = df.write
        (w.partitionBy(by) if by else w).parquet(at)
        return at

    def commit(self, name: str, base: DataFrame | None = None, inserts: DataFrame | None = None, tombstones: DataFrame | None = None, by: str | None = None, batch: int | None = None) -> int:
        """Write folders, then the manifest; a batch that was committed before is skipped."""
        m = self.manifest()
        if batch is not None and batch <= m["batch"]:
            return m["version"]
        t = m["tables"].setdefault(name, {"base": [], "inserts": [], "tombstones": []})
        if base is not None:
            t |= {"base": [self._folder(base, name, by)], "inserts": [], "tombstones": []}
        if inserts is not None:
            t["inserts"].append(self._folder(inserts, f"{name}-ins", by))
        if tombstones is not None:
            t["tombstones"].append(self._folder(tombstones, f"{name}-del", None))
        m |= {"version": m["version"] + 1, "batch": m["batch"] if batch is None else batch}
        at = self._path(f"{self.root}/manifests/{m['version']:08d}.json")
        part = self._path(f"{self.root}/manifests/.{uuid.uuid4().hex}")
        out = self._fs.create(part)
        out.write(bytearray(json.dumps(m).encode()))
        out.close()
        if not self._fs.rename(part, at):
            raise RuntimeError(f"version {m['version']} was committed by another writer")
        return m["version"]

    def read(self, name: str, version: int | None = None, key: str = "edge_id") -> DataFrame:
        """(base and inserts) without the tombstones' keys."""
        t = self.manifest(version)["tables"][name]
        df = self.spark.read.parquet(t["base"][0])
        for at in t["base"][1:] + t["inserts"]:
            df = df.unionByName(self.spark.read.parquet(at))
        if t["tombstones"]:
            df = df.join(self.spark.read.parquet(*t["tombstones"]).select(key).distinct(), key, "left_anti")
        return df

    def compact(self, name: str, by: str | None = None) -> int:
        return self.commit(name, base=self.read(name), by=by)


def terms(triples: DataFrame) -> DataFrame:
    """(term, id): id is the 64-bit hash and a number that tells terms of one hash apart (0 unless hashes collide)."""
    all_terms = triples.select(F.col("s").alias("term")).union(triples.select("p")).union(triples.select("o")).distinct()
    hashed = all_terms.withColumn("h", F.xxhash64("term"))
    rank = F.transform(F.array_sort(F.collect_list("term")), lambda t, i: F.struct(t.alias("term"), i.cast("long").alias("k")))
    return hashed.groupBy("h").agg(rank.alias("xs")).select("h", F.explode("xs").alias("x")).select("x.term", F.struct("h", "x.k").alias("id"))


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> None:
    """A catalog table in which joins on `key` need no shuffle."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
