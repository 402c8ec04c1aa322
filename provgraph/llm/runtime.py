"""What all operators share: shipping code, stage tables and folds."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Spark's switch, changeable in a session, by which a statement's shuffle files are removed when it ends.
CLEAN_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_PACKAGE = Path(__file__).resolve().parents[1]
_shipped: dict[str, str] = {}
_spaces: dict[str, str] = {}


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once for each application."""
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    folder = tempfile.mkdtemp(prefix="provgraph_code_")
    target = os.path.join(folder, f"{_PACKAGE.name}.zip")
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(_PACKAGE.rglob("*.py")):
            z.write(p, p.relative_to(_PACKAGE.parent))
    sc.addPyFile(target)
    _shipped[sc.applicationId] = target


def workspace(spark: SparkSession) -> str:
    """The folder that all executors share (spark.checkpoint.dir); a local one of our own only where it is unset."""
    shared = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not shared:
        key = spark.sparkContext.applicationId
        if key not in _spaces:
            _spaces[key] = tempfile.mkdtemp(prefix="provgraph_stage_")
            spark.sparkContext.setCheckpointDir(_spaces[key])
        shared = _spaces[key]
    return f"{shared.rstrip('/')}/stage-{uuid.uuid4().hex}"


def _remove(jvm_path, conf) -> None:
    try:
        jvm_path.getFileSystem(conf).delete(jvm_path, True)
    except Exception:  # noqa: BLE001 - the session may be gone at exit
        pass


def drop(spark: SparkSession, path: str) -> None:
    """Delete a stage table that no later step reads."""
    sc = spark.sparkContext
    _remove(sc._jvm.org.apache.hadoop.fs.Path(path), sc._jsc.hadoopConfiguration())


class Stage:
    """Stage tables of one operator call, written to the shared folder and read back.

    A table cuts the lineage: after a lost executor only the tasks of the running step are
    repeated.  Tables that the returned frame still reads stay until the session ends.
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.root, self.n = spark, workspace(spark), 0
        atexit.register(self._close)

    def _close(self) -> None:
        if self.spark.sparkContext._jsc is not None:
            try:
                drop(self.spark, self.root)
            except Exception:  # noqa: BLE001
                pass

    def path(self, name: str) -> str:
        self.n += 1
        return f"{self.root}/{self.n:03d}_{name}"

    def table(self, df: DataFrame, name: str) -> DataFrame:
        """Write a table and read it back; shuffle files of its making go at once, as nothing needs them behind the table."""
        at = self.path(name)
        conf = self.spark.conf
        before = conf.get(CLEAN_SHUFFLES, None)
        conf.set(CLEAN_SHUFFLES, "true")
        try:
            df.write.option("compression", "zstd").parquet(at)
        finally:
            if before is None:
                conf.unset(CLEAN_SHUFFLES)
            else:
                conf.set(CLEAN_SHUFFLES, before)
        out = self.spark.read.schema(df.schema).parquet(at)
        out._stage_path = at
        return out

    def drop(self, df: DataFrame) -> None:
        drop(self.spark, df._stage_path)


def fold(id_col: str | Column, n: int) -> Column:
    """crc32 of the id's text modulo n."""
    c = F.col(id_col) if isinstance(id_col, str) else id_col
    return F.pmod(F.crc32(c.cast("string").cast("binary")), F.lit(n))


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
