"""Committed state: Parquet tables in the folder that driver and executors share.

Loops cut their lineage by writing a table and reading it again. A table that has been
written survives lost executors and lets a later round start from files alone.
"""

from __future__ import annotations

import atexit
import contextlib
import functools
import gc
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``. Where it is unset, a folder of this machine that goes
    when the process ends, if driver and executors are one process; an error otherwise."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if root:
        return root.rstrip("/")
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        return f"file://{_own_folder()}"
    raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")


@functools.cache
def _own_folder() -> str:
    folder = tempfile.mkdtemp(prefix="kgfeat-")
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    return folder


ROWS_A_FILE = 100_000


_OPEN: dict[str, Workspace] = {}


@atexit.register
def _close_all() -> None:
    """Tables of results that nobody closed go with the process, if its JVM is still there to delete them."""
    for ws in list(_OPEN.values()):
        with contextlib.suppress(Exception):
            ws.close()


class Workspace:
    """A private folder below the shared one; every save is a committed Parquet table. It is deleted by
    close() or when the process ends, unless ``keep``."""

    def __init__(self, spark: SparkSession, tag: str, root: str | None = None, keep: bool = False):
        self.spark = spark
        self.base = f"{root or shared_root(spark)}/kgfeat/{tag}-{uuid.uuid4().hex[:12]}"
        self._n = 0
        self._tables: list[str] = []
        if not keep:
            _OPEN[self.base] = self

    def path(self, name: str) -> str:
        return f"{self.base}/{name}"

    def save(self, df: DataFrame, name: str, rows: int | None = None) -> DataFrame:
        """Write df, read it back with a fresh lineage. rows, a bound of its rows if one is known, keeps
        small tables in few files."""
        self._n += 1
        if rows is not None:
            df = df.coalesce(max(1, -(-rows // ROWS_A_FILE)))
        path = self.path(f"{self._n:03d}-{name}")
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._kgfeat_path = path
        return out

    def save_bucketed(self, df: DataFrame, name: str, buckets: int, key: str) -> DataFrame:
        """Save as a catalog table bucketed and sorted by key: later joins on key move only the other side."""
        self._n += 1
        table = f"kgfeat_{name}_{uuid.uuid4().hex[:12]}"
        df.write.bucketBy(buckets, key).sortBy(key).option("path", self.path(f"{self._n:03d}-{name}")).saveAsTable(table)
        self._tables.append(table)
        return self.spark.table(table)

    def close(self) -> None:
        """Delete all that was saved here."""
        for t in self._tables:
            self.spark.sql(f"DROP TABLE IF EXISTS {t}")
        self._tables.clear()
        self.delete(self.base)
        _OPEN.pop(self.base, None)

    def drop(self, df: DataFrame) -> None:
        """Delete a saved table that nothing refers to any more."""
        path = getattr(df, "_kgfeat_path", None)
        if path:
            self.delete(path)

    def sweep(self) -> None:
        """Files of shuffles stay until the driver collects its garbage: let it forget those of what is saved now."""
        gc.collect()
        self.spark._jvm.System.gc()

    def delete(self, path: str) -> None:
        jvm = self.spark._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(p, True)
