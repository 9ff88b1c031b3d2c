"""What every operator needs from a session: the package on the workers and a folder all executors share."""

from __future__ import annotations

import atexit
import gc
import os
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers; once for each Spark application."""
    sc = spark.sparkContext
    if sc.applicationId in _shipped:
        return
    root = Path(__file__).resolve().parent
    folder = tempfile.mkdtemp(prefix="rankfit-ship-")
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    target = os.path.join(folder, f"{root.name}.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as out:
        for path in sorted(root.rglob("*.py")):
            out.write(path, path.relative_to(root.parent))
    sc.addPyFile(target)
    _shipped.add(sc.applicationId)


def shared_folder(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; a local one only where the setting is absent, as in tests."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if named is None:
        if not sc.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir is not set: executors of a cluster need a folder they share")
        named = tempfile.mkdtemp(prefix="rankfit-checkpoint-")
        atexit.register(shutil.rmtree, named, ignore_errors=True)
        sc.setCheckpointDir(named)
    elif sc.getCheckpointDir() is None:
        sc.setCheckpointDir(named)
    return named


def cut(df: DataFrame) -> DataFrame:
    """Checkpoint `df` in the shared folder, so that later plans restart from its files."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def new_table(spark: SparkSession, name: str) -> str:
    """A fresh path below the shared folder for a table an operator writes and reads again."""
    return f"{shared_folder(spark).rstrip('/')}/rankfit-{name}-{uuid.uuid4().hex}"


def drop_table(spark: SparkSession, path: str) -> None:
    """Remove a table made by `new_table`, whatever file system it is on."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


class Scratch:
    """Parquet tables of one operator's intermediate results in the shared folder, removed when it has its result."""

    def __init__(self, spark: SparkSession, keep: int | None = None):
        """With `keep` only so many of the last tables stay."""
        self.spark, self.paths, self.keep = spark, [], keep

    def table(self, df: DataFrame) -> DataFrame:
        path = new_table(self.spark, "scratch")
        self.paths.append(path)
        df.write.parquet(path)
        if self.keep:
            self._drop(len(self.paths) - self.keep)
        return self.spark.read.schema(df.schema).parquet(path)

    def _drop(self, n: int) -> None:
        for _ in range(n):
            drop_table(self.spark, self.paths.pop(0))

    def close(self) -> None:
        self._drop(len(self.paths))


def forget_shuffles(spark: SparkSession) -> None:
    """Let Spark's cleaner remove the files of shuffles that nothing refers to: it only learns of them from collections."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
