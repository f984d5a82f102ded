"""Session helpers: shared folder, lineage cuts, table access.

Lineage is cut only through storage that every executor sees. On a cluster that
folder is named by ``spark.checkpoint.dir``; when no folder is named, a local master
(tests, a laptop) gets one under the local temp folder, removed at exit, and any other
master is refused.
"""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """URI of the folder that the driver and all executors share."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not named:
        named = spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir names no shared folder; a folder of one machine will not do on a cluster")
        os.makedirs("/tmp/checkpoints", exist_ok=True)
        own = tempfile.mkdtemp(prefix="grove-", dir="/tmp/checkpoints")
        atexit.register(shutil.rmtree, own, ignore_errors=True)
        spark.sparkContext.setCheckpointDir("file://" + own)
        named = "file://" + own
    return named.rstrip("/")


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path for a written table in the shared folder."""
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


#: Called with every table that is about to be written; a ledger that measures plans adds itself.
WATCHERS: list[Callable[[DataFrame], None]] = []


def _write(df: DataFrame, path: str) -> DataFrame:
    for watch in WATCHERS:
        watch(df)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def cut(df: DataFrame, name: str = "cut") -> DataFrame:
    """Write ``df`` once and read it back: flat lineage, columnar, prunable, and
    readable after any executor is lost."""
    return _write(df, scratch(df.sparkSession, name))


class Parts:
    """A table that grows part by part: each part is written once, and all are read by one scan,
    so a loop of many rounds leaves no union of many plans."""

    def __init__(self, spark: SparkSession, name: str, schema: str):
        self.spark, self.schema, self.path, self.n = spark, schema, scratch(spark, name), 0

    def add(self, df: DataFrame) -> DataFrame:
        self.n += 1
        return _write(df, f"{self.path}/part={self.n}")

    def frame(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(f"{self.path}/part=*") if self.n else self.spark.createDataFrame([], self.schema)

    def drop(self) -> None:
        if self.n:
            drop_paths(self.spark, self.path)


def drop_paths(spark: SparkSession, *paths: str) -> None:
    """Delete folders under the shared one once nothing reads them."""
    for name in paths:
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def drop_cut(*tables: DataFrame) -> None:
    """Delete the files behind tables made by :func:`cut` once nothing reads them."""
    for df in tables:
        base = shared_dir(df.sparkSession).split(":", 1)[-1].lstrip("/")
        drop_paths(df.sparkSession, *{f[: f.rindex("/")] for f in df.inputFiles() if base in f})


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
