"""Shared scratch space and lineage cuts.

Every intermediate table goes to the folder that the cluster names in
``spark.checkpoint.dir``; only where that is unset (tests, notebooks) does a
local folder of our own take its place, and only for a local master. Tables
that nobody dropped go when the process ends, or by ``close``.
"""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import uuid

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession

_OWN: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors can read and write."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _OWN:
        own = tempfile.mkdtemp(prefix="nudgegraph-")
        atexit.register(shutil.rmtree, own, True)
        _OWN.append("file://" + own)
    return _OWN[0]


def scratch_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_dir(spark)}/nudgegraph/{tag}-{uuid.uuid4().hex[:12]}"


#: folders of tables that were written and not dropped, with their sessions
_KEPT: dict[str, SparkSession] = {}


def close() -> None:
    """Delete all scratch tables of this process; frames that read them are void from then on."""
    for path, spark in list(_KEPT.items()):
        _KEPT.pop(path)
        with contextlib.suppress(Py4JError):  # the session may be gone already
            if spark.sparkContext._jsc is not None and not spark.sparkContext._jsc.sc().isStopped():
                delete_path(spark, path)


atexit.register(close)


class Scratch:
    """Intermediate tables of one operator call, deleted when no longer read."""

    def __init__(self, spark: SparkSession, tag: str):
        self.spark, self.tag, self.paths, self.held = spark, tag, {}, {}

    def keep(self, df: DataFrame, name: str) -> DataFrame:
        """Write ``df`` and return a frame that reads the written table."""
        path = scratch_path(self.spark, f"{self.tag}-{name}")
        df.write.option("compression", "zstd").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self.paths[id(out)], self.held[id(out)] = path, out
        _KEPT[path] = self.spark
        return out

    def frames(self) -> list[DataFrame]:
        """The frames that ``keep`` returned and nobody dropped."""
        return list(self.held.values())

    def drop(self, *frames: DataFrame) -> None:
        """Delete tables that ``keep`` returned."""
        for df in frames:
            path = self.paths.pop(id(df), None)
            self.held.pop(id(df), None)
            if path:
                delete_path(self.spark, path)
                _KEPT.pop(path, None)


def delete_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
