"""Lineage cuts on storage that every executor shares.

Iterative plans cut their lineage by writing a table below the folder named in
``spark.checkpoint.dir``; a lost executor then only costs a re-read. Where the
session names no folder (tests, notebooks) a private temporary one is set once,
but only if driver and executors are one process; a cluster has to name one.

Tables written inside a :class:`scope` are deleted when it ends, except kept ones.
"""

from __future__ import annotations

import tempfile
import threading
import uuid

from pyspark.sql import DataFrame, SparkSession

_local = threading.local()


def scratch_root(spark: SparkSession) -> str:
    """The shared folder for intermediate tables of this application."""
    sc = spark.sparkContext
    current = sc._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named and sc.master != "local" and not sc.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="cutfold-scratch-"))
    return sc._jsc.sc().getCheckpointDir().get()


class scope:
    """``with scope() as s``: tables that :func:`saved` writes inside are deleted at the
    end, but for those given to ``s.keep``, which the scope around takes over."""

    def __enter__(self) -> scope:
        self.tables: dict[str, DataFrame] = {}
        self.kept: dict[str, DataFrame] = {}
        _local.scopes = [*getattr(_local, "scopes", []), self]
        return self

    def keep(self, copy: DataFrame) -> DataFrame:
        """``copy``, which must be what :func:`saved` returned, outlives the scope."""
        self.kept[copy._scratch_path] = copy
        return copy

    def __exit__(self, *error) -> None:
        _local.scopes = _local.scopes[:-1]
        drop_saved(*(t for path, t in self.tables.items() if path not in self.kept))
        if _local.scopes:
            _local.scopes[-1].tables |= self.kept


def saved(df: DataFrame, name: str, partition_by: list[str] | None = None) -> DataFrame:
    """Write ``df`` once to shared storage and return a reader of the copy."""
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    copy = spark.read.schema(df.schema).parquet(path)
    copy._scratch_path = path
    if scopes := getattr(_local, "scopes", []):
        scopes[-1].tables[path] = copy
    return copy


def drop_saved(*copies: DataFrame) -> None:
    """Delete tables made by :func:`saved` that no later plan reads."""
    for copy in copies:
        path = getattr(copy, "_scratch_path", None)
        if path is None:
            continue
        jvm = copy.sparkSession._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        conf = copy.sparkSession.sparkContext._jsc.hadoopConfiguration()
        target.getFileSystem(conf).delete(target, True)
