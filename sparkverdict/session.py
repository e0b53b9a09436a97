"""Session helpers: shipping the package to workers and tables in the shared folder."""

from __future__ import annotations

import os
import tempfile
import threading
import uuid
import zipfile
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession


def ship_package(spark: SparkSession) -> None:
    """Python workers import this package by name; send it along once per context."""
    sc = spark.sparkContext
    if getattr(sc, "_sparkverdict_shipped", False):
        return
    root = Path(__file__).resolve().parent
    target = os.path.join(tempfile.mkdtemp(prefix="sparkverdict-ship-"), "sparkverdict_package.zip")
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    sc.addPyFile(target)
    sc._sparkverdict_shipped = True


def shared_dir(spark: SparkSession) -> str:
    conf = spark.sparkContext.getConf()
    found = conf.get("spark.checkpoint.dir", None)
    if not found:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = current.get() if current.isDefined() else None
    if not found:
        if conf.get("spark.master", "local").split("[")[0] != "local":
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="sparkverdict-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


_own = threading.local()


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Tables that this thread writes inside are deleted at the end; nothing that reads them may be used afterwards."""
    outer, _own.paths = getattr(_own, "paths", None), []
    try:
        yield
    finally:
        for path in _own.paths:
            dropped(spark, path)
        _own.paths = outer


def dropped(spark: SparkSession, path: str) -> None:
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(folder, True)


def written(df: DataFrame, label: str) -> DataFrame:
    """A table in the shared folder: evaluated once, without lineage, safe against lost executors; gone with the JVM."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/sparkverdict/{label}-{uuid.uuid4().hex}"
    hadoop_path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    hadoop_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop_path)
    if getattr(_own, "paths", None) is not None:
        _own.paths.append(path)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
