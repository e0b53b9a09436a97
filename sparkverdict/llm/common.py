"""Helpers that the operators share: shared-folder tables, shipping the package, prefix sums, word patterns."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: ASCII white space, the only characters that separate words here.
SPACE_CHARS = " \t\n\x0b\x0c\r"
SPACES = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; a local one only where the master is local."""
    conf = spark.sparkContext.getConf()
    found = conf.get("spark.checkpoint.dir", None)
    if not found:
        current = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = current.get() if current.isDefined() else None
    if not found:
        if not conf.get("spark.master", "local").split("[")[0] == "local":
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="sparkverdict-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def new_path(spark: SparkSession, label: str) -> str:
    """A fresh path in the shared folder; the JVM deletes it when it ends."""
    path = f"{shared_dir(spark)}/sparkverdict/{label}-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    hadoop_path = jvm.org.apache.hadoop.fs.Path(path)
    hadoop_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(hadoop_path)
    return path


def drop_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    hadoop_path = jvm.org.apache.hadoop.fs.Path(path)
    hadoop_path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop_path, True)


def materialise(df: DataFrame, label: str) -> DataFrame:
    """Write a table to the shared folder and read it back: cuts lineage, survives lost executors, computes once."""
    spark = df.sparkSession
    path = new_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def ship_package(spark: SparkSession) -> None:
    """Make this package importable in Python workers, wherever the driver found it."""
    sc = spark.sparkContext
    if getattr(sc, "_sparkverdict_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    target = os.path.join(tempfile.mkdtemp(prefix="sparkverdict-ship-"), "sparkverdict_package.zip")
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    sc.addPyFile(target)
    sc._sparkverdict_shipped = True


#: Rows that a Python worker holds as objects at once; Spark hands over ten thousand.
ROWS = 512


def slices(batches: Iterator) -> Iterator:
    """The batches in parts of few rows, so that texts as objects, and what is made of them, never stand for a whole batch."""
    for batch in batches:
        for low in range(0, batch.num_rows, ROWS):
            yield batch.slice(low, ROWS)


def hidden(df: DataFrame, *wanted: str) -> tuple[DataFrame, list[str]]:
    """The table with columns _c0, _c1, ... in place of its own, whose names so can't clash with working columns, and the
    new names of the wanted ones. `.toDF(*df.columns)` gives the old names back."""
    names = [f"_c{i}" for i in range(len(df.columns))]
    exact, lower = list(df.columns), [c.lower() for c in df.columns]
    return df.toDF(*names), [names[exact.index(w) if w in exact else lower.index(w.lower())] for w in wanted]


def words(text: Column) -> Column:
    """Array of the words of a text; none for null."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), SPACES), "")


def ordered_positions(df: DataFrame, group: str, order: list[str], amount: str, label: str) -> DataFrame:
    """Adds, within each group in the given order, `before` (sum of amount in earlier rows) and `row_before` (their count).

    A group may hold any share of the rows: rows are range-partitioned by (group, order), so a large group spans many
    tasks, each task sums its own run, and the small table of run totals gives every run its offset. Rows that tie in
    all of `order` may take either place. The result is a written table, so its order can't change between uses.
    """
    spark = df.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    ranged = (
        df.repartitionByRange(parts, F.col(group).asc_nulls_last(), *[F.col(c).asc_nulls_last() for c in order])
        .sortWithinPartitions(F.col(group).asc_nulls_last(), *[F.col(c).asc_nulls_last() for c in order])
        .withColumn("_at", F.monotonically_increasing_id())
    )
    placed = materialise(ranged, label).withColumn("_part", F.shiftright("_at", 33))
    runs = placed.groupBy("_part", group).agg(F.sum(amount).alias("_sum"), F.count(F.lit(1)).alias("_n"), F.min("_at").alias("_first"))
    earlier = Window.partitionBy(group).orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = runs.select(
        "_part", F.col(group).alias("_group"), "_first",
        F.coalesce(F.sum("_sum").over(earlier), F.lit(0)).alias("_sum0"),
        F.coalesce(F.sum("_n").over(earlier), F.lit(0)).alias("_n0"),
    )
    # inside one run the order is that of _at; a run is at most one partition, so this window never sees a whole hot group
    inside = Window.partitionBy("_part", group).orderBy("_at").rowsBetween(Window.unboundedPreceding, -1)
    return (
        placed.withColumn("_own", F.coalesce(F.sum(amount).over(inside), F.lit(0)))
        .join(offsets.withColumnRenamed("_part", "_opart"), (F.col("_part") == F.col("_opart")) & F.col(group).eqNullSafe(F.col("_group")))
        .withColumn("before", F.col("_sum0") + F.col("_own"))
        .withColumn("row_before", F.col("_n0") + F.col("_at") - F.col("_first"))
        .drop("_at", "_part", "_opart", "_group", "_first", "_sum0", "_n0", "_own")
    )
