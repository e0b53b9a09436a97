"""Streams: event-time windows, and a claim monitor that keeps one tally per key and speaks once, when its test settles.

The monitor's intervals hold under exchangeable arrival; time order does not give that, so `drift` shows beside it how the
share moves between windows. A key that falls silent can be closed by an event-time timer; its verdict is then the exact one
of its rows. Streams are drained into files of the shared folder, not into the driver.
"""

from __future__ import annotations

import pickle
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkverdict.operators.tally import Tally
from sparkverdict.plans.claims import Test
from sparkverdict.session import shared_dir, ship_package


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table read as a stream of files; its timestamps have no zone and are taken as UTC."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events*.parquet").option("recursiveFileLookup", "true").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def run_once(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """Drains what is there into files of the shared folder and returns them: each batch's rows, or the last whole result."""
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/sparkverdict/stream-{name}-{uuid.uuid4().hex}"
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(folder)

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/rows/batch={0 if mode == 'complete' else number}")

    q = stream.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{path}/progress").trigger(availableNow=True).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()
    rows = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{path}/rows")
    if not folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(rows):
        return spark.createDataFrame([], stream.schema)
    return spark.read.schema(stream.schema).parquet(f"{path}/rows/batch=*")


def tumbling(events: DataFrame, width: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.window("ts", width).alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def sliding(events: DataFrame, width: str = "2 days", step: str = "1 day") -> DataFrame:
    return events.withWatermark("ts", "2 hours").groupBy(F.window("ts", width, step).alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def monitor(
    events: DataFrame, key: str, hit: str, test: Test, size: int | None = None, alpha: float | None = None, patience: int | None = None, delay: str = "2 hours"
) -> DataFrame:
    """key, verdict, seen, hits, settled_by: one row per key, when its test settles.

    With `alpha` an interval may settle it, and the state holds the wealth of the interval's candidates (some 17 KB); without
    it is a handful of numbers. With `patience` (seconds) a key whose last row lies that long behind the watermark, itself
    `delay` behind the newest row, is closed by a timer and judged by the rows it has; rows that come later are ignored."""
    ship_package(events.sparkSession)

    def step(k: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        held, done, last = state.get if state.exists else (None, False, 0)
        if done:
            for _ in frames:
                pass
            return
        tally = pickle.loads(held) if held is not None else Tally(test, size, alpha)
        if state.hasTimedOut:
            tally.close()
        else:
            rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
            tally.push(rows["hit"].fillna(False).to_numpy(bool))
            last = max(last, int(rows["at"].max()))
        state.update((None if tally.settled else pickle.dumps(tally), tally.settled, last))
        if tally.settled:
            yield pd.DataFrame({key: [k[0]], "verdict": [tally.verdict], "seen": [tally.seen], "hits": [tally.hits], "settled_by": [tally.settled_by]})
        elif patience is not None:
            state.setTimeoutTimestamp(max(last + patience * 1000, state.getCurrentWatermarkMs() + 1))

    kind = events.schema[key].dataType.simpleString()
    rows = (events if patience is None else events.withWatermark("ts", delay)).select(key, "ts", "event_id", F.expr(hit).alias("hit"), F.unix_millis("ts").alias("at"))
    timer = "NoTimeout" if patience is None else "EventTimeTimeout"
    return rows.groupBy(key).applyInPandasWithState(step, f"{key} {kind}, verdict boolean, seen long, hits long, settled_by string", "tally binary, done boolean, last long", "append", timer)


def old_after_new(events: DataFrame, cut: str, last: str) -> DataFrame:
    """The events as a stream of three batches: those from the day `cut` on, then those from the day `last` on, then the
    older ones, late. Spark drops what is behind the watermark of the batch before, so the lateness shows in the third."""
    spark = events.sparkSession
    path = f"{shared_dir(spark)}/sparkverdict/late-{uuid.uuid4().hex}"
    folder = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(folder)
    new, newest = (F.col("ts") >= F.lit(day).cast("timestamp") for day in (cut, last))
    files = int(spark.conf.get("spark.sql.shuffle.partitions"))
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    fs, named, bare = folder.getFileSystem(conf), jvm.org.apache.hadoop.fs.Path, f"{path}-no-rows"
    made = lambda at: [f.getPath() for f in fs.listStatus(named(at)) if f.getPath().getName().endswith(".parquet")]
    events.limit(0).coalesce(1).write.parquet(bare)
    fs.deleteOnExit(named(bare))
    for number, part in enumerate((new & ~newest, newest, ~new)):
        # the stream takes files by their age; each part has as many as a batch takes, some without rows where rows are few
        events.filter(part).repartition(files).write.parquet(f"{path}/part={number}")
        for i in range(files - len(made(f"{path}/part={number}"))):
            jvm.org.apache.hadoop.fs.FileUtil.copy(fs, made(bare)[0], fs, named(f"{path}/part={number}/none-{i}.parquet"), False, conf)
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", files).option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").parquet(path)


def drift(events: DataFrame, hit: str, width: str = "7 days") -> DataFrame:
    """Hits and rows per window: a share that moves is no exchangeable stream."""
    return events.groupBy(F.window("ts", width).alias("w")).agg(F.count_if(F.expr(hit)).alias("hits"), F.count(F.lit(1)).alias("seen")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "hits", "seen")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.withWatermark("ts", "2 hours").dropDuplicatesWithinWatermark(["event_id"])


def errors_after_clicks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stream-stream join: errors of a user within an hour of a click; both sides keep an hour's state behind their watermarks."""
    clicks = event_stream(spark, sf_dir).filter("event_type = 'click'").withWatermark("ts", "2 hours").selectExpr("event_id AS click", "user_id AS click_user", "ts AS click_ts")
    errors = event_stream(spark, sf_dir).filter("event_type = 'error'").withWatermark("ts", "2 hours").selectExpr("event_id AS error", "user_id", "ts")
    return clicks.join(errors, F.expr("click_user = user_id AND ts >= click_ts AND ts <= click_ts + INTERVAL 1 HOUR")).select("click", "error")


def sink_batches(stream: DataFrame, path: str) -> DataFrame:
    """foreachBatch sink: each micro-batch overwrites a folder of its own number, so a batch that is run again changes nothing."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    q = stream.writeStream.foreachBatch(write).option("checkpointLocation", f"{path}-progress").trigger(availableNow=True).start()
    try:
        q.awaitTermination()
    finally:
        q.stop()
    return stream.sparkSession.read.parquet(path)
