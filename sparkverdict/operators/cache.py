"""Prompt cache: answers keyed by model and full prompt, a Parquet table partitioned by model.

Appends are idempotent: a retried append writes the same (hash, prompt, answer) again and reads collapse equal keys.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkverdict.functions.truth import Pred
from sparkverdict.operators.models import SemanticModel
from sparkverdict.session import ship_package, written

SCHEMA = "prompt_hash long, prompt string, answer boolean, model string"


class PromptCache:
    def __init__(self, spark: SparkSession, path: str) -> None:
        self.spark, self.path = spark, path

    def _exists(self) -> bool:
        p = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        return p.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).exists(p)

    def table(self, model: str) -> DataFrame:
        if not self._exists():
            return self.spark.createDataFrame([], SCHEMA)
        found = self.spark.read.schema(SCHEMA).parquet(self.path).filter(F.col("model") == model)
        return found.groupBy("prompt_hash", "prompt").agg(F.first("answer").alias("answer"))

    def append(self, answers: DataFrame, model: str) -> None:
        answers.select("prompt_hash", "prompt", "answer", F.lit(model).alias("model")).write.mode("append").partitionBy("model").parquet(self.path)


def answers(df: DataFrame, pred: Pred, model: SemanticModel, cache: PromptCache | None = None, out: str = "answer") -> tuple[DataFrame, int]:
    """df with the model's answer to pred, and how many prompts went to the model: equal prompts go once, known ones never."""
    ship_package(df.sparkSession)
    parts = [F.coalesce(F.col(c).cast("string"), F.lit("None")) for c in pred.columns]
    asked = df.withColumn("prompt", F.concat_ws("|", F.lit(pred.name), *parts)).withColumn("prompt_hash", F.xxhash64("prompt"))
    distinct = asked.dropDuplicates(["prompt_hash", "prompt"]).select("prompt_hash", "prompt", *pred.columns)
    known = cache.table(model.name).select("prompt_hash", "prompt", "answer") if cache else None
    misses = distinct.join(known, ["prompt_hash", "prompt"], "left_anti") if known is not None else distinct
    columns = list(pred.columns)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            said = [model.answer(pred, r) for r in frame[columns].to_dict("records")]
            yield pd.DataFrame({"prompt_hash": frame["prompt_hash"], "prompt": frame["prompt"], "answer": said})

    fresh = written(misses.mapInPandas(run, "prompt_hash long, prompt string, answer boolean"), "fresh-answers")
    n = fresh.count()
    every = fresh if known is None else fresh.unionByName(written(known, "known-answers"))
    if cache is not None:
        cache.append(fresh, model.name)
    joined = asked.join(every.withColumnRenamed("answer", out), ["prompt_hash", "prompt"], "left").drop("prompt_hash", "prompt")
    return joined, n
