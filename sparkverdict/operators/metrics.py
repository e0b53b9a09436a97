"""Measures over result, token and answer tables. Ungrounded (false) claims are the positive class."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def _ratio(a: Column, b: Column) -> Column:
    return F.coalesce(F.try_divide(a.cast("double"), b.cast("double")), F.lit(0.0))


def verification(results: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """verdict and expected -> tp, fp, fn, tn, precision, recall, f1, accuracy."""
    bad, said = ~F.col("expected"), ~F.col("verdict")
    n = results.groupBy(*by).agg(F.count_if(bad & said).alias("tp"), F.count_if(~bad & said).alias("fp"), F.count_if(bad & ~said).alias("fn"), F.count_if(~bad & ~said).alias("tn"))
    return scores(n)


def scores(n: DataFrame) -> DataFrame:
    c = F.col
    return n.withColumn("precision", _ratio(c("tp"), c("tp") + c("fp"))).withColumn("recall", _ratio(c("tp"), c("tp") + c("fn"))).withColumn("f1", _ratio(2 * c("tp"), 2 * c("tp") + c("fp") + c("fn"))).withColumn(
        "accuracy", _ratio(c("tp") + c("tn"), c("tp") + c("fp") + c("fn") + c("tn"))
    )


def cost(call_log: DataFrame, prices: DataFrame, by: tuple[str, ...] = ("claim_id",)) -> DataFrame:
    """Dollars per group of the log; cached answers are free. prices has one row per model."""
    priced = call_log.join(prices, "model")
    spent = (F.col("tokens_in") * F.col("usd_in") + F.col("tokens_out") * F.col("usd_out")) / 1e6
    return priced.groupBy(*by).agg(F.sum(F.when(F.col("cached"), 0).otherwise(spent)).alias("usd"), F.count_if(~F.col("cached")).alias("calls"))


def trials(df: DataFrame, value: str, by: tuple[str, ...]) -> DataFrame:
    return df.groupBy(*by).agg(F.avg(value).alias("mean"), F.min(value).alias("low"), F.max(value).alias("high"), F.stddev(value).alias("sd"))


def heat(df: DataFrame, configs: list[str]) -> DataFrame:
    """Correct trials per claim and configuration."""
    return df.groupBy("claim_id").pivot("config", configs).agg(F.count_if(F.col("verdict") == F.col("expected")))


def pareto(df: DataFrame, cost_col: str = "cost", value: str = "f1") -> DataFrame:
    """Configurations that no other beats: at most the cost, at least the value, one of them strictly. Few rows."""
    o = df.select(F.col(cost_col).alias("_c"), F.col(value).alias("_v"))
    better = (F.col("_c") <= F.col(cost_col)) & (F.col("_v") >= F.col(value)) & ((F.col("_c") < F.col(cost_col)) | (F.col("_v") > F.col(value)))
    return df.join(o, better, "left_anti")


def cost_ratio(df: DataFrame, base: str, other: str) -> DataFrame:
    """Cost of `other` over that of `base`, by config."""
    return df.agg(_ratio(F.max(F.when(F.col("config") == other, F.col("cost"))), F.max(F.when(F.col("config") == base, F.col("cost")))).alias("ratio"))


def provenance_precision(tokens: DataFrame, reference: DataFrame) -> DataFrame:
    """Tokens whose sign the reference (tid, hit) confirms, pooled."""
    hit = F.when(F.col("hit"), 1).otherwise(-1)
    both = tokens.join(reference.select("tid", "hit"), F.col("tuple_id") == F.col("tid"), "left")
    return both.agg(F.count_if(F.col("sign") == hit).alias("right"), F.count(F.lit(1)).alias("returned")).withColumn("precision", _ratio(F.col("right"), F.col("returned")))


def filter_quality(predicted: DataFrame, reference: DataFrame) -> DataFrame:
    """(op_id, tid) selected by either side, micro-averaged."""
    a, b = predicted.select("op_id", "tid", F.lit(True).alias("p")), reference.select("op_id", "tid", F.lit(True).alias("r"))
    both = a.join(b, ["op_id", "tid"], "full")
    return scores(both.agg(F.count_if(F.col("p") & F.col("r")).alias("tp"), F.count_if(F.col("p") & F.col("r").isNull()).alias("fp"), F.count_if(F.col("p").isNull() & F.col("r")).alias("fn"), F.lit(0).alias("tn")))


def map_accuracy(answers: DataFrame) -> DataFrame:
    """predicted <=> truth over all outputs of all maps."""
    return answers.agg(F.count_if(F.col("predicted").eqNullSafe(F.col("truth"))).alias("right"), F.count(F.lit(1)).alias("outputs")).withColumn("accuracy", _ratio(F.col("right"), F.col("outputs")))


def multiplier(costs: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    """claim_id, without, all -> geometric mean of the ratios; claims that cost nothing are counted apart."""
    ok = (F.col("all") > 0) & (F.col("without") > 0)
    return costs.groupBy(*by).agg(F.exp(F.avg(F.when(ok, F.log(F.col("without") / F.col("all"))))).alias("multiplier"), F.count_if(~ok).alias("excluded"))


def cache_gain(costs: DataFrame) -> DataFrame:
    return costs.agg(_ratio(F.sum("without"), F.sum("all")).alias("gain"), F.count_if(F.col("all") == 0).alias("free"))


def agreement(df: DataFrame, a: str = "human", b: str = "machine") -> DataFrame:
    """Exact match and the chance-corrected agreement of two raters."""
    n = df.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col(a) == F.col(b)).alias("same"))
    left = df.groupBy(F.col(a).alias("answer")).agg(F.count(F.lit(1)).alias("na"))
    right = df.groupBy(F.col(b).alias("answer")).agg(F.count(F.lit(1)).alias("nb"))
    chance = left.join(right, "answer").agg(F.coalesce(F.sum(F.col("na") * F.col("nb")), F.lit(0)).alias("ab"))
    # both sides are one row
    j = n.join(F.broadcast(chance), how="cross").withColumn("exact", _ratio(F.col("same"), F.col("n"))).withColumn("by_chance", _ratio(F.col("ab"), F.col("n") * F.col("n")))
    return j.select("n", "same", "exact", ((F.col("exact") - F.col("by_chance")) / (1 - F.col("by_chance"))).alias("kappa"))


def wilson(x: Column, n: Column, z: float = 1.959963984540054) -> tuple[Column, Column]:
    p, zz = x / n, z * z
    mid, half = (p + zz / (2 * n)) / (1 + zz / n), z * F.sqrt(p * (1 - p) / n + zz / (4 * n * n)) / (1 + zz / n)
    return mid - half, mid + half


def stratified(df: DataFrame, per_op: int = 4, seed: int = 0) -> DataFrame:
    """per_op decisions of each operator, as many of each answer as there are."""
    turn = F.row_number().over(Window.partitionBy("op_id", "answer").orderBy(F.xxhash64(F.lit(seed), F.col("tid")), "tid"))
    both = df.withColumn("_t", turn)
    pick = F.row_number().over(Window.partitionBy("op_id").orderBy("_t", "answer", "tid"))
    return both.filter(F.col("_t") <= per_op).withColumn("_p", pick).filter(F.col("_p") <= per_op).drop("_t", "_p")
