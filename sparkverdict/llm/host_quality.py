"""Host-level quality rules: documents fail simple text rules, hosts are judged by a shrunk failure rate, documents inherit it.

The whole path is DataFrame functions. One row needs no other row for its text rules, so texts are never shuffled; only
the narrow rule rows are written to the shared folder, aggregated by host and joined back.

Defined cases: null text has no words and so fails the word minimum; a null host forms no host and gets no verdict (its
documents are kept unless they fail themselves); a rate of exactly the limit fails its host; repeated rows count once each;
very long texts are taken whole, in memory and time about linear in their words; an empty table gives an empty result;
extra columns of the input are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkverdict.llm.common import materialise, words

WINDOW = 8
SALTS = 64
SYMBOLS = r"[#*$%&|<>]"


@dataclass(frozen=True)
class HostRules:
    min_words: int = 20
    max_repeat_percent: int = 30
    #: A host is rejected when its shrunk failure rate reaches this share.
    reject_rate: float = 0.5


def _shifted_mix(col: str, by: int) -> Column:
    """hash(i) := mix(hash(i), hash(i + by)); the tail mixes with null and is cut off later."""
    return F.zip_with(F.col(col), F.slice(F.col(col), by + 1, F.greatest(F.size(col), F.lit(1))), lambda a, b: F.xxhash64(a, b))


def rule_rows(docs: DataFrame, host: str = "source", rules: HostRules = HostRules()) -> DataFrame:
    """One narrow row per document: doc_id, host, the measures and base_failed."""
    text = F.coalesce(F.col("text"), F.lit(""))
    df = docs.select("doc_id", F.col(host).alias("host"), text.alias("t"), words(F.col("text")).alias("w"))
    lines = F.filter(F.split("t", "\n"), lambda x: F.length(F.btrim(x, F.lit(" \t\n\x0b\x0c\r"))) > 0)
    df = df.select(
        "doc_id", "host",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.regexp_count("t", F.lit(SYMBOLS)).cast("long").alias("n_symbols"),
        lines.alias("lines"),
        F.transform("w", lambda x: F.xxhash64(x)).alias("h1"),
    )
    df = df.select("*", (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines")).drop("lines")
    # windows of 8 words by doubling: 1 -> 2 -> 4 -> 8
    for i, (src, by) in enumerate((("h1", 1), ("h2", 2), ("h4", 4))):
        df = df.withColumn(f"h{2 ** (i + 1)}", _shifted_mix(src, by)).drop(src)
    df = df.withColumn("win", F.slice("h8", 1, F.greatest(F.size("h8") - (WINDOW - 1), F.lit(0)))).drop("h8")
    repeats = F.size("win") > F.size(F.array_distinct("win"))
    # only texts with a repeated window pay for the sort
    df = df.withColumn("pairs", F.when(repeats, F.sort_array(F.transform("win", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))).drop("win")
    hit = F.transform(
        F.col("pairs"),
        lambda x, k: F.when(
            (F.get(F.col("pairs"), k - 1)["h"] == x["h"]) | (F.get(F.col("pairs"), k + 1)["h"] == x["h"]), x["i"]
        ),
    )
    df = df.withColumn("at", F.sort_array(F.array_compact(hit))).drop("pairs")
    covered = F.aggregate(
        "at",
        F.struct(F.lit(0).alias("n"), F.lit(0).alias("end")),
        lambda acc, p: F.struct((acc["n"] + p + WINDOW - F.greatest(acc["end"], p)).alias("n"), (p + WINDOW).alias("end")),
        lambda acc: acc["n"],
    )
    df = df.withColumn("n_repeat_words", F.coalesce(covered, F.lit(0)).cast("long")).drop("at")
    failed = (F.col("n_words") < rules.min_words) | (100 * F.col("n_repeat_words") > rules.max_repeat_percent * F.col("n_words"))
    return df.withColumn("base_failed", failed)


def host_verdicts(rows: DataFrame, rules: HostRules = HostRules()) -> DataFrame:
    """host, docs, failures, shrunk rate and verdict. The beta prior comes from the hosts themselves (beta-binomial moments)."""
    hosts = rows.filter(F.col("host").isNotNull()).groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("base_failed").cast("long")).alias("bad"))
    n, p = F.col("total"), F.col("mean")
    overall = hosts.agg(F.sum("n").alias("total"), F.sum("bad").alias("bads"), F.count(F.lit(1)).alias("m"), F.sum((F.col("n") * F.col("n")).cast("double")).alias("sq"), F.sum(F.col("bad") * F.col("bad") / F.col("n")).alias("bad2"))
    overall = overall.withColumn("mean", F.col("bads") / F.col("total"))
    # sum n (r - p)^2 = sum bad^2/n - p * sum bad
    spread = F.col("bad2") - p * F.col("bads")
    noise = p * (1 - p)
    room = n - F.col("sq") / n - (F.col("m") - 1)
    rho = F.when((noise > 0) & (room > 0), (spread - noise * (F.col("m") - 1)) / (noise * room)).otherwise(F.lit(0.0))
    overall = overall.select(p.alias("mean"), F.least(F.greatest(rho, F.lit(1e-4)), F.lit(0.9999)).alias("rho"))
    overall = overall.select((F.col("mean") * (1 / F.col("rho") - 1)).alias("alpha"), (1 / F.col("rho") - 1).alias("strength"))
    # overall is one row (an aggregate without keys), the only broadcast that is asked for
    rated = hosts.join(F.broadcast(overall), how="cross").withColumn("rate", (F.col("bad") + F.col("alpha")) / (F.col("n") + F.col("strength")))
    return rated.select("host", "n", "bad", "rate", (F.col("rate") >= rules.reject_rate).alias("host_failed"))


def apply_host_rules(docs: DataFrame, host: str = "source", rules: HostRules = HostRules()) -> DataFrame:
    rows = materialise(rule_rows(docs, host, rules), "host-rules")
    # a host may have a third of all rows: its one verdict is copied SALTS times and its rows are spread over the copies
    verdicts = host_verdicts(rows, rules).filter("host_failed").select("host", "host_failed", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    spread = rows.withColumn("salt", F.pmod(F.xxhash64("doc_id", "n_words", "word_chars"), F.lit(SALTS)).cast("int"))
    joined = spread.join(verdicts, ["host", "salt"], "left").withColumn("host_failed", F.coalesce("host_failed", F.lit(False)))
    return joined.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed",
        (~F.col("base_failed") & ~F.col("host_failed")).alias("kept"), "host_failed",
    )
