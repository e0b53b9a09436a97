"""The main experiment from runs: every claim by every engine, tier and seed, in a run log, and the measures over it.

The log is made once per application and tables, in the shared folder: a row per claim, engine, tier and seed. One pass of
the engine serves all tiers and seeds of a claim (`verify_each`); claims are independent jobs, a few at a time. The log grows
with claims and configurations, never with the data. Expected verdicts are those of the columns.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkverdict import workloads
from sparkverdict.operators import metrics, provenance
from sparkverdict.operators.confseq import BUDGETS, budget_shares, truth_refuted
from sparkverdict.operators.engine import tuple_id, verify_each
from sparkverdict.operators.models import ACCURACY, PRICES, RuleModel, SemanticModel, tier
from sparkverdict.plans.claims import Claim, Nested, Quantified, RankIs, evaluate
from sparkverdict.plans.optimizer import VerifyOptions, plan
from sparkverdict.session import scratch, ship_package, written
from sparkverdict.sources.relations import base, relation, relation_sql

Query = Callable[[SparkSession, str], DataFrame]
Q: dict[str, Query] = {}
SQL: dict[str, str] = {}
SEEDS = (0, 1, 2)
#: Engines and the tiers that they run with.
ENGINES = {"naive": "ABC", "optimized": "ABCDE"}
#: Claims that run at the same time; each is a chain of short jobs.
AT_ONCE = 8
#: The switches that verify() reads; the prompt cache that lasts from run to run is replayed by metric_a12.
SWITCHES = ("early_stop", "relevance", "estimate", "fusion", "similarity", "cache")
LOG = "claim_id string, engine string, tier string, seed int, verdict boolean, expected boolean, seen long, calls long, tokens_in long, tokens_out long, settled_by string"
_made: dict[tuple, DataFrame] = {}


def _options(engine: str) -> VerifyOptions:
    return VerifyOptions.none() if engine == "naive" else VerifyOptions.all()


def each_claim(spark: SparkSession, sf_dir: str, names: tuple[str, ...], run: Callable[[Claim, DataFrame], list[tuple]]) -> list[tuple]:
    """run() over all named claims, their relations assembled once each. What a claim writes on its way goes with it."""
    claims = workloads.benchmark()
    wanted = sorted({claims[n].relation for n in names})
    # given tables are read where they are; no claim looks into the list of turns
    frames = {r: base(spark, sf_dir, r) if r in ("documents", "events", "lineitem", "pages") else written(relation(spark, sf_dir, r).drop("turns"), f"relation-{r}") for r in wanted}

    def one(name: str) -> list[tuple]:
        with scratch(spark):
            return run(claims[name], frames[claims[name].relation])

    ship_package(spark)
    with ThreadPoolExecutor(AT_ONCE) as pool:
        parts = list(pool.map(one, names))
    return [row for part in parts for row in part]


def run_log(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(workloads.benchmark()), seeds: tuple[int, ...] = SEEDS) -> DataFrame:
    """claim x engine x tier x seed, see LOG."""
    key = (spark.sparkContext.applicationId, sf_dir, names, seeds)
    if key in _made:
        return _made[key]

    def one(claim: Claim, df: DataFrame) -> list[tuple]:
        expected = bool(evaluate(claim, df).first()["verdict"])
        rows = []
        for engine, tiers in ENGINES.items():
            trials = [(t, s) for t in tiers for s in seeds]
            models: list[SemanticModel] = [tier(t, s) for t, s in trials]
            with scratch(spark):
                for (t, s), r in zip(trials, verify_each(claim, df, _options(engine), models), strict=True):
                    rows.append((claim.claim_id, engine, t, s, bool(r.verdict), expected, r.seen, r.calls, r.tokens_in, r.tokens_out, r.settled_by))
        return rows

    _made[key] = written(spark.createDataFrame(each_claim(spark, sf_dir, names, one), LOG).coalesce(1), "run-log")
    return _made[key]


def _usd() -> Column:
    """Dollars of a row of the log, by its tier's list price."""
    out = F.lit(None).cast("double")
    for t, (a, b) in PRICES.items():
        out = F.when(F.col("tier") == t, (F.col("tokens_in") * a + F.col("tokens_out") * b) / 1e6).otherwise(out)
    return out


def _configured(log: DataFrame) -> DataFrame:
    return log.withColumn("config", F.concat_ws("-", "engine", "tier")).withColumn("usd", _usd())


def main_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per configuration, over three trials: mean, least and greatest of precision, recall, F1, accuracy, and of dollars and calls a claim."""
    rows = _configured(run_log(spark, sf_dir))
    quality = metrics.verification(rows, ("config", "seed"))
    spent = rows.groupBy("config", "seed").agg(F.avg("usd").alias("usd"), F.avg("calls").alias("calls"))
    both = quality.join(spent, ["config", "seed"])
    out = None
    for value in ("precision", "recall", "f1", "accuracy", "usd", "calls"):
        one = metrics.trials(both, value, ("config",)).select("config", F.lit(value).alias("measure"), *[F.round(c, 9).alias(c) for c in ("mean", "low", "high")])
        out = one if out is None else out.union(one)
    return out


def heat_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Right trials of three, per claim and configuration."""
    configs = [f"{e}-{t}" for e, tiers in ENGINES.items() for t in tiers]
    return metrics.heat(_configured(run_log(spark, sf_dir)), configs).select("claim_id", *[F.coalesce(F.col(f"`{c}`"), F.lit(0)).alias(c.replace("-", "_")) for c in configs])


def _points(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _configured(run_log(spark, sf_dir))
    return metrics.verification(rows, ("config",)).select("config", "f1").join(rows.groupBy("config").agg(F.avg("usd").alias("cost")), "config")


def frontier(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Configurations that no other beats in F1 and dollars a claim."""
    return metrics.pareto(_points(spark, sf_dir)).select("config", F.round("f1", 9).alias("f1"), F.round("cost", 9).alias("cost"))


def ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Naive over optimized dollars, per tier that both ran with."""
    rows = _configured(run_log(spark, sf_dir)).groupBy("tier", "engine").agg(F.sum("usd").alias("usd"), F.sum("calls").alias("calls"))
    side = lambda e, c: F.max(F.when(F.col("engine") == e, F.col(c)))
    out = rows.groupBy("tier").agg((side("naive", "usd") / side("optimized", "usd")).alias("usd_ratio"), (side("naive", "calls") / side("optimized", "calls")).alias("call_ratio"))
    return out.filter("usd_ratio IS NOT NULL").select("tier", F.round("usd_ratio", 9).alias("usd_ratio"), F.round("call_ratio", 9).alias("call_ratio"))


QUALITY = "claim_id string, engine string, tier string, outputs long, right long, tp long, fp long, fn long, returned long, confirmed long"


def quality_log(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(workloads.benchmark())) -> DataFrame:
    """Per run of an ungrouped claim: outputs of its map and the right ones, the semantic filter's selections among the rows
    it saw, cited tokens and those whose sign the columns confirm. A row per claim, engine and tier."""
    claims = workloads.benchmark()
    flat = tuple(n for n in names if isinstance(claims[n].form, Quantified))
    key = (spark.sparkContext.applicationId, sf_dir, flat, "quality")
    if key in _made:
        return _made[key]

    def one(claim: Claim, df: DataFrame) -> list[tuple]:
        inside = claim.semantic_scope.safe() if claim.semantic_scope is not None else F.lit(True)
        true = df.select(tuple_id(claim.relation).alias("tid"), inside.alias("inside"), claim.form.phi.safe().alias("true"))
        rows = []
        for engine, tiers in ENGINES.items():
            done = dict(zip(tiers, verify_each(claim, df, _options(engine), [tier(t, SEEDS[0]) for t in tiers]), strict=True))
            said = reduce(DataFrame.union, [r.processed.withColumn("tier", F.lit(t)) for t, r in done.items()]).join(true, "tid")
            filtered = F.lit(claim.semantic_scope is not None)
            maps = said.groupBy("tier").agg(
                F.count_if("keep").alias("outputs"), F.count_if(F.col("keep") & (F.col("hit") == F.col("true"))).alias("right"),
                F.count_if(filtered & F.col("keep") & F.col("inside")).alias("tp"), F.count_if(filtered & F.col("keep") & ~F.col("inside")).alias("fp"), F.count_if(filtered & ~F.col("keep") & F.col("inside")).alias("fn"),
            )
            cited = reduce(DataFrame.union, [provenance.cite_run(claim, r).select("tuple_id", "sign").withColumn("tier", F.lit(t)) for t, r in done.items()])
            sign = F.when(F.col("true"), 1).otherwise(-1)
            tokens = cited.join(true, F.col("tuple_id") == F.col("tid")).groupBy("tier").agg(F.count(F.lit(1)).alias("returned"), F.count_if(F.col("sign") == sign).alias("confirmed"))
            # a row per tier
            for r in maps.join(tokens, "tier", "full").na.fill(0).collect():
                rows.append((claim.claim_id, engine, r["tier"], r["outputs"], r["right"], r["tp"], r["fp"], r["fn"], r["returned"], r["confirmed"]))
        return rows

    _made[key] = written(spark.createDataFrame(each_claim(spark, sf_dir, flat, one), QUALITY).coalesce(1), "quality-log")
    return _made[key]


def operator_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per configuration, pooled over the runs: accuracy of maps, precision, recall and F1 of filters, precision of citations."""
    total = quality_log(spark, sf_dir).groupBy(F.concat_ws("-", "engine", "tier").alias("config")).agg(*[F.sum(c).alias(c) for c in ("outputs", "right", "tp", "fp", "fn", "returned", "confirmed")])
    scored = metrics.scores(total.withColumn("tn", F.lit(0)))
    return scored.select(
        "config", "outputs", F.round(F.try_divide("right", "outputs"), 9).alias("map_accuracy"), *[F.round(c, 9).alias(f"filter_{c}") for c in ("precision", "recall", "f1")],
        "returned", F.round(F.try_divide("confirmed", "returned"), 9).alias("citation_precision"),
    )


def settled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How the optimized runs ended, and the share of the naive engine's calls that they made."""
    rows = run_log(spark, sf_dir).filter("tier IN ('A', 'B', 'C')")
    naive = rows.filter("engine = 'naive'").select("claim_id", "tier", "seed", F.col("calls").alias("naive_calls"))
    both = rows.filter("engine = 'optimized'").join(naive, ["claim_id", "tier", "seed"])
    return both.groupBy("settled_by").agg(F.count(F.lit(1)).alias("runs"), F.count_if(F.col("verdict") == F.col("expected")).alias("right"), F.round(F.sum("calls") / F.sum("naive_calls"), 9).alias("call_share"))


def applicable(claim: Claim) -> list[str]:
    """Switches that change how the claim runs; without any other the run would be the same."""
    full = plan(claim, VerifyOptions.all())
    what = lambda p: (p.calls_per_row, p.size_known, p.inner_order, p.outer_order, p.similarity, p.stops)
    return [off for off in SWITCHES if off == "cache" or what(plan(claim, VerifyOptions.all().without(off))) != what(full)]


def ablation(spark: SparkSession, sf_dir: str, names: tuple[str, ...] = tuple(workloads.benchmark())) -> DataFrame:
    """claim x switched-off optimization that its run uses: calls and verdict with everything on and without it."""
    key = (spark.sparkContext.applicationId, sf_dir, names, "ablation")
    if key in _made:
        return _made[key]

    def one(claim: Claim, df: DataFrame) -> list[tuple]:
        expected = bool(evaluate(claim, df).first()["verdict"])
        full = verify_each(claim, df, VerifyOptions.all(), [RuleModel()])[0]
        rows = []
        for off in applicable(claim):
            less = verify_each(claim, df, VerifyOptions.all().without(off), [RuleModel()])[0]
            rows.append((claim.claim_id, off, less.calls, full.calls, less.verdict == expected, full.verdict == expected))
        return rows

    schema = "claim_id string, off string, without long, `all` long, right_without boolean, right_all boolean"
    _made[key] = written(spark.createDataFrame(each_claim(spark, sf_dir, names, one), schema).coalesce(1), "ablation")
    return _made[key]


def multipliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per switch: geometric mean of the factors in calls, and the change in accuracy when it is off."""
    rows = ablation(spark, sf_dir)
    delta = rows.groupBy("off").agg(F.count(F.lit(1)).alias("claims"), F.round(F.avg(F.col("right_without").cast("int")) - F.avg(F.col("right_all").cast("int")), 9).alias("accuracy_change"))
    return metrics.multiplier(rows, ("off",)).withColumn("multiplier", F.round("multiplier", 9)).join(delta, "off")


# --- the naive engine's calls, which SQL can count ---
def _phi(claim: Claim):
    form = claim.form
    while isinstance(form, Nested):
        form = form.inner
    return [form.phi] if isinstance(form, RankIs) else [p for _, p in form.tallies]


def naive_calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Calls of the naive engine: a filter's call for each row, then one per test for each row that it keeps."""

    def one(claim: Claim, df: DataFrame) -> list[tuple]:
        return [(claim.claim_id, verify_each(claim, df, VerifyOptions.none(), [RuleModel()])[0].calls)]

    return spark.createDataFrame(each_claim(spark, sf_dir, tuple(workloads.benchmark()), one), "claim_id string, calls long")


def _naive_calls_sql(claim: Claim) -> str:
    tests = len({p.name.removeprefix("not_") for p in _phi(claim)})
    where = f"WHERE coalesce({claim.scope.sql}, false)" if claim.scope else ""
    calls = f"{tests} * count(*)" if claim.semantic_scope is None else f"count(*) + {tests} * count(*) FILTER (coalesce({claim.semantic_scope.sql}, false))"
    return f"SELECT '{claim.claim_id}' AS claim_id, ({calls})::BIGINT AS calls FROM {relation_sql(claim.relation)} AS src {where}"


# --- seeded trials of the intervals themselves ---
ALPHA = 0.05
#: Rows of a pool on average, and the seeded streams and families that each pool gives.
POOL, STREAMS, FAMILIES = 1_000, 40, 10
MEANS = (0.02, 0.1, 0.3, 0.5, 0.95)


def pooled(spark: SparkSession, sf_dir: str, run: Callable, schema: str) -> DataFrame:
    """run(pool's number, u) over every event, dealt by a hash into pools of about POOL rows; u is user_id modulo 100 in the
    order of event_id, so that u < 100 * m is a test that about the share m of the rows passes; events without a user have no
    outcome. A task holds one pool at a time."""
    ship_package(spark)
    events = base(spark, sf_dir, "events").select("event_id", F.pmod("user_id", F.lit(100)).cast("int").alias("u")).filter("u IS NOT NULL")
    pools = max(1, events.count() // POOL)
    dealt = events.withColumn("pool", F.pmod(F.xxhash64("event_id", F.lit(17)), F.lit(pools)))

    def each(key, frame):
        return run(int(key[0]), frame.sort_values("event_id")["u"].to_numpy())

    return dealt.groupBy("pool").applyInPandas(each, schema)


def _added(got: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    return got.groupBy(*keys).agg(F.sum("trials").alias("trials"), F.sum("missed").alias("missed")).withColumn("share", F.round(F.col("missed") / F.col("trials"), 9))


def stream_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seeded streams of 500 to 800 rows of each pool of events, drawn with and without replacement, of which the pool's own
    share is ever refuted at alpha = .05."""

    def run(pool: int, u: np.ndarray) -> pd.DataFrame:
        out = []
        for n, m in enumerate(MEANS):
            hit = u < 100 * m
            for kind in ("with", "without"):
                rng = np.random.default_rng((17, pool, n, kind == "with"))
                rows = min(len(hit), int(rng.integers(500, 801)))
                bits = hit[rng.integers(0, len(hit), (STREAMS, rows))] if kind == "with" else rng.permuted(np.tile(hit, (STREAMS, 1)), axis=1)[:, :rows]
                out.append((m, kind, STREAMS, int(truth_refuted(ALPHA, bits, hit.mean(), None if kind == "with" else len(hit)).sum())))
        return pd.DataFrame(out, columns=["mean", "kind", "trials", "missed"])

    return _added(pooled(spark, sf_dir, run, "mean double, kind string, trials long, missed long"), ("mean", "kind"))


def family_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Families of groups, each group a test of its own over a pool of events with its share of alpha: families in which any
    interval can ever miss."""

    def run(pool: int, u: np.ndarray) -> pd.DataFrame:
        out = []
        for m in (4, 20):
            for kind in ("with", "without"):
                rng = np.random.default_rng((18, pool, m, kind == "with"))
                missed = dict.fromkeys(BUDGETS, 0)
                for _ in range(FAMILIES):
                    hit = u[None, :] < rng.integers(0, 101, m)[:, None]
                    rows = min(300, len(u))
                    bits = np.take_along_axis(hit, rng.integers(0, len(u), (m, rows)), axis=1) if kind == "with" else rng.permuted(hit, axis=1)[:, :rows]
                    for budget in BUDGETS:
                        missed[budget] += bool(truth_refuted(np.asarray(budget_shares(ALPHA, budget, m)), bits, hit.mean(axis=1), None if kind == "with" else len(u)).any())
                out += [(budget, m, kind, FAMILIES, n) for budget, n in missed.items()]
        return pd.DataFrame(out, columns=["budget", "groups", "kind", "trials", "missed"])

    return _added(pooled(spark, sf_dir, run, "budget string, groups int, kind string, trials long, missed long"), ("budget", "groups", "kind"))


Q |= {"metric_quality": operator_quality, "metric_quality_log": quality_log, "metric_a17_streams": stream_coverage, "metric_a17_family": family_coverage}
Q |= {
    "metric_main": main_table, "metric_heat": heat_map, "metric_frontier": frontier, "metric_ratio": ratios, "metric_settled": settled, "metric_run_log": run_log,
    "metric_a11": ablation, "metric_a11_multiplier": multipliers, "metric_naive_calls": naive_calls,
}
SQL["metric_naive_calls"] = " UNION ALL ".join(_naive_calls_sql(c) for c in workloads.benchmark().values())


def queries() -> dict[str, Query]:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
