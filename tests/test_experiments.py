"""Experiments run over the whole benchmark."""

from __future__ import annotations

import duckdb
import pandas as pd
import pytest

from sparkverdict import experiments, trials, workloads
from sparkverdict.operators.engine import verify, verify_each
from sparkverdict.operators.models import ACCURACY, RuleModel, tier
from sparkverdict.plans.optimizer import VerifyOptions
from sparkverdict.sources.relations import relation


@pytest.mark.parametrize("name", ["agent_all", "program_sample", "program_scan_all", "program_iterate"])
def test_baselines_answer_every_claim(spark, sf_dir, name):
    got = {r.claim_id: tuple(r) for r in experiments.Q[name](spark, sf_dir).collect()}
    assert set(got) == set(workloads.benchmark())
    if name in experiments.SQL:
        con = duckdb.connect()
        for t in ("documents", "conversations"):
            con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
        assert sorted(got.values()) == sorted(con.sql(experiments.SQL[name]).fetchall())


def test_ablation_covers_what_runs_use(spark, sf_dir):
    offs = {n: trials.applicable(c) for n, c in workloads.benchmark().items()}
    assert {x for found in offs.values() for x in found} == set(trials.SWITCHES)
    assert offs["c08"] and {"fusion", "similarity"} <= set(offs["c03"]) and "fusion" in offs["c09"]
    some = trials.ablation(spark, sf_dir, ("c02", "c03")).collect()
    assert {(r.claim_id, r.off) for r in some} == {(n, x) for n in ("c02", "c03") for x in offs[n]}
    assert {r.off: r.without > r["all"] for r in some if r.claim_id == "c03"}["similarity"]


def test_models_run_together_as_alone(spark, sf_dir):
    """Every way to run a claim gives each of several models what it gets alone."""
    models = [tier("E", 1), RuleModel()]
    for name, options in (("c13", VerifyOptions.all()), ("c08", VerifyOptions.all()), ("c08", VerifyOptions.none()), ("c09", VerifyOptions.none()), ("c13", VerifyOptions.none())):
        claim = workloads.benchmark()[name]
        df = relation(spark, sf_dir, claim.relation).coalesce(1)
        for model, got in zip(models, verify_each(claim, df, options, models), strict=True):
            alone = verify(claim, df, options, model)
            assert (got.verdict, got.seen, got.hits, got.calls, got.tokens_in, got.overshoot, got.settled_by) == (alone.verdict, alone.seen, alone.hits, alone.calls, alone.tokens_in, alone.overshoot, alone.settled_by), (name, model)


def test_main_table_is_the_log_counted(spark, sf_dir):
    names = ("c02", "c08", "c13", "c25")
    log = [r.asDict() for r in trials.run_log(spark, sf_dir, names).collect()]
    assert len(log) == len(names) * 3 * (3 + 5)
    run, trials.run_log = trials.run_log, lambda s, d: run(s, d, names)
    try:
        table = {(r.config, r.measure): r for r in trials.main_table(spark, sf_dir).collect()}
        heat = {r.claim_id: r.asDict() for r in trials.heat_map(spark, sf_dir).collect()}
    finally:
        trials.run_log = run
    for engine, tier_ in (("naive", "A"), ("optimized", "E")):
        by_seed = [[r for r in log if r["engine"] == engine and r["tier"] == tier_ and r["seed"] == s] for s in trials.SEEDS]
        accuracy = [sum(r["verdict"] == r["expected"] for r in rows) / len(rows) for rows in by_seed]
        calls = [sum(r["calls"] for r in rows) / len(rows) for rows in by_seed]
        got, cost = table[f"{engine}-{tier_}", "accuracy"], table[f"{engine}-{tier_}", "calls"]
        assert (got.low, got.high) == (min(accuracy), max(accuracy)) and cost.mean == pytest.approx(sum(calls) / 3)
        for n in names:
            assert heat[n][f"{engine}_{tier_}"] == sum(r["verdict"] == r["expected"] for rows in by_seed for r in rows if r["claim_id"] == n)
    total = lambda e: sum(r["calls"] for r in log if r["engine"] == e and r["tier"] == "A")
    assert total("optimized") < total("naive")


def test_quality_is_counted_from_the_runs(spark, sf_dir):
    """The naive engine answers all rows of the scope and as often right as its tier; cited tokens are rows that it saw."""
    rows = {(r["claim_id"], r["engine"], r["tier"]): r for r in trials.quality_log(spark, sf_dir, ("c03", "c13")).collect()}
    assert len(rows) == 2 * (3 + 5)
    docs = relation(spark, sf_dir, "documents")
    for (name, engine, tier), r in rows.items():
        claim = workloads.benchmark()[name]
        scoped = docs.filter(claim.scope.safe()) if claim.scope else docs
        assert r["right"] <= r["outputs"] and r["confirmed"] <= r["returned"] <= r["outputs"]
        if claim.semantic_scope is None:
            assert r["tp"] == r["fp"] == r["fn"] == 0
        else:
            assert r["outputs"] == r["tp"] + r["fp"]
        if engine == "naive" and name == "c13":
            assert r["outputs"] == scoped.count() and abs(r["right"] / r["outputs"] - ACCURACY[tier]) < 0.08


def test_silent_keys_are_closed_and_late_rows_dropped(spark, sf_dir):
    found = experiments.queries()
    con = duckdb.connect()
    con.sql(f"CREATE VIEW events AS SELECT * FROM read_parquet('{sf_dir}/events.parquet')")
    for name in ("stream_late", "stream_monitor_timer"):
        df = found[name](spark, sf_dir)
        want = con.sql(f"SELECT {', '.join(df.columns)} FROM ({experiments.oracle_sql()[name]})").fetchall()
        assert want and sorted(map(tuple, df.collect())) == sorted(want), name


@pytest.mark.parametrize("first, last", [("2024-01-01 00:00:00.2", "2024-01-30 23:59:59.7"), ("2024-01-01 00:00:11", "2024-01-31 00:00:30")])
def test_late_stream_cuts_at_the_middle_with_few_newest_rows(spark, tmp_path, first, last):
    """Fractions of seconds count for the middle; a last day of one row is still a batch of its own."""
    con = duckdb.connect()
    con.sql(
        f"""COPY (SELECT i AS event_id, CASE i WHEN 0 THEN TIMESTAMP '{first}' WHEN 899 THEN TIMESTAMP '{last}' ELSE TIMESTAMP '2024-01-01 01:00:00' + to_hours((i % 29) * 24 + i % 22) END AS ts,
         i % 7 AS user_id, 'k' || (i % 3) AS event_type, 1.0 AS value, '' AS props FROM range(900) t(i)) TO '{tmp_path}/events.parquet' (FORMAT parquet)"""
    )
    con.sql(f"CREATE VIEW events AS SELECT * FROM read_parquet('{tmp_path}/events.parquet')")
    df = experiments.queries()["stream_late"](spark, str(tmp_path))
    want = con.sql(f"SELECT {', '.join(df.columns)} FROM ({experiments.oracle_sql()['stream_late']})").fetchall()
    assert want and sorted(map(tuple, df.collect())) == sorted(want)


def test_a_log_leaves_no_tables_of_its_runs(spark, sf_dir):
    """What a claim writes goes with it, and a grouped claim's rows are dealt out once for all models."""
    from pathlib import Path

    from sparkverdict.session import shared_dir

    folder = Path(shared_dir(spark).removeprefix("file://"), "sparkverdict")
    before = set(folder.glob("*"))
    log = trials.run_log(spark, sf_dir, ("c03", "c05", "c13"), (0, 1))
    assert {p.name.split("-")[0] for p in set(folder.glob("*")) - before} == {"run"} and log.count() == 3 * 8 * 2


@pytest.mark.parametrize("name", ["metric_a14", "metric_a7", "metric_a7_ratio"])
def test_measures_read_a_given_table(spark, sf_dir, name):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{sf_dir}/documents.parquet')")
    df = experiments.queries()[name](spark, sf_dir)
    want = con.sql(f"SELECT {', '.join(df.columns)} FROM ({experiments.oracle_sql()[name]})").fetchall()
    assert want and sorted(map(tuple, df.collect())) == sorted(want)
    assert any(f.endswith("documents.parquet") for f in df.inputFiles())


def test_interval_trials_take_their_streams_from_events(spark, tmp_path):
    """Every event is in one pool; the trials grow with the table, and intervals miss in at most about alpha of them."""
    spark.range(3000).selectExpr("id AS event_id", "id * 7 % 1000 AS user_id").coalesce(1).write.parquet(f"{tmp_path}/events.parquet")
    rows = {(r["mean"], r["kind"]): r for r in trials.stream_coverage(spark, str(tmp_path)).collect()}
    assert len(rows) == 10 and {r.trials for r in rows.values()} == {3 * trials.STREAMS} and all(r.share < 0.12 for r in rows.values())
    families = trials.family_coverage(spark, str(tmp_path)).collect()
    assert len(families) == 12 and {r.trials for r in families} == {3 * trials.FAMILIES}
    seen = trials.pooled(spark, str(tmp_path), lambda pool, u: pd.DataFrame({"n": [len(u)], "s": [int(u.sum())]}), "n long, s long").collect()
    assert sum(r.n for r in seen) == 3000 and sum(r.s for r in seen) == sum(i * 7 % 1000 % 100 for i in range(3000))
    assert {r["mean"] for r in experiments.queries()["metric_a17"](spark, str(tmp_path)).collect()} == {0.02, 0.3, 0.95}
