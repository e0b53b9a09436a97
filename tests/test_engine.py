"""The engine against plain aggregates: any order, wave or option that is certain gives the same verdict, with fewer calls."""

from __future__ import annotations

import math
from dataclasses import replace
from fractions import Fraction

import duckdb
import pytest
from pyspark.sql import functions as F

from sparkverdict import workloads
from sparkverdict.functions import truth
from sparkverdict.operators import provenance, relevance
from sparkverdict.operators.cache import PromptCache, answers
from sparkverdict.operators.engine import verify
from sparkverdict.operators.models import RuleModel
from sparkverdict.operators.ranking import global_position
from sparkverdict.plans.claims import EXISTS, FORALL, Claim, Nested, Quantified, claim_sql, count, evaluate, share
from sparkverdict.plans.optimizer import VerifyOptions
from sparkverdict.sources.relations import base, relation, relation_sql


@pytest.mark.parametrize("name", ["c01", "c02", "c05", "c08", "c13", "c16", "c17", "c21", "c23", "c25"])
def test_certain_options_agree_with_the_aggregate(spark, sf_dir, name):
    claim = workloads.benchmark()[name]
    df = relation(spark, sf_dir, claim.relation)
    want = bool(evaluate(claim, df).first()["verdict"])
    fast = verify(claim, df, VerifyOptions.exact())
    slow = verify(claim, df, VerifyOptions.none())
    assert fast.verdict == slow.verdict == want and fast.calls <= slow.calls + 32
    for seed, batch in ((1, 8), (2, 64)):
        assert verify(claim, df, VerifyOptions(estimate=False, similarity=False, seed=seed, batch=batch)).verdict == want


def test_claims_equal_their_sql(spark, sf_dir):
    con = duckdb.connect()
    for t in ("documents", "conversations", "events", "lineitem", "customer", "nation", "region", "pages"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    for claim in workloads.all_claims().values():
        got = evaluate(claim, relation(spark, sf_dir, claim.relation)).first()
        assert tuple(got) == con.sql(claim_sql(claim, relation_sql(claim.relation))).fetchall()[0], claim.claim_id


def test_witness_order_and_overshoot(spark):
    rows = [(i, "a licence: licensed" if i == 777 else "nothing here", "en", 12) for i in range(1000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, n_chars long")
    claim = Claim("w", "documents", Quantified(EXISTS, truth.lic))
    found = verify(claim, df, replace(VerifyOptions.exact(), cache=False))
    assert found.verdict and found.seen == 1 and found.calls == 32 and found.tokens == [(None, 777, 1)]
    cached = verify(claim, df, VerifyOptions.exact())  # the other 31 rows of the wave are one prompt
    assert cached.seen == 1 and cached.overshoot == 31 and cached.calls == 2
    plain = verify(claim, df, VerifyOptions(relevance=False, estimate=False))
    assert plain.verdict and plain.seen == 778
    never = verify(Claim("n", "documents", Quantified(count(">", 1), truth.lic)), df, VerifyOptions.exact())
    assert not never.verdict and never.seen <= 1000


def test_empty_and_null_relations(spark):
    df = spark.createDataFrame([], "doc_id long, text string, lang string, n_chars long")
    assert verify(Claim("e", "documents", Quantified(EXISTS, truth.lic)), df).verdict is False
    nulls = spark.createDataFrame([(1, None, "en", None)], df.schema)
    assert verify(Claim("e", "documents", Quantified(count("==", 0), truth.lic)), nulls, VerifyOptions.exact()).verdict is True


def test_rows_without_a_key_of_their_own_count(spark):
    """Null and repeated keys neither lose nor multiply rows."""
    rows = [(None if i % 3 == 0 else i % 5, "licensed" if i % 2 else "plain", "en", 9, f"g{i % 2}") for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, n_chars long, source string")
    for test, want in ((count("==", 20), True), (count(">=", 21), False), (count("<=", 20), True)):
        for options in (VerifyOptions.exact(), VerifyOptions.none()):
            got = verify(Claim("k", "documents", Quantified(test, truth.lic)), df, options)
            assert got.verdict is want and got.seen <= 40
    nested = Claim("n", "documents", Nested(EXISTS, ("source",), Quantified(count("==", 20), truth.lic)))
    assert verify(nested, df, VerifyOptions.exact()).verdict is True


def test_group_execution_and_cache_take_effect(spark):
    rows = [(i, "licensed" if i % 10 < 4 else "plain", "en", 9, f"g{i % 4}") for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, n_chars long, source string").coalesce(1)
    claim = Claim("g", "documents", Nested(FORALL, ("source",), Quantified(EXISTS, truth.lic)))
    exact = VerifyOptions(estimate=False, similarity=False, cache=False)
    by_order, by_hash = verify(claim, df, exact), verify(claim, df, replace(exact, group_exec="hash"))
    assert by_order.verdict is by_hash.verdict is True and by_order.calls == 4 and by_hash.calls == 400
    deep = Claim("d", "documents", Nested(EXISTS, ("lang",), Nested(FORALL, ("source",), Quantified(count(">=", 40), truth.lic))))
    assert verify(deep, df, exact).verdict is verify(deep, df, replace(exact, group_exec="hash")).verdict is True
    flat = Claim("f", "documents", Quantified(count("==", 160), truth.lic))
    whole, cached = verify(flat, df, VerifyOptions.none()), verify(flat, df, replace(VerifyOptions.none(), cache=True))
    assert whole.verdict is cached.verdict is True and whole.calls == 400 > cached.calls == 2


def test_budgets_by_arrival_and_counts_after_the_filter(spark, sf_dir):
    """Groups may share alpha by arrival; a filter that runs first gives the size, and the same verdict."""
    rows = [(i, "licensed" if i % 10 < 6 else "plain", "en", 9, f"g{i % 30}") for i in range(30_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, n_chars long, source string").coalesce(1)
    claim = Claim("g", "documents", Nested(count(">=", 3), ("source",), Quantified(share(">", Fraction(1, 5)), truth.lic)))
    options = VerifyOptions(cache=False)
    known, arrival = verify(claim, df, options), verify(claim, df, replace(options, budget="arrival"))
    assert known.verdict is arrival.verdict is True and arrival.plan.alpha_inner > known.plan.alpha_inner
    filtered = workloads.benchmark()["c03"]
    docs = relation(spark, sf_dir, "documents")
    want = bool(evaluate(filtered, docs).first()["verdict"])
    first = verify(filtered, docs, replace(VerifyOptions.exact(), cardinality="after_filter", cache=False))
    assert first.verdict == want and first.plan.size_known and first.size is not None
    assert first.size == docs.filter(filtered.scope.safe()).filter(filtered.semantic_scope.safe()).count()
    # every row in the scope meets the filter, only what it keeps meets the map
    assert first.calls <= docs.filter(filtered.scope.safe()).count() + first.size
    every = verify(filtered, docs.limit(0), replace(VerifyOptions.exact(), cardinality="after_filter"))
    assert every.verdict is False and every.calls == 0


def test_runs_cite_what_they_processed(spark, sf_dir):
    """Tokens come from the answers of the run: signs are right, none is beyond the point where the run stopped."""
    df = relation(spark, sf_dir, "documents")
    truth_of = {r.doc_id: bool(r.hit) for r in df.select("doc_id", truth.long.safe().alias("hit")).collect()}
    shares = [(share(">=", Fraction(1, 10)), True), (share(">=", Fraction(9, 10)), False), (share("<", Fraction(1, 10)), False), (EXISTS, True), (FORALL, False), (count(">=", 5), True)]
    for test, want in shares:
        claim = Claim("c", "documents", Quantified(test, truth.long))
        for options in (VerifyOptions(), VerifyOptions.exact(), VerifyOptions.none()):
            result = verify(claim, df, options)
            tokens = provenance.cite_run(claim, result).collect()
            assert result.verdict is want and all(truth_of[r.tuple_id] == (r.sign == 1) for r in tokens)
            yes = sum(r.sign == 1 for r in tokens)
            reached = provenance.rule(test, want, result.hits, result.seen) != (-1, -1)
            assert len({r.tuple_id for r in tokens}) == len(tokens) <= result.seen
            if test.kind == "share" and reached:
                least = test.value * result.seen
                assert yes == len(tokens) and yes == (result.hits if result.settled_by == "interval" else math.ceil(least))
            elif not reached:
                assert len(tokens) == result.seen and yes == result.hits


def test_deep_nested_citations(spark):
    rows = [(i, f"l{i % 2}", f"s{i % 6}", 3000 if i % 5 else 10, "x") for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, lang string, source string, n_chars long, text string")
    claim = Claim("d", "documents", Nested(EXISTS, ("lang",), Nested(FORALL, ("source",), Quantified(count(">=", 3), truth.long))))
    got = provenance.cite(claim, df).collect()
    assert len(got) == 9 and {r.grp for r in got} == {"l0/s0", "l0/s2", "l0/s4"} and all(r.sign == 1 for r in got)


def test_cache_asks_each_prompt_once(spark, tmp_path):
    df = spark.createDataFrame([(i, f"text {i % 4} licensed" if i % 2 else f"text {i % 4}") for i in range(40)], "doc_id long, text string")
    cache = PromptCache(spark, f"file://{tmp_path}/cache")
    first, n = answers(df, truth.lic, RuleModel(), cache)
    again, m = answers(df, truth.lic, RuleModel(), cache)
    _, other = answers(df, truth.lic, RuleModel("another"), cache)
    assert (n, m, other) == (4, 0, 4)
    assert first.filter("answer").count() == again.filter("answer").count() == 20


def test_positions_and_fused_ranks(spark):
    df = spark.range(500).select("id", (F.col("id") * 7919 % 101).alias("a"), (F.col("id") * 31 % 17).alias("b"))
    placed = {r.id: r.pos for r in global_position(df.repartition(7), [F.col("a").desc(), F.col("id").asc()]).collect()}
    assert placed == {r.id: i for i, r in enumerate(sorted(df.collect(), key=lambda r: (-r.a, r.id)))}
    rank = {s: {r.id: i + 1 for i, r in enumerate(sorted(df.collect(), key=lambda r: (-r[s], r.id)))} for s in ("a", "b")}
    for r in relevance.rrf(df, "id", ["a", "b"]).collect():
        assert r.rel_score == pytest.approx(1 / (60 + rank["a"][r.id]) + 1 / (60 + rank["b"][r.id]))


def test_similarity_threshold_is_monotone(spark, sf_dir):
    docs = base(spark, sf_dir, "documents").select(relevance.similarity_column(F.col("text"), "licensed copyright").alias("s"), truth.lic.safe().alias("y"))
    rows = relevance.sweep(docs, "s", "y", [-1.0, 0.1, 0.15, 0.4]).orderBy("threshold").collect()
    assert rows[0].dropped == 0 and [r.dropped for r in rows] == sorted(r.dropped for r in rows) and [r.kept_pos for r in rows] == sorted((r.kept_pos for r in rows), reverse=True)
