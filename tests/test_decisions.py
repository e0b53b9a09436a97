"""Planning decisions and comparators as queries, and citations of share ranks."""

from __future__ import annotations

from collections import Counter

from sparkverdict import decisions
from sparkverdict.functions import truth
from sparkverdict.operators import provenance
from sparkverdict.plans.claims import Claim, RankIs


def test_sentences_keep_what_documents_lose(spark, sf_dir):
    rows = decisions.queries()["sim_granularity"](spark, sf_dir).collect()
    at = {(r.level, r.threshold): r for r in rows}
    assert len(rows) == 10
    assert at["sentence", 0.15].kept_pos == at["sentence", 0.15].n_pos  # recall 1 at the default threshold
    assert at["document", 0.15].kept_pos < at["document", 0.15].n_pos
    for level in ("sentence", "document"):
        kept = [at[level, t].kept_pos for t in (0.05, 0.1, 0.15, 0.2, 0.3)]
        assert kept == sorted(kept, reverse=True)


def test_cache_and_waves(spark, sf_dir):
    runs = {r.run: r for r in decisions.queries()["metric_a12"](spark, sf_dir).collect()}
    assert runs[2].asked == 0 < runs[1].asked and runs[1].hits == runs[2].hits
    for r in decisions.queries()["metric_a16"](spark, sf_dir).collect():
        assert r.stop <= r.seen <= r.hash_rows and 0 <= r.overshoot < 32


def test_budgets_stay_within_alpha(spark, sf_dir):
    rows = decisions.queries()["plan_error_budgets"](spark, sf_dir).collect()
    assert len(rows) == 18 and all(r.known_total <= 0.05 + 1e-12 and r.arrival_total <= 0.05 for r in rows)


def test_share_ranks_cite_whole_numbers(spark):
    """29 of 100 is .29, and .29 times 100 is a little less than 29: the larger group must still show 30 hits."""
    rows = [(f"{g}{i}", g, 3000 if i < hits else 10) for g, hits in (("a", 29), ("b", 30), ("c", 58)) for i in range(200 if g == "c" else 100)]
    docs = spark.createDataFrame([(n, s, c, "x", "en") for n, (_, s, c) in enumerate(rows)], "doc_id long, source string, n_chars long, text string, lang string")
    claim = Claim("share", "documents", RankIs(("source",), ("a",), 2, truth.long, by="share"))
    got = Counter((r.grp, r.sign) for r in provenance.cite(claim, docs).collect())
    # b is above a: 30 hits of b, 71 misses of a; c ties with a (58 of 200), and both sides of a tie show all
    assert got["b", 1] == 30 and got["b", -1] == 0 and got["c", 1] == 58 and got["c", -1] == 142
    assert got["a", 1] == 29 and got["a", -1] == 71
