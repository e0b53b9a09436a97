"""What the optimizer decides and what its parts save, as queries: orders, error budgets, signals, cache, comparators, more citations."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from sparkverdict.functions import truth
from sparkverdict.operators import metrics, provenance, relevance
from sparkverdict.operators.cache import PromptCache, answers
from sparkverdict.operators.confseq import bonferroni, geometric
from sparkverdict.operators.engine import verify
from sparkverdict.operators.models import RuleModel
from sparkverdict.plans.claims import EXISTS, FORALL, Claim, Quantified, count, share
from sparkverdict.plans.optimizer import VerifyOptions, choose_order
from sparkverdict.session import shared_dir
from sparkverdict.sources.relations import base, relation, stems

Query = Callable[[SparkSession, str], DataFrame]
Q: dict[str, Query] = {}
SQL: dict[str, str] = {}

# --- the order rule, for each comparison with and without a known size ---
_TESTS = {
    "exists": EXISTS, "forall": FORALL, "count >= 3": count(">=", 3), "count > 3": count(">", 3), "count >= 50": count(">=", 50), "count > 50": count(">", 50), "count < 50": count("<", 50), "count <= 50": count("<=", 50),
    "count == 50": count("==", 50), "count != 50": count("!=", 50), **{f"share {op} 0.5": share(op, 0.5) for op in (">=", ">", "<", "<=", "==", "!=")},
}


def order_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(name, known, choose_order(test, known)) for name, test in _TESTS.items() for known in (True, False)]
    return spark.createDataFrame(rows, "test string, size_known boolean, chosen string")


Q["plan_order_rules"] = order_rules
SQL["plan_order_rules"] = f"""WITH t AS (SELECT unnest([{", ".join(f"'{x}'" for x in _TESTS)}]) AS test), k AS (SELECT unnest([true, false]) AS size_known)
 SELECT test, size_known, CASE WHEN test = 'exists' THEN 'relevance' WHEN test = 'forall' OR test LIKE 'share%' THEN 'estimate'
 WHEN test LIKE 'count >%' THEN CASE WHEN size_known AND test LIKE '%50' THEN 'estimate' ELSE 'relevance' END
 WHEN size_known THEN 'estimate' ELSE 'none' END AS chosen FROM t, k"""


def error_budgets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each interval's share of alpha = .05: with m groups known, and by arrival where m is unknown; what all intervals use up."""
    rows = [
        (o, a, m, bonferroni(0.05, o, a, m), o * a * m * bonferroni(0.05, o, a, m), geometric(0.05, o, a, m), o * a * sum(geometric(0.05, o, a, i) for i in range(1, m + 1)))
        for o in (1, 2) for a in (1, 2, 3) for m in (1, 4, 20)
    ]
    cols = ("known", "known_total", "arrival", "arrival_total")
    return spark.createDataFrame(rows, "operators int, tallies int, groups int, known double, known_total double, arrival double, arrival_total double").select("operators", "tallies", "groups", *[F.round(c, 12).alias(c) for c in cols])


Q["plan_error_budgets"] = error_budgets
SQL["plan_error_budgets"] = """SELECT o::INT AS operators, a::INT AS tallies, m::INT AS groups, round(0.05::DOUBLE / (o * a * m), 12) AS known, round(0.05::DOUBLE, 12) AS known_total,
 round(0.05::DOUBLE / (o * a * pow(2, m)), 12) AS arrival, round(0.05::DOUBLE * (1 - pow(0.5, m)), 12) AS arrival_total
 FROM (SELECT unnest([1, 2]) AS o), (SELECT unnest([1, 2, 3]) AS a), (SELECT unnest([1, 4, 20]) AS m)"""

# --- relevance signals one by one, and a limit in place of the full order ---
_QUERY = " ".join(truth.INSULTS)


def signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = F.coalesce(F.col("text"), F.lit(""))
    return base(spark, sf_dir, "documents").select(
        "doc_id", F.round(relevance.text_cosine(stems(t), _QUERY), 9).alias("cosine"), relevance.n_present(t, truth.INSULTS).cast("long").alias("present"), relevance.n_absent(t, ("licens", "copyright")).cast("long").alias("absent")
    )


_PRESENT = " + ".join(f"contains(lower(t), '{w}')::BIGINT" for w in truth.INSULTS)
Q["rel_signals"] = signals
SQL["rel_signals"] = f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
 b AS (SELECT *, list_distinct(list_transform(list_filter(string_split_regex(lower(t), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> ''), lambda w: left(w, 5))) AS bag FROM d)
 SELECT doc_id, round(coalesce(len(list_intersect(bag, [{", ".join(f"'{w[:5]}'" for w in truth.INSULTS)}])) / nullif(sqrt(len(bag) * {len(truth.INSULTS)}.0::DOUBLE), 0), 0), 9) AS cosine,
 {_PRESENT} AS present, (NOT contains(lower(t), 'licens'))::BIGINT + (NOT contains(lower(t), 'copyright'))::BIGINT AS absent FROM b"""

_LIMITS = (5, 20, 100)


def top_k_limit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hits that a limit of k rows in the order of the include words keeps, against all hits: a limit loses what the full order only delays."""
    docs = base(spark, sf_dir, "documents").select("doc_id", relevance.n_absent(F.col("text"), ("the", "and")).cast("long").alias("s"), truth.abuse.safe().alias("hit"))
    every = docs.agg(F.count_if("hit").alias("all_hits"))
    kept = None
    for k in _LIMITS:
        one = docs.orderBy(F.col("s").desc(), "doc_id").limit(k).agg(F.lit(k).alias("k"), F.count_if("hit").alias("kept_hits"))
        kept = one if kept is None else kept.union(one)
    # one row on the broadcast side
    return kept.join(F.broadcast(every), how="cross")


Q["base_topk_limit"] = top_k_limit
SQL["base_topk_limit"] = " UNION ALL ".join(
    f"SELECT {k}::INT AS k, count(*) FILTER (hit) AS kept_hits, (SELECT count(*) FROM documents WHERE coalesce({truth.abuse.sql}, false)) AS all_hits FROM (SELECT coalesce({truth.abuse.sql}, false) AS hit FROM documents ORDER BY (NOT contains(lower(text), 'the'))::INT + (NOT contains(lower(text), 'and'))::INT DESC, doc_id LIMIT {k})"
    for k in _LIMITS
)


def granularity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall and filter rate at each threshold, for sentences and for whole documents."""
    out = None
    for level in ("sentence", "document"):
        docs = base(spark, sf_dir, "documents").select(relevance.similarity_column(F.col("text"), _QUERY, level).alias("score"), truth.abuse.safe().alias("selected"))
        one = relevance.sweep(docs, "score", "selected", [0.05, 0.1, 0.15, 0.2, 0.3]).withColumn("level", F.lit(level))
        out = one if out is None else out.union(one)
    return out


Q["sim_granularity"] = granularity

# --- early stopping: rows that a sorted streaming aggregate evaluates against a hash aggregate, and the overshoot of waves ---
_WAVE = 32


def stop_savings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per source for "at least 20 licence texts", sizes known: settle point, rows evaluated in waves, overshoot, rows of a hash aggregate."""
    docs = base(spark, sf_dir, "documents").select("source", "doc_id", truth.lic.safe().alias("hit"))
    w = Window.partitionBy("source").orderBy("doc_id")
    placed = docs.select("source", F.row_number().over(w).cast("long").alias("pos"), F.count_if("hit").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("h"), F.count(F.lit(1)).over(Window.partitionBy("source")).alias("n"))
    settled = placed.filter((F.col("h") >= 20) | (F.col("h") + F.col("n") - F.col("pos") < 20)).groupBy("source").agg(F.min("pos").alias("stop"), F.max("n").alias("hash_rows"))
    waves = F.least("hash_rows", F.ceil(F.col("stop") / _WAVE) * _WAVE).cast("long")
    return settled.select("source", "stop", waves.alias("seen"), (waves - F.col("stop")).alias("overshoot"), "hash_rows")


Q["metric_a16"] = stop_savings
SQL["metric_a16"] = f"""WITH p AS (SELECT source, row_number() OVER w AS pos, count(*) FILTER (coalesce({truth.lic.sql}, false)) OVER w AS h, count(*) OVER (PARTITION BY source) AS n FROM documents WINDOW w AS (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING)),
 s AS (SELECT source, min(pos) AS stop, max(n) AS hash_rows FROM p WHERE h >= 20 OR h + n - pos < 20 GROUP BY 1)
 SELECT source, stop, least(hash_rows, ((stop + {_WAVE - 1}) // {_WAVE}) * {_WAVE}) AS seen, least(hash_rows, ((stop + {_WAVE - 1}) // {_WAVE}) * {_WAVE}) - stop AS overshoot, hash_rows FROM s"""


def cache_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Prompts that reach the model when a claim is checked, and when it is checked again: equal texts once, known ones never."""
    cache = PromptCache(spark, f"{shared_dir(spark)}/sparkverdict/cache-{uuid.uuid4().hex}")
    docs = base(spark, sf_dir, "documents").select("doc_id", "text")
    runs = []
    for run in (1, 2):
        said, asked = answers(docs, truth.abuse, RuleModel(), cache)
        runs.append((run, asked, said.filter("answer").count()))
    return spark.createDataFrame(runs, "run int, asked long, hits long")


Q["metric_a12"] = cache_replay
SQL["metric_a12"] = f"SELECT run::INT AS run, CASE run WHEN 1 THEN (SELECT count(DISTINCT coalesce(text, 'None')) FROM documents) ELSE 0 END::BIGINT AS asked, (SELECT count(*) FROM documents WHERE coalesce({truth.abuse.sql}, false)) AS hits FROM (SELECT unnest([1, 2]) AS run)"


def trials(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean, least and greatest over three trials: the lengths of the documents of each language by doc_id mod 3."""
    one = base(spark, sf_dir, "documents").groupBy("lang", (F.col("doc_id") % 3).alias("trial")).agg(F.avg("n_chars").alias("v"))
    return metrics.trials(one, "v", ("lang",)).select("lang", *[F.round(c, 6).alias(c) for c in ("mean", "low", "high", "sd")])


Q["metric_a5"] = trials
SQL["metric_a5"] = "SELECT lang, round(avg(v), 6) AS mean, round(min(v), 6) AS low, round(max(v), 6) AS high, round(stddev_samp(v), 6) AS sd FROM (SELECT lang, doc_id % 3 AS t, avg(n_chars) AS v FROM documents GROUP BY 1, 2) GROUP BY 1"


def heat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Right trials of each source in a grid of configurations: a test that errs on documents of one remainder."""
    docs = base(spark, sf_dir, "documents").select(F.col("source").alias("claim_id"), F.concat(F.lit("r"), (F.col("doc_id") % 3).cast("string")).alias("config"), truth.long.safe().alias("expected"), (truth.long.safe() != (F.col("doc_id") % 7 == 0)).alias("verdict"))
    return metrics.heat(docs, ["r0", "r1", "r2"]).select("claim_id", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("r0", "r1", "r2")])


Q["metric_a6"] = heat
SQL["metric_a6"] = "SELECT source AS claim_id, " + ", ".join(f"count(*) FILTER (doc_id % 3 = {i} AND doc_id % 7 <> 0) AS r{i}" for i in range(3)) + " FROM documents GROUP BY 1"

# --- citations of the comparisons that look down ---
#: Claim, which sign is cited (0: both) and how many rows in the order of doc_id.
_CITED = {
    "v11": (share(">=", Fraction(1, 100)), 1, "(SELECT ceil(count(*) / 100.0)::BIGINT FROM documents)"),
    "v12": (count(">=", 10**6), 0, None),
    "v13": (count("==", 3), 0, None),
    "v14": (count("!=", 1), 0, None),
    "v15_le": (count("<=", 1), 1, "2"),
    "v15_gt": (count(">", 10**6), 0, None),
    "v15_lt": (share("<", Fraction(9, 10)), 0, None),
}


def _cite(claim: Claim) -> Query:
    return lambda spark, sf_dir: provenance.cite(claim, relation(spark, sf_dir, claim.relation)).select("claim_id", "grp", "tuple_id", F.col("sign").cast("long").alias("sign"))


for _id, (_test, _sign, _limit) in _CITED.items():
    Q[f"prov_{_id}"] = _cite(Claim(_id, "documents", Quantified(_test, truth.abuse)))
    _hit = f"coalesce({truth.abuse.sql}, false)"
    SQL[f"prov_{_id}"] = f"SELECT '{_id}' AS claim_id, NULL::VARCHAR AS grp, doc_id AS tuple_id, CASE WHEN {_hit} THEN 1 ELSE -1 END::BIGINT AS sign FROM documents" + (f" WHERE {_hit} = {str(_sign > 0).lower()} ORDER BY doc_id LIMIT {_limit}" if _limit else "")

# --- citations from what a run has answered, without asking again ---
_NEVER = Claim("never", "documents", Quantified(EXISTS, truth.secret & truth.card), truth.symbolic("lang", "=", "fr"))
_ALWAYS = Claim("always", "documents", Quantified(FORALL, ~truth.abuse), truth.symbolic("lang", "=", "fr"))
_SOME = Claim("some", "documents", Quantified(EXISTS, truth.lic))
_MANY = Claim("many", "documents", Quantified(share(">=", Fraction(1, 5)), truth.long))
_FEW = Claim("few", "documents", Quantified(share(">=", Fraction(4, 5)), truth.long))


def _run_cite(claim: Claim, options: VerifyOptions) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = relation(spark, sf_dir, claim.relation)
        tokens = provenance.cite_run(claim, verify(claim, df, options))
        return tokens.select("claim_id", "grp", "tuple_id", F.col("sign").cast("long").alias("sign"))

    return query


for _name, _claim, _options in (
    ("v5", _SOME, VerifyOptions.exact()), ("v7_run", _NEVER, VerifyOptions.exact()), ("v8_run", _ALWAYS, VerifyOptions.exact()),
    ("v11_run", _MANY, VerifyOptions()), ("v12_run", _FEW, VerifyOptions()),
):
    Q[f"prov_{_name}"] = _run_cite(_claim, _options)
for _name, _claim, _sign in (("v7_run", _NEVER, -1), ("v8_run", _ALWAYS, 1)):
    SQL[f"prov_{_name}"] = f"SELECT '{_claim.claim_id}' AS claim_id, NULL::VARCHAR AS grp, doc_id AS tuple_id, {_sign}::BIGINT AS sign FROM documents WHERE coalesce({_claim.form.phi.sql}, false) = {str(_sign > 0).lower()} AND lang = 'fr'"


def queries() -> dict[str, Query]:
    return dict(Q)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
