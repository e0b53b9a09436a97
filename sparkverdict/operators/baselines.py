"""The comparators, as deterministic policies over the same tests: a judge of the prefix that fits its context, an agent that
pages through retrieved rows, programs that scan or sample, and a majority of models as ground truth."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparkverdict.operators import ranking, relevance
from sparkverdict.operators.engine import Result, tuple_id, verify
from sparkverdict.operators.models import EnsembleModel, SemanticModel
from sparkverdict.plans.claims import Claim, Nested, Quantified, Test, claim_sql, evaluate
from sparkverdict.plans.optimizer import VerifyOptions
from sparkverdict.sources.relations import RELATIONS

CONTEXT = 200_000


def row_tokens(text: str) -> Column:
    return F.ceil(F.length(F.coalesce(F.col(text).cast("string"), F.lit(""))) / 4).cast("long") + 16


def prefix(claim: Claim, df: DataFrame, budget: int = CONTEXT) -> DataFrame:
    """Rows in id order while their tokens fit the budget. No more than budget/16 rows can fit, so that many are sorted."""
    rows = df.withColumn("_tid", tuple_id(claim.relation)).withColumn("_tok", row_tokens(RELATIONS[claim.relation][1]))
    first = rows.orderBy("_tid").limit(budget // 16 + 1)
    running = F.sum("_tok").over(Window.orderBy("_tid").rowsBetween(Window.unboundedPreceding, 0))
    return first.withColumn("_run", running).filter(F.col("_run") <= budget).drop("_tid", "_tok", "_run")


def whole_context(claim: Claim, df: DataFrame, budget: int = CONTEXT) -> DataFrame:
    """claim_id, verdict, hits, seen as judged from the prefix alone."""
    return evaluate(claim, prefix(claim, df, budget))


def prefix_sql(source: str, key: str, text: str, budget: int) -> str:
    return f"(SELECT * EXCLUDE (_run) FROM (SELECT *, sum(ceil(length(coalesce({text}, '')) / 4)::BIGINT + 16) OVER (ORDER BY {key}) AS _run FROM {source}) WHERE _run <= {budget})"


#: Rows of an agent's pages, and parts of a thousand that a program samples in turn, the whole relation last.
PAGES = (10, 20, 30, 40, 50, 50)
SLICES = (50, 100, 200, 400, 1000)


def _positive(claim: Claim):
    """Whether an answer is certain from a part of the rows, as a column over verdict, hits and seen."""
    form = claim.form
    if isinstance(form, Quantified) and not form.also:
        if form.test.kind == "exists":
            return F.col("verdict")
        if form.test.kind == "forall":
            return ~F.col("verdict")
        if form.test.kind == "count" and form.test.op in (">=", ">"):
            return F.col("verdict")
    return F.lit(False)


def _of_nothing(claim: Claim) -> bool:
    """The verdict over no rows."""
    form = claim.form
    return bool(form.test.verdict(0, 0) if isinstance(form, Quantified) else form.outer.verdict(0, 0) if isinstance(form, Nested) else False)


def _first_answer(claim: Claim, trace: DataFrame, stop: Column) -> DataFrame:
    """The answer of the first turn at which the policy stops; of no rows, that of the empty relation."""
    turns = Window.orderBy("turn")  # a handful of rows, one per turn
    seen = trace.withColumn("before", F.lag(F.struct("verdict", "hits")).over(turns)).withColumn("last", F.lead("turn").over(turns).isNull())
    first = F.min_by(F.struct("verdict", "hits", "seen", "turn"), F.when(stop | F.col("last"), F.col("turn")))
    at = seen.agg(first.alias("a"))
    zero = F.lit(0).cast("long")
    return at.select(F.lit(claim.claim_id).alias("claim_id"), F.coalesce("a.verdict", F.lit(_of_nothing(claim))).alias("verdict"), F.coalesce("a.hits", zero).alias("hits"), F.coalesce("a.seen", zero).alias("seen"), F.coalesce("a.turn", F.lit(0)).alias("turn"))


def agent_trace(claim: Claim, df: DataFrame, pages: tuple[int, ...] = PAGES) -> DataFrame:
    """turn, verdict, hits, seen: what the agent would answer after each page. It asks for the rows nearest to the claim's
    words within its structured filter, then for the next page, and takes what it has read for the relation."""
    form = claim.form
    while isinstance(form, Nested):
        form = form.inner
    rows = df.withColumn("tid", tuple_id(claim.relation))
    if claim.scope is not None:  # the structured pre-filter of a retrieval query
        rows = rows.filter(claim.scope.safe())
    scores = relevance.relevance_scores(rows, "tid", RELATIONS[claim.relation][1], relevance.spec_for(form.phi))
    top = scores.orderBy(F.col("rel_score").desc(), "tid").limit(sum(pages)).select("tid", F.row_number().over(Window.orderBy(F.col("rel_score").desc(), "tid")).alias("pos"))
    page, upto = F.lit(len(pages)), 0
    for i, n in reversed(list(enumerate(pages, 1))):
        upto = sum(pages[:i])
        page = F.when(F.col("pos") <= upto, i).otherwise(page)
    # at most sum(pages) ids; a row stands in its page's turn and in all later ones
    read = rows.join(F.broadcast(top), "tid").withColumn("turn", F.explode(F.sequence(page, F.lit(len(pages))))).drop("tid", "pos")
    return evaluate(claim, read, ("turn",))


def retrieval_agent(claim: Claim, df: DataFrame, pages: tuple[int, ...] = PAGES) -> DataFrame:
    """Reads on until its answer is certain from what it read, or a page has brought no hit, or there are no more pages."""
    dry = F.col("before").isNotNull() & (F.col("before.hits") == F.col("hits"))
    return _first_answer(claim, agent_trace(claim, df, pages), _positive(claim) | dry)


def _slice(claim: Claim, seed: int) -> Column:
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), tuple_id(claim.relation).cast("string"))), 1, 4), 16, 10).cast("long") % 1000


def _scaled(claim: Claim) -> Test | None:
    """The test of a count, which a program scales up from its sample."""
    test = getattr(claim.form, "test", None)
    return test if test is not None and test.kind == "count" and not claim.form.also else None


def iterating_program(claim: Claim, df: DataFrame, slices: tuple[int, ...] = SLICES, seed: int = 3) -> DataFrame:
    """A program that counts over a sample, looks at its answer, and runs again over a larger one until two answers agree; the
    last run reads every row. Counts of a sample are scaled up. A row of all runs is a row of the first ones more than once."""
    turn = F.lit(len(slices))
    for i, n in reversed(list(enumerate(slices[:-1], 1))):
        turn = F.when(_slice(claim, seed) < n, i).otherwise(turn)
    got = evaluate(claim, df.withColumn("turn", F.explode(F.sequence(turn, F.lit(len(slices))))), ("turn",))
    if test := _scaled(claim):
        per_mille = F.element_at(F.array(*[F.lit(n) for n in slices]), F.col("turn"))
        got = got.withColumn("hits", F.expr("hits * 1000L").cast("long")).withColumn("hits", F.floor(F.col("hits") / per_mille).cast("long")).withColumn("verdict", test.verdict(F.col("hits"), F.col("seen")))
    return _first_answer(claim, got, F.col("before").isNotNull() & (F.col("before.verdict") == F.col("verdict")))


def iterating_sql(claim: Claim, source: str, key: str, slices: tuple[int, ...] = SLICES, seed: int = 3) -> str:
    """The same for DuckDB."""
    part = f"(('0x' || substr(md5('{seed}|' || {key}), 1, 4))::BIGINT % 1000)"
    test, runs = _scaled(claim), []
    for i, n in enumerate(slices, 1):
        one = claim_sql(claim, f"(SELECT * FROM {source} AS s0 WHERE {part} < {n})")
        hits = f"hits * 1000 // {n}" if test else "hits"
        runs.append(f"SELECT {i} AS turn, claim_id, {test.sql(hits, 'seen') if test else 'verdict'} AS verdict, ({hits})::BIGINT AS hits, seen FROM ({one})")
    trace = f"SELECT *, lag(verdict) OVER w AS before, lead(turn) OVER w IS NULL AS last FROM ({' UNION ALL '.join(runs)}) WHERE seen > 0 WINDOW w AS (ORDER BY turn)"
    nothing = f"SELECT '{claim.claim_id}', {str(_of_nothing(claim)).lower()}, 0, 0, 0"
    return f"SELECT * FROM (SELECT claim_id, verdict, hits, seen, turn::INT AS turn FROM ({trace}) WHERE before = verdict OR last UNION ALL {nothing}) ORDER BY turn = 0, turn LIMIT 1"


def program_agent(claim: Claim, df: DataFrame, program: str = "sample", fraction: float = 0.2, seed: int = 3) -> DataFrame:
    """full_scan is exact; sample reads a hash slice and scales counts; iterate samples again until two answers agree;
    retrieve_then_count is the agent's reading with exact counting."""
    if program == "full_scan":
        return evaluate(claim, df)
    if program == "retrieve_then_count":
        return retrieval_agent(claim, df).drop("turn")
    if program == "iterate":
        return iterating_program(claim, df, seed=seed).drop("turn")
    turn = F.pmod(F.xxhash64(F.lit(seed), tuple_id(claim.relation)), F.lit(1000))
    part = evaluate(claim, df.filter(turn < int(fraction * 1000)))
    if not (test := _scaled(claim)):
        return part
    scaled = part.withColumn("hits", F.round(F.col("hits") / fraction).cast("long"))
    return scaled.withColumn("verdict", test.verdict(F.col("hits"), F.col("seen")))


def naive(claim: Claim, df: DataFrame, model: SemanticModel | None = None) -> Result:
    """Every optimization off, each test a call of its own."""
    return verify(claim, df, VerifyOptions.none(), model)


def ensemble_reference(claim: Claim, df: DataFrame, models: tuple[SemanticModel, ...]) -> Result:
    return verify(claim, df, VerifyOptions.none(), EnsembleModel(models))


def top_k_only(claim: Claim, df: DataFrame, k: int) -> Result:
    """Relevance order cut after k rows: may miss what full order finds."""
    return verify(claim, df, VerifyOptions(estimate=False, top_k=k))


def paged(df: DataFrame, score: str, key: str, page: int, number: int) -> DataFrame:
    """One page of a ranked relation without a single-task sort of all."""
    placed = ranking.global_position(df.select(key, score), [F.col(score).desc(), F.col(key).asc()])
    return placed.filter((F.col("pos") >= page * number) & (F.col("pos") < page * (number + 1)))
