"""Runs a planned claim with as few semantic calls as its tests need.

Ungrouped claims read waves of rows in a fixed order (by relevance, or by a seeded hash of the row's id) and stop at the
first row that settles the test. Rows that a wave read past that point count as overshoot, nothing else. Waves grow
geometrically, each writes its answers to the shared folder (citations are taken from there, and no answer is lost with an
executor), and the driver sees a place and some bits of each row, of one wave at a time. Without early stopping a claim
is one aggregation. Grouped claims give whole groups to a table function that reads each group in order and skips the rest
of a settled one; groups come in waves too, by a seeded hash or by relevance, until the outer test settles; deeper levels
fold up in Spark. With group_exec='hash' every row is answered and groups are plain aggregates, so that a group of any
size is spread over tasks. Ranks need every row and get one aggregation.

Rows are told apart by their relation's key. Where a key is null or repeated, rows get ids of the engine's own, so that
none is lost or multiplied; tokens then cite those ids.

`verify_each` runs a claim for several models at once (trials of one experiment): rows are ordered, staged and grouped once,
each wave asks the models that have not settled, and each model's result is what it would be alone. Rows of answers carry
the model's number `m`.

At scale: the order is a narrow table of (id, place); texts are joined to it only for the stage at hand (a bounded prefix
of places, written sorted by place so that a wave reads a few row groups), and no row of text is sorted globally.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from dataclasses import dataclass, field, replace

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from sparkverdict.operators import ranking, relevance
from sparkverdict.operators.confseq import ClassicalCI, geometric
from sparkverdict.operators.models import ANSWER_TOKENS, RuleModel, SemanticModel, tokens_in
from sparkverdict.operators.tally import Tally
from sparkverdict.plans.claims import EXISTS, Claim, Nested, Quantified, RankIs, domain, rank_groups
from sparkverdict.plans.optimizer import Plan, VerifyOptions, plan
from sparkverdict.session import dropped, ship_package, written
from sparkverdict.sources.relations import RELATIONS

STAGE = 65_536
SAMPLE_TOKENS = 100


@dataclass
class Result:
    claim_id: str
    verdict: bool
    settled_by: str
    seen: int
    hits: int
    size: int | None
    lo: float = 0.0
    hi: float = 1.0
    calls: int = 0
    overshoot: int = 0
    tokens_in: int = 0
    tokens_out: int = 0
    complete: bool = True
    vacuous: bool = False
    #: At most SAMPLE_TOKENS signed (group, tuple_id, sign); provenance.cite() gives all of them as a DataFrame.
    tokens: list[tuple] = field(default_factory=list)
    plan: Plan | None = None
    #: What the run has answered up to its end, as a written table: tid, pos, hit (of the first test).
    answers: DataFrame | None = field(default=None, repr=False)
    #: The same with the rows that a semantic filter dropped: tid, keep, hit.
    processed: DataFrame | None = field(default=None, repr=False)


def tuple_id(name: str) -> Column:
    keys = RELATIONS[name][0]
    if not keys:  # the engine numbers the rows
        return F.lit(None).cast("long")
    return F.col(keys[0]).try_cast("long") if len(keys) == 1 else F.col(keys[0]).cast("long") * 8 + F.col(keys[1])


def _needed(claim: Claim) -> list[str]:
    form = claim.form
    while isinstance(form, Nested):
        form = form.inner
    preds = [form.phi] if isinstance(form, RankIs) else [p for _, p in form.tallies]
    preds += [claim.semantic_scope] if claim.semantic_scope else []
    return sorted({c for p in preds for c in p.columns})


#: Prompts that a task remembers.
REMEMBERED = 100_000


class _Evaluator:
    """Answers for one row: whether it is in the scope, its bits, calls and tokens. With the prompt cache on, a task asks
    equal prompts once."""

    def __init__(self, claim: Claim, model: SemanticModel, fusion: bool, max_fused: int, cache: bool = False) -> None:
        self.cache, self.memory = cache, {}
        form = claim.form
        while isinstance(form, Nested):
            form = form.inner
        self.maps = [p for _, p in form.tallies]
        self.scope, self.model, self.fusion, self.max_fused = claim.semantic_scope, model, fusion, max_fused
        self.distinct = {p.name.removeprefix("not_") for p in self.maps if p.semantic}

    def __call__(self, row: dict) -> tuple[bool, list[bool], int, int]:
        prompts = len(self.distinct) + (self.scope is not None)
        columns = tuple(dict.fromkeys(c for p in [*self.maps, *([self.scope] if self.scope else [])] for c in p.columns))
        asked = tuple(row[c] for c in columns)
        if self.cache:
            try:
                if asked in self.memory:
                    keep, bits = self.memory[asked]
                    return keep, bits, 0, 0
            except TypeError:  # a value that can't be a key
                asked = None
        calls = -(-prompts // self.max_fused) if self.fusion else prompts
        keep = self.scope is None or self.model.answer(self.scope, row)
        if not keep and not self.fusion:
            calls = 1  # the filter came first, nothing follows
        bits = [self.model.answer(p, row) for p in self.maps] if keep else []
        if self.cache and asked is not None:
            if len(self.memory) >= REMEMBERED:
                self.memory.clear()
            self.memory[asked] = keep, bits
        return keep, bits, calls, calls * tokens_in(row, columns)


def _wave_rows(evaluators: dict[int, _Evaluator], columns: list[str], batch: int):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for low in range(0, len(frame), batch):  # one request to each model per batch
                part = frame.iloc[low : low + batch]
                rows = part[columns].to_dict("records")
                for m, evaluate in evaluators.items():
                    answers = [evaluate(r) for r in rows]
                    yield pd.DataFrame({
                        "m": m, "pos": part["pos"], "tid": part["tid"], "keep": [a[0] for a in answers], "bits": [sum(b << i for i, b in enumerate(a[1])) for a in answers],
                        "calls": [a[2] for a in answers], "tokens": [a[3] for a in answers],
                    })

    return run


WAVE = "m int, pos long, tid long, keep boolean, bits int, calls int, tokens long"


def _evaluators(claim: Claim, models: list[SemanticModel], options: VerifyOptions) -> dict[int, _Evaluator]:
    return {m: _Evaluator(claim, model, options.fusion, options.max_fused, options.cache) for m, model in enumerate(models)}


def _positions(df: DataFrame, claim: Claim, order: str, options: VerifyOptions) -> DataFrame:
    """tid and place."""
    if order == "relevance":
        form = claim.form
        text = RELATIONS[claim.relation][1]
        scores = relevance.relevance_scores(df, "tid", text, relevance.spec_for(form.phi), options.rrf_k)
        return ranking.global_position(scores, [F.col("rel_score").desc(), F.col("tid").asc()])
    key = F.xxhash64(F.lit(options.seed), F.col("tid")) if order == "estimate" else F.col("tid")
    return ranking.global_position(df.select("tid", key.alias("k")), [F.col("k").asc(), F.col("tid").asc()])


def _tallies(form: Quantified, size: int | None, alpha: float | None, options: VerifyOptions) -> list[Tally]:
    out = [Tally(t, size, alpha, options.eps, options.early_stop) for t, _ in form.tallies]
    if options.interval == "classical":
        for t in out:
            t.interval = ClassicalCI(alpha, size) if t.interval is not None else None
    return out


def _decided(tallies: list[Tally]) -> bool:
    return any(t.verdict is False for t in tallies) or all(t.settled for t in tallies)


def _needed_frame(df: DataFrame, columns: list[str], keys: tuple[str, ...] = ()) -> DataFrame:
    return df.select("tid", *keys, *[c for c in columns if c not in keys])


def _answered(df: DataFrame, evaluators: dict[int, _Evaluator], columns: list[str], keys: tuple[str, ...] = ()) -> DataFrame:
    """Every row's answers by every model: m, tid, keys, keep, bits, calls, tokens."""
    needed = _needed_frame(df, columns, keys)
    schema = ", ".join(f"`{k}` {needed.schema[k].dataType.simpleString()}" for k in ("tid", *keys))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            rows = frame[columns].to_dict("records")
            for m, evaluate in evaluators.items():
                answers = [evaluate(r) for r in rows]
                out = frame[["tid", *keys]].copy()
                out.insert(0, "m", m)
                out["keep"], out["bits"] = [a[0] for a in answers], [sum(b << i for i, b in enumerate(a[1])) for a in answers]
                out["calls"], out["tokens"] = [a[2] for a in answers], [a[3] for a in answers]
                yield out

    return needed.mapInPandas(run, f"m int, {schema}, keep boolean, bits int, calls int, tokens long")


def _by_model(df: DataFrame, models: list[SemanticModel], *columns: Column) -> list[dict]:
    """One row of aggregates per model, those of no rows where a model has none."""
    found = {r["m"]: r.asDict() for r in df.groupBy("m").agg(*columns).collect()}
    nothing = df.limit(0).agg(*columns).first().asDict() if len(found) < len(models) else {}
    return [found.get(m, nothing) for m in range(len(models))]


def _bit(i: int) -> Column:
    return F.col("keep") & (F.shiftright("bits", i).bitwiseAND(F.lit(1)) == 1)


def _run_all_rows(claim: Claim, df: DataFrame, models: list[SemanticModel], p: Plan) -> list[Result]:
    """An ungrouped claim without early stopping: one pass, one aggregation."""
    options, form = p.options, claim.form
    answers = written(_answered(df, _evaluators(claim, models, options), _needed(claim)), "answers")
    hits = [F.count_if(_bit(i)).alias(f"h{i}") for i in range(len(form.tallies))]
    out = []
    for m, got in enumerate(_by_model(answers, models, F.count(F.lit(1)).alias("n"), F.count_if("keep").alias("kept"), F.sum("calls").alias("calls"), F.sum("tokens").alias("tokens"), *hits)):
        verdicts = [bool(t.verdict(got[f"h{i}"], got["kept"])) for i, (t, _) in enumerate(form.tallies)]
        calls = got["calls"] or 0
        out.append(Result(
            claim.claim_id, all(verdicts), "exhausted", got["n"], got["h0"], got["n"] if p.size_known else None, calls=calls, tokens_in=got["tokens"] or 0, tokens_out=calls * ANSWER_TOKENS,
            vacuous=got["kept"] == 0, plan=p, answers=answers.filter(F.col("keep") & (F.col("m") == m)).select("tid", F.col("tid").alias("pos"), _bit(0).alias("hit")),
            processed=answers.filter(F.col("m") == m).select("tid", "keep", _bit(0).alias("hit")),
        ))
    return out


@dataclass
class _Run:
    """One model's way through the waves of an ungrouped claim."""

    tallies: list[Tally]
    result: Result
    end: int = 0
    low: int = 0

    @property
    def decided(self) -> bool:
        return _decided(self.tallies)

    def take(self, got: pd.DataFrame) -> None:
        self.result.calls += int(got["calls"].sum())
        self.result.tokens_in += int(got["tokens"].sum())
        for row in got.itertuples():
            if self.decided:
                self.result.overshoot += 1
                continue
            self.result.seen += 1
            self.end = row.pos + 1
            if not row.keep:
                continue
            for i, t in enumerate(self.tallies):
                t.push([row.bits >> i & 1])
            if len(self.result.tokens) < SAMPLE_TOKENS:
                self.result.tokens.append((None, int(row.tid), 1 if row.bits & 1 else -1))

    def finish(self, total: int) -> Result:
        early, result = self.decided, self.result
        for t in self.tallies:
            if not early:
                t.close()
        result.verdict = all(bool(t.verdict) for t in self.tallies)
        first = next((t for t in self.tallies if t.verdict is False), self.tallies[0])
        result.settled_by, result.hits, result.lo, result.hi = first.settled_by or "exhausted", self.tallies[0].hits, first.lo, first.hi
        result.complete, result.vacuous = result.settled_by != "interval" and (self.low >= total or result.settled_by == "bound"), self.tallies[0].seen == 0 and not early
        result.tokens_out = result.calls * ANSWER_TOKENS
        return result


def _run_rows(claim: Claim, df: DataFrame, models: list[SemanticModel], p: Plan, size: int | None) -> list[Result]:
    """An ungrouped claim, in waves."""
    options, spark = p.options, df.sparkSession
    evaluators = _evaluators(claim, models, options)
    runs = [_Run(_tallies(claim.form, size, p.alpha_inner, options), Result(claim.claim_id, False, "", 0, 0, size, plan=p)) for _ in models]
    columns = _needed(claim)
    places = _positions(df, claim, p.inner_order, options)
    total = size if size is not None else places.count()
    limit = min(total, options.top_k) if options.top_k else total
    wave, low, stage, stage_end, waves = options.batch, 0, None, 0, []
    while low < limit and (active := {m: evaluators[m] for m, r in enumerate(runs) if not r.decided}):
        if low >= stage_end:
            stage_end = min(limit, max(STAGE, stage_end * 8))
            wanted = places.filter((F.col("pos") >= low) & (F.col("pos") < stage_end)).select("tid", "pos")
            if stage is not None and stage.inputFiles():  # its places have all been read
                dropped(spark, stage.inputFiles()[0].rsplit("/", 1)[0])
            stage = written(_needed_frame(df, columns).join(wanted, "tid").repartitionByRange("pos").sortWithinPartitions("pos"), "stage")
        high = min(low + wave, stage_end)
        part = stage.filter((F.col("pos") >= low) & (F.col("pos") < high))
        waves.append(written(part.mapInPandas(_wave_rows(active, columns, options.batch), WAVE), "wave"))
        got = waves[-1].toPandas().sort_values("pos")
        for m in active:
            runs[m].take(got[got["m"] == m])
            runs[m].low = high
        low, wave = high, min(wave * options.growth, options.max_wave)
    if stage is not None and stage.inputFiles():
        dropped(spark, stage.inputFiles()[0].rsplit("/", 1)[0])
    every = waves[0] if waves else spark.createDataFrame([], WAVE)
    for part in waves[1:]:
        every = every.union(part)
    for m, run in enumerate(runs):
        taken = every.filter((F.col("m") == m) & (F.col("pos") < run.end))
        run.finish(total).answers = taken.filter("keep").select("tid", "pos", _bit(0).alias("hit"))
        run.result.processed = taken.select("tid", "keep", _bit(0).alias("hit"))
    return [r.result for r in runs]


class _Group:
    """One model's way through a group."""

    def __init__(self, tallies: list[Tally]) -> None:
        self.tallies, self.seen, self.kept, self.calls, self.tokens, self.sample = tallies, 0, 0, 0, 0, []

    def take(self, tid: int, answer: tuple[bool, list[bool], int, int]) -> None:
        keep, bits, calls, tokens = answer
        self.seen, self.calls, self.tokens = self.seen + 1, self.calls + calls, self.tokens + tokens
        if keep:
            self.kept += 1
            for t, b in zip(self.tallies, bits, strict=True):
                t.push([b])
            if len(self.sample) < 5:
                self.sample.append(tid if bits[0] else -tid - 1)


def _group_function(evaluators: dict[int, _Evaluator], form: Quantified, alpha: float | None, options: VerifyOptions, columns: list[str]):
    """A table function: one call per row of a partition (a group, in order) asks the models that have not settled the group;
    when all have, the rest is skipped. So a row is dealt out once, however many models there are."""
    from pyspark.sql.functions import udtf
    from pyspark.sql.udtf import SkipRestOfInputTableException

    @udtf(returnType="m int, g string, verdict boolean, seen long, hits long, calls long, tokens long, settled_by string, sample array<long>")
    class RunGroup:
        def __init__(self) -> None:
            self.g, self.groups = None, None

        def eval(self, row):
            if self.groups is None:
                self.g = row["g"]
                own = alpha
                if alpha is not None and options.budget == "arrival":
                    own = geometric(alpha, 1, 1, row["gpos"] + 1) or None  # too late a group is counted exactly
                self.groups = {m: _Group(_tallies(form, row["n"] if e.scope is None else None, own, options)) for m, e in evaluators.items()}
            asked, values = False, {c: row[c] for c in columns}
            for m, group in self.groups.items():
                if not (options.early_stop and _decided(group.tallies)):
                    group.take(row["tid"], evaluators[m](values))
                    asked = asked or not (options.early_stop and _decided(group.tallies))
            if not asked:
                raise SkipRestOfInputTableException

        def terminate(self):
            for m, group in (self.groups or {}).items():
                if not _decided(group.tallies):
                    for t in group.tallies:
                        t.close()
                verdict = all(bool(t.verdict) for t in group.tallies) if group.kept else None
                yield m, self.g, verdict, group.seen, group.tallies[0].hits, group.calls, group.tokens, group.tallies[0].settled_by or "bound", group.sample

    return RunGroup


def _fold(groups: DataFrame, outers: list) -> DataFrame:
    """Verdicts of the groups at all keys (columns m, keys and verdict) folded up to those of the outermost level's groups."""
    for i in range(len(outers) - 1, 0, -1):
        test, upper = outers[i][0], list(outers[i - 1][1])
        counted = groups.groupBy("m", *upper).agg(F.count_if("verdict").alias("_h"), F.count(F.lit(1)).alias("_n"))
        groups = counted.select("m", *upper, test.verdict(F.col("_h"), F.col("_n")).alias("verdict"))
    return groups


def _run_groups(claim: Claim, df: DataFrame, models: list[SemanticModel], p: Plan) -> list[Result]:
    options, form, spark = p.options, claim.form, df.sparkSession
    keys, inner, outers = [], form, []
    while isinstance(inner, Nested):
        keys += inner.keys
        outers.append((inner.outer, tuple(keys)))
        inner = inner.inner
    columns = _needed(claim)
    evaluators = _evaluators(claim, models, options)
    if options.group_exec == "hash" or not options.early_stop:
        return _run_hashed_groups(claim, df, models, p, columns, keys, inner, outers)
    g = F.to_json(F.struct(*keys), {"ignoreNullFields": "false"})
    ordered = _needed_frame(df, columns, tuple(keys))
    if p.inner_order == "relevance" or p.outer_order == "relevance":
        scores = relevance.relevance_scores(df, "tid", RELATIONS[claim.relation][1], relevance.spec_for(inner.phi), options.rrf_k)
        ordered = written(ordered.join(scores.select("tid", "rel_score"), "tid"), "scored")
    sizes = ordered.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), *([F.max("rel_score").alias("best")] if p.outer_order == "relevance" else []))
    sizes = written(sizes.withColumn("g", g), "group-sizes")
    hashed = F.xxhash64(F.lit(options.seed), F.col("g")).asc()
    places = {"relevance": [F.col("best").desc()] if p.outer_order == "relevance" else [], "none": []}.get(p.outer_order, [hashed])
    sizes = ranking.global_position(sizes, [*places, F.col("g").asc()], "gpos")
    m = sizes.count()
    p = plan(claim, options, m)
    within = {"estimate": F.xxhash64(F.lit(options.seed), F.col("tid")).cast("double"), "relevance": -F.col("rel_score") if p.inner_order == "relevance" else None}.get(p.inner_order, F.col("tid").cast("double"))
    ordered = ordered.withColumn("k", within)
    flat = len(outers) == 1
    results = [Result(claim.claim_id, False, "", 0, 0, m, plan=p) for _ in models]
    tallies = [Tally(outers[0][0], m if flat and claim.semantic_scope is None else None, p.alpha_outer if flat else None, options.eps, flat) for _ in models]
    name = f"run_groups_{uuid.uuid4().hex}"  # names of a session, which other runs share

    def answered(low: int, high: int, active: list[int]) -> DataFrame:
        chosen = sizes.filter((F.col("gpos") >= low) & (F.col("gpos") < high)).select(*keys, "n", "g", "gpos")
        ordered.join(chosen, keys).createOrReplaceTempView(f"{name}_wave")
        spark.udtf.register(name, _group_function({x: evaluators[x] for x in active}, inner, p.alpha_inner, options, columns))
        got = spark.sql(f"SELECT * FROM {name}(TABLE(SELECT * FROM {name}_wave) PARTITION BY g ORDER BY (k, tid))")
        return written(got.join(sizes.select("g", "gpos", *keys), "g"), "group-wave")

    if flat:
        wave, low = max(options.batch, 32), 0
        while low < m and (active := [x for x, t in enumerate(tallies) if not t.settled]):
            for row in answered(low, low + wave, active).select("m", "g", "gpos", "verdict", "seen", "calls", "tokens", "sample").toPandas().sort_values("gpos").itertuples():
                result, outer = results[row.m], tallies[row.m]
                result.calls += int(row.calls)
                result.tokens_in += int(row.tokens)
                if outer.settled:
                    result.overshoot += int(row.seen)
                    continue
                result.seen += int(row.seen)
                if row.verdict is None:
                    continue
                outer.push([bool(row.verdict)])
                result.tokens += [(row.g, int(x) if x >= 0 else -int(x) - 1, 1 if x >= 0 else -1) for x in row.sample[: max(0, SAMPLE_TOKENS - len(result.tokens))]]
            low, wave = low + wave, min(wave * options.growth, options.max_wave)
        for result, outer in zip(results, tallies, strict=True):
            result.verdict = outer.close()
            result.settled_by, result.hits, result.lo, result.hi = outer.settled_by or "exhausted", outer.hits, outer.lo, outer.hi
    else:  # deeper levels fold up over all groups' verdicts
        got = answered(0, m, list(range(len(models))))
        costs = _by_model(got, models, F.sum("calls").alias("calls"), F.sum("tokens").alias("tokens"), F.sum("seen").alias("seen"))
        tops = _by_model(_fold(got.filter(F.col("verdict").isNotNull()).select("m", *keys, "verdict"), outers), models, F.count_if("verdict").alias("h"), F.count(F.lit(1)).alias("n"))
        for result, cost, top in zip(results, costs, tops, strict=True):
            result.calls, result.tokens_in, result.seen, result.hits = cost["calls"] or 0, cost["tokens"] or 0, cost["seen"] or 0, top["h"]
            result.verdict, result.settled_by = bool(outers[0][0].verdict(top["h"], top["n"])), "exhausted"
    spark.catalog.dropTempView(f"{name}_wave")
    for result in results:
        result.complete, result.tokens_out = result.settled_by != "interval", result.calls * ANSWER_TOKENS
    return results


def _run_hashed_groups(claim: Claim, df: DataFrame, models: list[SemanticModel], p: Plan, columns: list[str], keys: list[str], inner: Quantified, outers: list) -> list[Result]:
    """Every row is answered; groups of all levels are aggregates, pre-aggregated where the rows are."""
    answers = written(_answered(df, _evaluators(claim, models, p.options), columns, tuple(keys)), "answers")
    costs = _by_model(answers, models, F.sum("calls").alias("calls"), F.sum("tokens").alias("tokens"), F.count(F.lit(1)).alias("n"))
    hits = [F.count_if(_bit(i)).alias(f"_h{i}") for i in range(len(inner.tallies))]
    groups = answers.filter("keep").groupBy("m", *keys).agg(F.count(F.lit(1)).alias("_n"), *hits)
    ok = F.lit(True)
    for i, (test, _) in enumerate(inner.tallies):
        ok = ok & test.verdict(F.col(f"_h{i}"), F.col("_n"))
    tops = _by_model(_fold(groups.select("m", *keys, ok.alias("verdict")), outers), models, F.count_if("verdict").alias("h"), F.count(F.lit(1)).alias("n"))
    return [
        Result(claim.claim_id, bool(outers[0][0].verdict(top["h"], top["n"])), "exhausted", cost["n"], top["h"], top["n"], calls=cost["calls"] or 0, tokens_in=cost["tokens"] or 0, tokens_out=(cost["calls"] or 0) * ANSWER_TOKENS, plan=p)
        for cost, top in zip(costs, tops, strict=True)
    ]


def _run_rank(claim: Claim, df: DataFrame, models: list[SemanticModel], p: Plan) -> list[Result]:
    """Every row of every group is needed: one fused pass, then a hash aggregation, then one row per group is ranked."""
    form, options = claim.form, p.options
    columns, keys = _needed(claim), list(form.keys)
    as_rows = Claim(claim.claim_id, claim.relation, Quantified(EXISTS, form.phi), claim.scope, claim.semantic_scope)
    answered = written(_answered(df, _evaluators(as_rows, models, options), columns, tuple(keys)).withColumn("hit", _bit(0)), "answers")
    costs = _by_model(answered, models, F.sum("calls").alias("calls"), F.sum("tokens").alias("tokens"), F.count(F.lit(1)).alias("n"))
    from sparkverdict.functions.truth import Pred

    hit = Pred("hit", lambda: F.col("hit"), "hit", lambda r: r["hit"], ("hit",))
    ranked = rank_groups(answered.filter("keep"), RankIs(form.keys, form.target, form.rank, hit, form.by, form.descending), ("m",))
    at = None
    for k, v in zip(form.keys, form.target, strict=True):
        at = (F.col(k) == v) if at is None else at & (F.col(k) == v)
    found = {r["m"]: r for r in ranked.filter(at).collect()}  # one row per model
    out = []
    for m, cost in enumerate(costs):
        row, calls = found.get(m), cost["calls"] or 0
        out.append(Result(claim.claim_id, row is not None and row["rank"] == form.rank, "exhausted", cost["n"], row["hits"] if row else 0, row["seen"] if row else 0, calls=calls, tokens_in=cost["tokens"] or 0, tokens_out=calls * ANSWER_TOKENS, plan=p))
    return out


def _identified(claim: Claim, rows: DataFrame) -> tuple[DataFrame, int]:
    """Rows with an id that tells them apart, and their number."""
    counts = rows.agg(F.count(F.lit(1)).alias("n"), F.count("tid").alias("keyed"), F.count_distinct("tid").alias("distinct")).first()
    if counts["keyed"] == counts["distinct"] == counts["n"]:
        return rows, counts["n"]
    return written(rows.withColumn("tid", F.monotonically_increasing_id()), "identified"), counts["n"]


def _after_filter(claim: Claim, rows: DataFrame, options: VerifyOptions, model: SemanticModel, p: Plan) -> Result:
    """The semantic filter runs over every row first; what it keeps is a relation of known size, over which the rest runs."""
    rows, _ = _identified(claim, rows)
    if p.similarity:
        near = relevance.prefilter(rows, RELATIONS[claim.relation][1], relevance.spec_for(claim.semantic_scope), options.threshold)
        rows = rows.join(written(near.select("tid"), "similar"), "tid", "left_semi")
    asks = Claim(claim.claim_id, claim.relation, Quantified(EXISTS, claim.semantic_scope))
    asked = written(_answered(rows, _evaluators(asks, [model], options), _needed(asks)), "filtered")
    spent = asked.agg(F.sum("calls").alias("calls"), F.sum("tokens").alias("tokens")).first()
    kept = written(rows.join(asked.filter(_bit(0)).select("tid"), "tid", "left_semi").drop("tid"), "kept")
    result = verify_each(replace(claim, scope=None, semantic_scope=None), kept, options, [model])[0]
    result.calls += spent["calls"] or 0
    result.tokens_in += spent["tokens"] or 0
    result.tokens_out, result.plan = result.calls * ANSWER_TOKENS, p
    return result


def verify(claim: Claim, df: DataFrame, options: VerifyOptions = VerifyOptions(), model: SemanticModel | None = None) -> Result:
    """Checks a claim over its relation. With every option off each row meets each semantic test."""
    return verify_each(claim, df, options, [model or RuleModel()])[0]


def verify_each(claim: Claim, df: DataFrame, options: VerifyOptions, models: list[SemanticModel]) -> list[Result]:
    """The same for several models (a bounded list: their settled waves come to the driver), one result each."""
    ship_package(df.sparkSession)
    p = plan(claim, options)
    rows = df.withColumn("tid", tuple_id(claim.relation))
    if claim.scope is not None:
        rows = rows.filter(claim.scope.safe())
    if options.cardinality == "after_filter" and claim.semantic_scope is not None and not isinstance(claim.form, RankIs):
        return [_after_filter(claim, rows, options, model, p) for model in models]
    if isinstance(claim.form, RankIs) and not p.similarity:
        return _run_rank(claim, rows, models, p)
    rows, size = _identified(claim, rows)
    if p.similarity:
        near = relevance.prefilter(rows, RELATIONS[claim.relation][1], relevance.spec_for(claim.semantic_scope), options.threshold)
        rows = rows.join(written(near.select("tid"), "similar"), "tid", "left_semi")  # sentences are compared once
    if isinstance(claim.form, RankIs):
        return _run_rank(claim, rows, models, p)
    if isinstance(claim.form, Nested):
        return _run_groups(claim, rows, models, p)
    if not options.early_stop and not options.top_k:
        return _run_all_rows(claim, rows, models, p)
    return _run_rows(claim, rows, models, p, size if p.size_known else None)


def as_frame(spark: SparkSession, result: Result) -> DataFrame:
    return spark.createDataFrame([(result.claim_id, bool(result.verdict))], "claim_id string, verdict boolean")


def reference(claim: Claim, df: DataFrame) -> DataFrame:
    """Which rows of the domain hit, by columns alone: tid, group keys and hit."""
    form = claim.form
    keys: list[str] = []
    while isinstance(form, Nested):
        keys += form.keys
        form = form.inner
    keys += list(form.keys) if isinstance(form, RankIs) else []
    return domain(claim, df).select(tuple_id(claim.relation).alias("tid"), *keys, form.phi.safe().alias("hit"))
