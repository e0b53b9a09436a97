"""The query builder: immutable frames of filters, maps, aggregates, ranks and a check; and the compiler of logical forms.

A frame keeps its columns and its logical steps. `collect()` runs the columns (the naive engine). `collect(options, model)`
turns the steps into a claim and gives it to the engine, which stops early, estimates, fuses and cites; it works over any
DataFrame. Comparisons of an aggregate's value, written behind the aggregate, are pushed into it there: the engine's tallies
know the test that they may stop on. `compile_claim` goes from a structured claim text to a claim.

Defined cases: a null row attribute makes a test false; a filter, test or value of null counts as false; typed answers that do
not fit their type are null (`bad_answers` counts them); steps that no claim form has (`claim()` names them) run as columns only;
tables without rows, repeated rows and rows without a key are handled by the engine as stated there.
"""

from __future__ import annotations

import re
import uuid
from dataclasses import dataclass, field, replace
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from sparkverdict.functions.truth import Pred
from sparkverdict.plans.claims import EXISTS, FORALL, Claim, Nested, Quantified, RankIs, Test, count, share


@dataclass(frozen=True)
class Prompt:
    """A semantic expression: a template over attributes, answered by a registered test; or, for other types than boolean
    ('string', 'bigint', 'double', or a tuple of the allowed words), by a reply that is checked against the type."""

    template: str
    pred: Pred | None = None
    returns: str | tuple[str, ...] = "boolean"
    reply: Column | None = None

    def check(self, columns: list[str]) -> None:
        missing = [c for c in re.findall(r"\{(\w+)\}", self.template) if c not in columns]
        if missing:
            raise ValueError(f"prompt names attributes that the relation lacks: {missing}")
        if (self.pred is None) != (self.returns != "boolean" and self.reply is not None):
            raise ValueError("a boolean prompt needs a test, any other a reply")

    def render(self) -> Column:
        parts = re.split(r"\{(\w+)\}", self.template)
        return F.concat(*[F.coalesce(F.col(p).cast("string"), F.lit("")) if i % 2 else F.lit(p) for i, p in enumerate(parts)])

    def value(self) -> Column:
        if self.pred is not None:
            return self.pred.safe()
        return typed(self.reply, self.returns)


def typed(reply: Column, returns: str | tuple[str, ...]) -> Column:
    """A model's reply as a value of the type: white space around it and the case of allowed words do not matter."""
    text = F.trim(reply.cast("string"))
    if isinstance(returns, str):
        return text if returns == "string" else text.try_cast(returns)
    out = F.lit(None).cast("string")
    for word in returns:
        out = F.when(F.lower(text) == word.lower(), F.lit(word)).otherwise(out)
    return out


def bad_answers(df: DataFrame, reply: Column, returns: str | tuple[str, ...]) -> DataFrame:
    """asked, bad: replies, and those of them that are no value of the type."""
    return df.agg(F.count(F.lit(1)).alias("asked"), F.count_if(typed(reply, returns).isNull()).alias("bad"))


@dataclass(frozen=True)
class Compare:
    """A comparison of an aggregate's value with a constant; `both` holds further ones that must hold too."""

    name: str
    op: str
    value: Fraction | bool
    both: tuple[Compare, ...] = ()

    def __and__(self, other: Compare) -> Compare:
        return replace(self, both=(*self.both, replace(other, both=()), *other.both))

    def parts(self) -> tuple[Compare, ...]:
        return (replace(self, both=()), *self.both)


@dataclass(frozen=True, eq=False)
class Ref:
    """A value that an earlier step named."""

    name: str

    def _with(self, op: str, value) -> Compare:
        return Compare(self.name, op, value if isinstance(value, bool) else Fraction(str(value)) if not isinstance(value, Fraction) else value)

    def __ge__(self, v) -> Compare:
        return self._with(">=", v)

    def __gt__(self, v) -> Compare:
        return self._with(">", v)

    def __le__(self, v) -> Compare:
        return self._with("<=", v)

    def __lt__(self, v) -> Compare:
        return self._with("<", v)

    def __eq__(self, v) -> Compare:  # type: ignore[override]
        return self._with("==", v)

    def __ne__(self, v) -> Compare:  # type: ignore[override]
        return self._with("!=", v)


ref = Ref


@dataclass(frozen=True)
class Agg:
    """An aggregate of a boolean that an earlier step named: 'exists', 'forall', 'count' or 'share'."""

    kind: str
    of: str

    def column(self) -> Column:
        e = F.col(self.of)
        return {"exists": any_true, "forall": all_true, "count": lambda x: F.count_if(F.coalesce(x, F.lit(False))), "share": proportion}[self.kind](e)

    def test(self, cmp: Compare) -> Test:
        if self.kind in ("exists", "forall"):
            if cmp.value is not True or cmp.op != "==":
                raise NotImplementedError(f"a comparison of a truth value but with true: {cmp}")
            return EXISTS if self.kind == "exists" else FORALL
        return Test(self.kind, cmp.op, cmp.value)

    def compared(self, cmp: Compare) -> Column:
        value = F.col(cmp.name)
        if self.kind in ("exists", "forall"):
            return value == F.lit(cmp.value)
        return self.test(cmp).verdict(value["hits"], value["seen"]) if self.kind == "share" else self.test(cmp).verdict(value, None)


def some(of: str) -> Agg:
    return Agg("exists", of)


def every(of: str) -> Agg:
    return Agg("forall", of)


def how_many(of: str) -> Agg:
    return Agg("count", of)


def portion(of: str) -> Agg:
    return Agg("share", of)


Expr = Column | Prompt | Compare | Ref


@dataclass(frozen=True)
class VerifyFrame:
    df: DataFrame
    steps: tuple[str, ...] = ()
    #: The relation before the first step, its key (none: the engine numbers rows) and text, and the steps as data.
    source: DataFrame | None = None
    key: tuple[str, ...] = ()
    text: str | None = None
    relation: str = ""
    ops: tuple[tuple, ...] = ()
    known: dict[str, Agg] = field(default_factory=dict)

    @staticmethod
    def over(df: DataFrame, key: tuple[str, ...] = (), text: str | None = None) -> VerifyFrame:
        """A frame over any DataFrame; `key` is one whole-number column, or none."""
        if len(key) > 1:
            raise ValueError("one key column, or none")
        first = next((f.name for f in df.schema if isinstance(f.dataType, StringType)), None)
        return VerifyFrame(df, (), df, tuple(key), text or first, f"frame_{uuid.uuid4().hex}")

    def _column(self, e: Expr) -> Column:
        if isinstance(e, Prompt):
            e.check(self.df.columns)
            return e.value()
        if isinstance(e, Ref):
            return F.col(e.name)
        if isinstance(e, Compare):
            out = None
            for c in e.parts():
                one = self.known[c.name].compared(c) if c.name in self.known else Test("count", c.op, c.value).verdict(F.col(c.name), None)
                out = one if out is None else out & one
            return out
        return e

    def _then(self, df: DataFrame, step: str, *op, **changes) -> VerifyFrame:
        return replace(self, df=df, steps=(*self.steps, step), ops=(*self.ops, op), **changes)

    def filter(self, e: Expr) -> VerifyFrame:
        return self._then(self.df.filter(F.coalesce(self._column(e), F.lit(False))), f"filter {_name(e)}", "filter", e)

    def map(self, e: Expr, name: str) -> VerifyFrame:
        return self._then(self.df.withColumn(name, self._column(e)), f"map {name} = {_name(e)}", "map", e, name)

    def aggregate(self, aggs: dict[str, Column | Agg], group_by: tuple[str, ...] = ()) -> VerifyFrame:
        columns = [(a.column() if isinstance(a, Agg) else a).alias(n) for n, a in aggs.items()]
        known = {n: a for n, a in aggs.items() if isinstance(a, Agg)}
        return self._then(self.df.groupBy(*group_by).agg(*columns), f"aggregate {', '.join(aggs)} by {', '.join(group_by) or '-'}", "aggregate", aggs, tuple(group_by), known=known)

    def with_rank(self, e: Column | Ref, descending: bool = True, name: str = "rank") -> VerifyFrame:
        value = self._column(e)
        if isinstance(e, Ref) and e.name in self.known and self.known[e.name].kind == "share":
            value = value["hits"] / value["seen"]
        return self._then(self.df.withColumn(name, F.dense_rank().over(Window.orderBy(value.desc() if descending else value.asc()))), f"rank by {_name(e)}", "rank", e, descending, name)

    def at(self, **values) -> VerifyFrame:
        """The group with these key values."""
        df = self.df
        for k, v in values.items():
            df = df.filter(F.col(k) == F.lit(v))
        return self._then(df, f"at {values}", "at", values)

    def check(self, e: Expr) -> VerifyFrame:
        return self._then(self.df.withColumn("verdict", F.coalesce(self._column(e), F.lit(False))), f"check {_name(e)}", "check", e)

    def claim(self) -> tuple[Claim, DataFrame]:
        """The steps as a claim and the relation that it is about. Steps without a place in a claim raise NotImplementedError."""
        rows, preds, semantic, levels, bits, rank, target, final = self.source, {}, None, [], {}, None, {}, None
        if rows is None:
            raise NotImplementedError("the frame was not made by VerifyFrame.over")
        for op, *args in self.ops:
            if op == "filter" and not levels and isinstance(args[0], Prompt) and args[0].pred is not None:
                semantic = args[0].pred if semantic is None else semantic & args[0].pred
            elif op == "filter" and not levels and isinstance(args[0], Column) and not preds:
                rows = rows.filter(F.coalesce(args[0], F.lit(False)))
            elif op == "map" and not levels and isinstance(args[0], Prompt) and args[0].pred is not None:
                preds[args[1]] = args[0].pred
            elif op == "map" and not levels and isinstance(args[0], Column | Prompt) and not preds:
                rows = rows.withColumn(args[1], self._column(args[0]) if isinstance(args[0], Column) else args[0].value())
            elif op == "map" and levels and isinstance(args[0], Compare):
                bits[args[1]] = (len(levels) - 1, args[0])
            elif op == "aggregate" and all(isinstance(a, Agg) for a in args[0].values()):
                levels.append(tuple(args))
            elif op == "rank" and len(levels) == 1 and isinstance(args[0], Ref):
                rank = args
            elif op == "at" and rank:
                target |= args[0]
            elif op == "check" and isinstance(args[0], Compare | Ref):
                final = args[0] if isinstance(args[0], Compare) else args[0] == True  # noqa: E712
            else:
                raise NotImplementedError(f"no claim form has the step {op} {args}")
        if final is None or not levels:
            raise NotImplementedError("a claim ends with a check of an aggregate")
        if rank:
            (aggs, keys), (by, descending, name) = levels[0], rank
            if final.both or final.name != name or final.op != "==" or set(target) != set(keys):
                raise NotImplementedError("a rank claim checks one group's rank for one value")
            agg = aggs[by.name]
            form = RankIs(keys, tuple(target[k] for k in keys), int(final.value), preds[agg.of], agg.kind, descending)
        else:
            tests = []  # of each level, from the rows out
            for i, (aggs, _) in enumerate(levels):
                cmp = final if i == len(levels) - 1 else next((c for at, c in (bits[a.of] for a in levels[i + 1][0].values()) if at == i), None)
                tests.append([(aggs[c.name].test(c), aggs[c.name].of) for c in cmp.parts()])
            if any(len(t) > 1 for t in tests[1:]) or levels[-1][1]:
                raise NotImplementedError("outer levels have one test, and the last has no keys")
            first = tests[0]
            form = Quantified(first[0][0], preds[first[0][1]], tuple((t, preds[n]) for t, n in first[1:]))
            for i in range(1, len(levels)):
                form = Nested(tests[i][0][0], tuple(k for k in levels[i - 1][1] if k not in levels[i][1]), form)
        return Claim(self.relation, self.relation, form, None, semantic), rows

    def collect(self, options=None, model=None):
        """Without options the columns' rows; with them the engine's result: verdict, calls, tokens to cite, and the plan."""
        if options is None:
            return self.df.collect()
        from sparkverdict.operators.engine import verify
        from sparkverdict.sources.relations import RELATIONS

        claim, rows = self.claim()
        if self.text is None:  # nothing to order or compare by
            options = options.without("relevance").without("similarity")
        RELATIONS[self.relation] = (self.key, self.text)
        return verify(claim, rows, options, model)

    def explain(self, options=None) -> str:
        lines = "\n".join(reversed(self.steps))
        if options is None:
            return lines
        from sparkverdict.plans.optimizer import plan

        return plan(self.claim()[0], options).explain() + "\n" + lines

    def plan_json(self, options) -> dict:
        """What the optimizer decided, as plain values."""
        from sparkverdict.plans.optimizer import plan

        p = plan(self.claim()[0], options)
        return {"steps": list(self.steps), **{k: getattr(p, k) for k in ("calls_per_row", "size_known", "inner_order", "outer_order", "alpha_inner", "alpha_outer", "similarity", "stops")}}


def _name(e: Expr) -> str:
    if isinstance(e, Compare):
        return " and ".join(f"{c.name} {c.op} {c.value}" for c in e.parts())
    return f"prompt({e.template!r})" if isinstance(e, Prompt) else e.name if isinstance(e, Ref) else str(e._jc.toString())


def any_true(e: Column) -> Column:
    return F.coalesce(F.bool_or(e), F.lit(False))


def all_true(e: Column) -> Column:
    return F.coalesce(F.bool_and(F.coalesce(e, F.lit(False))), F.lit(True))


def proportion(e: Column) -> Column:
    return F.struct(F.count_if(F.coalesce(e, F.lit(False))).alias("hits"), F.count(F.lit(1)).alias("seen"))


#: Vague quantifiers and the tests they stand for.
HINTS: dict[str, Test] = {
    "common": share(">=", 0.1), "handful": count(">=", 5), "multiple": count(">=", 2), "majority": share(">", Fraction(1, 2)), "most": share(">", Fraction(1, 2)),
    "minority": share("<", Fraction(1, 2)), "mixed": share(">=", Fraction(1, 5)), "some": EXISTS, "all": FORALL, "every": FORALL,
}
_WORDS = {"at least": ">=", "more than": ">", "at most": "<=", "fewer than": "<", "exactly": "==", "not exactly": "!="}


def quantifier(phrase: str, hints: dict[str, Test] = HINTS) -> Test:
    """'at least 3', 'more than 20 %', 'majority', 'no' is the caller's negation."""
    p = phrase.strip().lower()
    if p in hints:
        return hints[p]
    m = re.fullmatch(r"(at least|more than|at most|fewer than|not exactly|exactly)\s+([\d.]+)\s*(%|percent)?", p)
    if not m:
        raise ValueError(f"no quantifier: {phrase!r}")
    return share(_WORDS[m[1]], Fraction(m[2]) / 100) if m[3] else count(_WORDS[m[1]], int(m[2]))


def compile_claim(text: str, relation: str, preds: dict[str, Pred], scopes: dict[str, Pred] | None = None, columns: list[str] | None = None) -> Claim:
    """A claim in the controlled form that decomposition emits:

    '<quantifier> rows are <test>', '<quantifier> <key> have <quantifier> rows that are <test>',
    '<key> <value> ranks <n> by <count|share> of <test>', each with an optional 'among <scope>: ' in front.
    Unknown tests, scopes and keys are refused.
    """
    scope = None
    m = re.match(r"among (\w+): (.*)", text)
    if m:
        scope, text = (scopes or {})[m[1]], m[2]

    def pred(name: str) -> Pred:
        return ~preds[name.removeprefix("not ")] if name.startswith("not ") else preds[name]

    def key(name: str) -> tuple[str, ...]:
        if columns is not None and name not in columns:
            raise ValueError(f"the relation has no attribute {name!r}")
        return (name,)

    if m := re.fullmatch(r"(\w+) (\S+) ranks (\d+) by (count|share) of ((?:not )?\w+)", text):
        value = int(m[2]) if m[2].lstrip("-").isdigit() else m[2]
        form = RankIs(key(m[1]), (value,), int(m[3]), pred(m[5]), m[4])
    elif m := re.fullmatch(r"(.+?) (\w+) have (.+?) rows that are ((?:not )?\w+)", text):
        form = Nested(quantifier(m[1]), key(m[2]), Quantified(quantifier(m[3]), pred(m[4])))
    elif m := re.fullmatch(r"(.+?) rows are ((?:not )?\w+)", text):
        form = Quantified(quantifier(m[1]), pred(m[2]))
    else:
        raise ValueError(f"no claim: {text!r}")
    claim = Claim(re.sub(r"\W+", "_", text)[:60], relation, form, text=text)
    return claim.scoped(scope) if scope is not None else claim


def instructions(style: str, entity: str) -> str:
    """What a semantic aggregation is asked for."""
    return {"summarize": f"Summarize the {entity}.", "compare": f"Compare the groups of {entity}.", "rank": f"Rank the groups of {entity}."}[style]


def decompose(responses: DataFrame, key: str = "response_id", text: str = "response") -> DataFrame:
    """One row per claim of a prose response: sentences, then clauses; pronouns are resolved to the sentence's first subject."""
    sent = responses.select(key, F.posexplode(F.filter(F.split(text, r"(?<=[.!?])\s+"), lambda s: F.length(F.trim(s)) > 0)).alias("sent_no", "sent"))
    subject = F.first(F.regexp_extract("sent", r"^(\w+)", 1)).over(Window.partitionBy(key).orderBy("sent_no"))
    known = sent.withColumn("subject", subject)
    clauses = known.select(key, "sent_no", "subject", F.posexplode(F.split(F.regexp_replace("sent", r"[.!?]$", ""), r";\s+|, and ")).alias("clause_no", "clause"))
    resolved = F.when(F.col("clause").rlike("^(It|They|it|they)\\b"), F.regexp_replace("clause", r"^(It|They|it|they)\b", "")).otherwise(F.lit(None))
    return clauses.select(key, "sent_no", "clause_no", F.when(resolved.isNotNull(), F.concat("subject", resolved)).otherwise(F.col("clause")).alias("claim"))


def semantic_aggregate(df: DataFrame, text: str, summarize: str = "max_by", chunk_tokens: int = 4096, fan_in: int = 8) -> DataFrame:
    """Chunk-and-merge over a relation: rows are packed into chunks by a hash, each chunk gives one partial answer, answers
    merge fan_in at a time until one is left. The offline model keeps the longest text and counts what it read."""
    total = df.agg(F.sum(F.ceil(F.length(text) / 4))).first()[0] or 0
    chunks = max(1, -(-int(total) // chunk_tokens))
    part = df.withColumn("chunk", F.pmod(F.xxhash64(text), F.lit(chunks)))
    pick = F.max_by(text, F.struct(F.length(text), F.col(text)))
    level = part.groupBy("chunk").agg(pick.alias("answer"), F.count(F.lit(1)).alias("rows"))
    while chunks > 1:
        chunks = -(-chunks // fan_in)
        best = F.max_by("answer", F.struct(F.length("answer"), F.col("answer")))
        level = level.withColumn("chunk", F.floor(F.col("chunk") / fan_in)).groupBy("chunk").agg(best.alias("answer"), F.sum("rows").alias("rows"))
    return level.select("answer", "rows")
