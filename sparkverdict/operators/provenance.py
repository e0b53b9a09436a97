"""Citations: one minimal set of signed row tokens that explains a verdict.

Every row of the domain gives a positive token if it hits and a negative one if not. A true sentence is explained by a
monomial of its provenance polynomial, a false one by a monomial of its negation's. Tables of tokens are DataFrames
(claim_id, grp, tuple_id, sign), evaluated where they are used; explanations of as many tokens as rows stay distributed.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace
from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from sparkverdict.operators.engine import Result, reference
from sparkverdict.plans.claims import Claim, Nested, Quantified, RankIs, Test, holds

Monomial = frozenset


# --- the interpreter: formulas over a handful of rows, the oracle of the rules below ---


@dataclass(frozen=True)
class Lit:
    row: int
    positive: bool


@dataclass(frozen=True)
class And:
    parts: tuple


@dataclass(frozen=True)
class Or:
    parts: tuple


@dataclass(frozen=True)
class Not:
    part: object


def push_negation(f, negate: bool = False):
    """Negations move down to the literals."""
    if isinstance(f, Not):
        return push_negation(f.part, not negate)
    if isinstance(f, Lit):
        return Lit(f.row, f.positive ^ negate)
    parts = tuple(push_negation(p, negate) for p in f.parts)
    return Or(parts) if isinstance(f, And) == negate else And(parts)


def polynomial(f, bits: list[bool]) -> set[Monomial]:
    """The monomials of a formula without negation under the rows' bits; the empty set is 0, {{}} is 1. Absorption keeps the minimal."""
    if isinstance(f, Lit):
        return {frozenset([(f.row, 1 if f.positive else -1)])} if bits[f.row] == f.positive else set()
    if isinstance(f, Or):
        out = set().union(*[polynomial(p, bits) for p in f.parts]) if f.parts else set()
    else:
        out = {frozenset()}
        for p in f.parts:
            out = {a | b for a in out for b in polynomial(p, bits)}
    return {m for m in out if not any(o < m for o in out)}


def formula(test: Test, rows: list[int]):
    """The first-order sentence of a test over the given rows. "At least" is a sum over subsets of hits; the comparisons that
    look down or at one number are sums over exact sets: these rows hit and all others do not."""
    if test.kind == "exists":
        return Or(tuple(Lit(r, True) for r in rows))
    if test.kind == "forall":
        return And(tuple(Lit(r, True) for r in rows))
    n = len(rows)
    k = test.value if test.kind == "count" else test.value * n
    if test.op in (">=", ">"):
        least = max(0, math.ceil(k) if test.op == ">=" else math.floor(k) + 1)
        return Or(tuple(And(tuple(Lit(r, True) for r in c)) for c in combinations(rows, least)))
    sizes = [j for j in range(n + 1) if holds(test.op, j, k)]
    return Or(tuple(And(tuple(Lit(r, r in c) for r in rows)) for j in sizes for c in combinations(rows, j)))


_OPPOSITE = {">=": "<", ">": "<=", "<": ">=", "<=": ">", "==": "!=", "!=": "=="}


def explanations(test: Test, bits: list[bool]) -> tuple[bool, set[Monomial]]:
    """The verdict and all minimal explanations of it: monomials of the sentence, or of its negation where it is false."""
    rows = list(range(len(bits)))
    true = polynomial(push_negation(formula(test, rows)), bits)
    if true:
        return True, true
    if test.kind in ("exists", "forall"):
        return False, polynomial(push_negation(Not(formula(test, rows))), bits)
    return False, polynomial(push_negation(formula(replace(test, op=_OPPOSITE[test.op]), rows)), bits)


# --- the rules, as what to take from the rows in their order ---


def rule(test: Test, verdict: bool, hits: int, seen: int) -> tuple[int, int]:
    """How many positive and how many negative tokens explain the verdict. -1 stands for all of the rows seen: a count that
    was reached is shown by as many hits, a count that was not, and an exact one, by every row."""
    if test.kind == "exists":
        return (1, 0) if verdict else (0, -1)
    if test.kind == "forall":
        return (-1, 0) if verdict else (0, 1)
    if test.op in ("==", "!=") or verdict != (test.op in (">=", ">")):
        return -1, -1
    k = test.value if test.kind == "count" else test.value * seen
    # what is shown to be reached: at least k by a true >= and a false <, more than k by a true > and a false <=
    return max(0, math.ceil(k) if test.op in (">=", "<") else math.floor(k) + 1), 0


def _take(rows: DataFrame, partition: list[str], positives: Column, negatives: Column) -> DataFrame:
    """The first so many rows of each sign, in the order of tid, within each partition."""
    order = Window.partitionBy(*partition, "hit").orderBy("tid")
    n = F.when(F.col("hit"), positives).otherwise(negatives)
    return rows.withColumn("_n", n).filter(F.col("_n") != 0).withColumn("_r", F.row_number().over(order)).filter((F.col("_n") < 0) | (F.col("_r") <= F.col("_n"))).drop("_r", "_n")


def _tokens(claim: Claim, rows: DataFrame, grp: Column) -> DataFrame:
    return rows.select(F.lit(claim.claim_id).alias("claim_id"), grp.cast("string").alias("grp"), F.col("tid").alias("tuple_id"), F.when(F.col("hit"), 1).otherwise(-1).cast("tinyint").alias("sign"))


def cite(claim: Claim, df: DataFrame) -> DataFrame:
    """Tokens of one explanation of the claim's verdict over its whole relation, from columns alone. cite_run() takes them
    from what a run has answered."""
    form, rows = claim.form, reference(claim, df)
    if isinstance(form, Quantified):
        counts = rows.agg(F.count_if("hit").alias("h"), F.count(F.lit(1)).alias("n")).first()
        p, n = rule(form.test, bool(form.test.verdict(counts["h"], counts["n"])), counts["h"], counts["n"])
        return _flat(claim, rows, p, n, "tid")
    if isinstance(form, RankIs):
        return _cite_rank(claim, form, rows)
    return _cite_nested(claim, form, rows)


def _flat(claim: Claim, rows: DataFrame, p: int, n: int, order: str) -> DataFrame:
    """p positive and n negative tokens, first in the given order; -1: all of that sign."""
    if p < 0 and n < 0:
        return _tokens(claim, rows, F.lit(None))
    if (p, n) in ((-1, 0), (0, -1)):
        return _tokens(claim, rows.filter(F.col("hit") == (p < 0)), F.lit(None))
    # the first so many: a limit over sorted rows of one sign, never a single-task sort of all
    return _tokens(claim, rows.filter(F.col("hit") == (p > 0)).orderBy(order).limit(max(p, n)), F.lit(None))


def cite_run(claim: Claim, result: Result) -> DataFrame:
    """Tokens of an ungrouped claim from the answers its run has written: no row is asked again, and none is cited that the
    run did not reach. A verdict that an interval settled is shown by the whole sample on its side."""
    if not isinstance(claim.form, Quantified) or result.answers is None:
        raise ValueError("only runs over the rows of an ungrouped claim leave answers")
    rows, test = result.answers, claim.form.test
    p, n = rule(test, result.verdict, result.hits, result.seen)
    if result.settled_by == "interval" and p > 0:
        p = -1
    return _flat(claim, rows, p, n, "pos")


def _cite_nested(claim: Claim, form: Nested, rows: DataFrame) -> DataFrame:
    """Any depth: verdicts fold up level by level, then each level's rule chooses among the groups (at last, the rows) of
    those that the level above has chosen."""
    levels, inner, keys = [], form, []
    while isinstance(inner, Nested):
        keys = [*keys, *inner.keys]
        levels.append((list(keys), inner.outer))
        inner = inner.inner
    count = [F.count_if("ok").alias("h"), F.count(F.lit(1)).alias("n")]
    at = rows.groupBy(*keys).agg(F.count_if("hit").alias("h"), F.count(F.lit(1)).alias("n"))
    at = at.withColumn("ok", inner.test.verdict(F.col("h"), F.col("n")))
    tables = [(keys, inner.test, at)]
    for (upper, _), (_, test) in zip(levels[-2::-1], levels[:0:-1], strict=True):
        at = at.groupBy(*upper).agg(*count).withColumn("ok", test.verdict(F.col("h"), F.col("n")))
        tables.insert(0, (upper, test, at))
    total = at.agg(*count).first()
    p, n = rule(form.outer, bool(form.outer.verdict(total["h"], total["n"])), total["h"], total["n"])
    top, test, at = tables[0]
    chosen = _first(at, [], top, "ok", F.lit(p), F.lit(n))
    for lower, next_test, below in tables[1:]:
        pos, neg = _rule_columns(test)
        wanted = chosen.select(*top, pos.alias("_p"), neg.alias("_q"))
        chosen = _first(below.join(wanted, top), top, lower, "ok", F.col("_p"), F.col("_q")).drop("_p", "_q")
        top, test = lower, next_test
    pos, neg = _rule_columns(test)
    wanted = chosen.select(*top, pos.alias("_p"), neg.alias("_q"))
    return _tokens(claim, _first(rows.join(wanted, top), top, ["tid"], "hit", F.col("_p"), F.col("_q")), F.concat_ws("/", *[F.col(k).cast("string") for k in top]))


def _first(rows: DataFrame, within: list[str], order: list[str], sign: str, positives: Column, negatives: Column) -> DataFrame:
    """The first so many rows of each sign within each group; without a group there is one row per group of the top level."""
    place = Window.partitionBy(*within, sign).orderBy(*order)
    n = F.when(F.col(sign), positives).otherwise(negatives)
    return rows.withColumn("_n", n).filter(F.col("_n") != 0).withColumn("_r", F.row_number().over(place)).filter((F.col("_n") < 0) | (F.col("_r") <= F.col("_n"))).drop("_r", "_n")


def _rule_columns(test: Test) -> tuple[Column, Column]:
    """rule() as columns over h, n, ok of a group."""
    ok, n = F.col("ok"), F.col("n")
    zero, every = F.lit(0).cast("long"), F.lit(-1).cast("long")
    if test.kind == "exists":
        return F.when(ok, 1).otherwise(zero), F.when(ok, zero).otherwise(every)
    if test.kind == "forall":
        return F.when(ok, every).otherwise(zero), F.when(ok, zero).otherwise(1)
    if test.op in ("==", "!="):
        return every, every
    num, den = test.value.numerator, test.value.denominator
    top = F.lit(num) if test.kind == "count" else n * num
    floor, exact = F.floor(top / den), (top % den) == 0
    j = F.when(exact, floor).otherwise(floor + 1) if test.op in (">=", "<") else floor + 1
    reached = ok if test.op in (">=", ">") else ~ok
    return F.when(reached, F.greatest(j, zero)).otherwise(every), F.when(reached, zero).otherwise(every)


def _cite_rank(claim: Claim, form: RankIs, rows: DataFrame) -> DataFrame:
    """The comparisons of the target group with each other group: the larger side shows more hits than the smaller one's
    value, the smaller side shows no more than its value; equal sides show all. Shares scale by each group's own size."""
    keys = list(form.keys)
    value = F.col("h") / F.col("n") if form.by == "share" else F.col("h").cast("double")
    groups = rows.groupBy(*keys).agg(F.count_if("hit").alias("h"), F.count(F.lit(1)).alias("n")).withColumn("v", value)
    is_target = None
    for k, t in zip(keys, form.target, strict=True):
        is_target = (F.col(k) == t) if is_target is None else is_target & (F.col(k) == t)
    target = groups.filter(is_target).select(F.col("h").alias("th"), F.col("n").alias("tn"), F.col("v").alias("tv"))
    # target is one row
    both = groups.filter(~is_target).join(F.broadcast(target), how="cross")
    scale = F.col("n") if form.by == "share" else F.lit(1)
    t_scale = F.col("tn") if form.by == "share" else F.lit(1)
    # a group above the target cites more hits than the target's value makes of its size; one below cites its misses down to that
    # products before quotients: a share times a size may fall just short of a whole number
    level, own_level = (F.col("th") * scale / t_scale, F.col("h") * t_scale / scale) if form.by == "share" else (F.col("th"), F.col("h"))
    bar = F.floor(level)
    above, below = F.col("v") > F.col("tv"), F.col("v") < F.col("tv")
    need = both.select(*keys, F.when(above, bar + 1).when(below, F.lit(0)).otherwise(F.lit(-1)).cast("long").alias("p"), F.when(above, F.lit(0)).when(below, F.col("n") - F.ceil(level) + 1).otherwise(F.lit(-1)).cast("long").alias("q"))
    mine = both.agg(
        F.max(F.when(below, F.floor(own_level) + 1)).alias("p"),
        F.max(F.when(above, F.col("tn") - F.ceil(own_level) + 1)).alias("q"),
        F.bool_or(F.col("v") == F.col("tv")).alias("same"),
    )
    own = mine.select(*[F.lit(t).alias(k) for k, t in zip(keys, form.target, strict=True)], F.when(F.col("same"), -1).otherwise(F.coalesce("p", F.lit(0))).cast("long").alias("p"), F.when(F.col("same"), -1).otherwise(F.coalesce("q", F.lit(0))).cast("long").alias("q"))
    chosen = rows.join(need.union(own), keys)
    return _tokens(claim, _take(chosen, keys, F.col("p"), F.col("q")), F.concat_ws("/", *[F.col(k).cast("string") for k in keys]))
