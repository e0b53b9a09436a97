"""Logical forms of claims, and their evaluation as plain aggregates (the naive engine) and as SQL (its twin)."""

from __future__ import annotations

from dataclasses import dataclass, replace
from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkverdict.functions.truth import Pred

OPS = (">=", ">", "<=", "<", "==", "!=")
_SQL_OP = {"==": "=", "!=": "<>"}


def holds(op: str, a, b):
    """a op b for numbers and for columns."""
    return {">=": lambda: a >= b, ">": lambda: a > b, "<=": lambda: a <= b, "<": lambda: a < b, "==": lambda: a == b, "!=": lambda: a != b}[op]()


@dataclass(frozen=True)
class Test:
    """A quantifier over bits: exists, forall, count op k, share op p."""

    __test__ = False
    kind: str
    op: str = ">="
    value: Fraction = Fraction(1)

    def verdict(self, hits, seen):
        """Truth over a whole domain; no test of an empty domain holds but forall, counts compare zero."""
        if self.kind == "exists":
            return hits > 0
        if self.kind == "forall":
            return hits == seen
        if self.kind == "count":
            return holds(self.op, hits, int(self.value))
        out = holds(self.op, hits * self.value.denominator, seen * self.value.numerator)
        return (out & (seen > 0)) if isinstance(out, Column) else out and seen > 0

    def sql(self, hits: str, seen: str) -> str:
        op = _SQL_OP.get(self.op, self.op)
        if self.kind == "exists":
            return f"({hits} > 0)"
        if self.kind == "forall":
            return f"({hits} = {seen})"
        if self.kind == "count":
            return f"({hits} {op} {int(self.value)})"
        return f"({hits} * {self.value.denominator} {op} {seen} * {self.value.numerator} AND {seen} > 0)"


EXISTS, FORALL = Test("exists"), Test("forall")


def count(op: str, k: int) -> Test:
    return Test("count", op, Fraction(k))


def share(op: str, p: float | Fraction) -> Test:
    return Test("share", op, Fraction(str(p)) if not isinstance(p, Fraction) else p)


@dataclass(frozen=True)
class Quantified:
    """The test over the rows of the domain; several (test, pred) pairs must all hold."""

    test: Test
    phi: Pred
    also: tuple[tuple[Test, Pred], ...] = ()

    @property
    def tallies(self) -> tuple[tuple[Test, Pred], ...]:
        return ((self.test, self.phi), *self.also)


@dataclass(frozen=True)
class Nested:
    outer: Test
    keys: tuple[str, ...]
    inner: Quantified | Nested


@dataclass(frozen=True)
class RankIs:
    keys: tuple[str, ...]
    target: tuple
    rank: int
    phi: Pred
    by: str = "share"
    descending: bool = True


Form = Quantified | Nested | RankIs


@dataclass(frozen=True)
class Claim:
    claim_id: str
    relation: str
    form: Form
    scope: Pred | None = None  # symbolic
    semantic_scope: Pred | None = None
    expected: bool | None = None
    text: str = ""
    style: str = "summarize"

    def scoped(self, pred: Pred) -> Claim:
        """One more filter: in front of the others if symbolic."""
        if pred.semantic:
            return replace(self, semantic_scope=pred if self.semantic_scope is None else self.semantic_scope & pred)
        return replace(self, scope=pred if self.scope is None else self.scope & pred)


def domain(claim: Claim, df: DataFrame) -> DataFrame:
    for pred in (claim.scope, claim.semantic_scope):
        if pred is not None:
            df = df.filter(pred.safe())
    return df


def _keys(form: Form) -> list[tuple[str, ...]]:
    """Key prefixes from the outermost grouping in."""
    out, so_far = [], ()
    while isinstance(form, Nested):
        so_far += form.keys
        out.append(so_far)
        form = form.inner
    return out


def _innermost(form: Nested) -> Quantified:
    while isinstance(form, Nested):
        form = form.inner
    return form


def evaluate(claim: Claim, df: DataFrame, within: tuple[str, ...] = ()) -> DataFrame:
    """claim_id, within, verdict, hits, seen: every row meets every test. hits and seen are those of the outermost quantifier.
    Each value of `within` is a relation of its own."""
    rows, form = domain(claim, df), claim.form
    head = F.lit(claim.claim_id).alias("claim_id")
    if isinstance(form, Quantified):
        aggs = [F.count_if(p.safe()).alias(f"h{i}") for i, (_, p) in enumerate(form.tallies)]
        one = rows.groupBy(*within).agg(*aggs, F.count(F.lit(1)).alias("seen"))
        verdict = _all(t.verdict(F.col(f"h{i}"), F.col("seen")) for i, (t, _) in enumerate(form.tallies))
        return one.select(head, *within, verdict.alias("verdict"), F.col("h0").alias("hits"), "seen")
    if isinstance(form, RankIs):
        ranked = rank_groups(rows, form, within)
        found = ranked.filter(_is_target(form)).select(*within, F.col("rank"), "hits", "seen")
        at = found.groupBy(*within).agg(F.max("rank").alias("rank"), F.max("hits").alias("hits"), F.max("seen").alias("seen"))
        return at.select(head, *within, F.coalesce(F.col("rank") == form.rank, F.lit(False)).alias("verdict"), F.coalesce("hits", F.lit(0)).alias("hits"), F.coalesce("seen", F.lit(0)).alias("seen"))
    levels, inner = _keys(form), _innermost(form)
    aggs = [F.count_if(p.safe()).alias(f"h{i}") for i, (_, p) in enumerate(inner.tallies)]
    level = rows.groupBy(*within, *levels[-1]).agg(*aggs, F.count(F.lit(1)).alias("n"))
    level = level.select(*within, *levels[-1], _all(t.verdict(F.col(f"h{i}"), F.col("n")) for i, (t, _) in enumerate(inner.tallies)).alias("ok"))
    tests, f = [], form
    while isinstance(f, Nested):
        tests.append(f.outer)
        f = f.inner
    for keys, test in zip(reversed(levels[:-1]), reversed(tests[1:]), strict=True):
        level = level.groupBy(*within, *keys).agg(F.count_if("ok").alias("h"), F.count(F.lit(1)).alias("n")).select(*within, *keys, test.verdict(F.col("h"), F.col("n")).alias("ok"))
    top = level.groupBy(*within).agg(F.count_if("ok").alias("hits"), F.count(F.lit(1)).alias("seen"))
    return top.select(head, *within, tests[0].verdict(F.col("hits"), F.col("seen")).alias("verdict"), "hits", "seen")


def rank_groups(rows: DataFrame, form: RankIs, within: tuple[str, ...] = ()) -> DataFrame:
    """within, keys, hits, seen, rank: dense, one row per group; ties share a rank. Shares of equal fractions are equal doubles."""
    from pyspark.sql import Window

    groups = rows.groupBy(*within, *form.keys).agg(F.count_if(form.phi.safe()).alias("hits"), F.count(F.lit(1)).alias("seen"))
    value = F.col("hits") / F.col("seen") if form.by == "share" else F.col("hits")
    return groups.withColumn("rank", F.dense_rank().over((Window.partitionBy(*within) if within else Window).orderBy(value.desc() if form.descending else value.asc())))


def _is_target(form: RankIs) -> Column:
    return _all(F.col(k) == v for k, v in zip(form.keys, form.target, strict=True))


def _all(columns) -> Column:
    out = None
    for c in columns:
        out = c if out is None else out & c
    return out


def claim_sql(claim: Claim, source: str) -> str:
    """The same for DuckDB, from the same form, with `source` as the relation's SQL."""
    where = " AND ".join(f"coalesce({p.sql}, false)" for p in (claim.scope, claim.semantic_scope) if p is not None)
    rows = f"SELECT * FROM {source} AS src" + (f" WHERE {where}" if where else "")
    form, name = claim.form, claim.claim_id
    if isinstance(form, Quantified):
        hits = ", ".join(f"count(*) FILTER (coalesce({p.sql}, false)) AS h{i}" for i, (_, p) in enumerate(form.tallies))
        ok = " AND ".join(t.sql(f"h{i}", "seen") for i, (t, _) in enumerate(form.tallies))
        return f"SELECT '{name}' AS claim_id, {ok} AS verdict, h0 AS hits, seen FROM (SELECT {hits}, count(*) AS seen FROM ({rows}))"
    if isinstance(form, RankIs):
        keys = ", ".join(form.keys)
        value = "hits / seen" if form.by == "share" else "hits"
        where = " AND ".join(f"{k} = {v!r}" for k, v in zip(form.keys, form.target, strict=True))
        groups = f"SELECT {keys}, count(*) FILTER (coalesce({form.phi.sql}, false)) AS hits, count(*) AS seen FROM ({rows}) GROUP BY {keys}"
        ranked = f"SELECT *, dense_rank() OVER (ORDER BY {value} {'DESC' if form.descending else 'ASC'}) AS rank FROM ({groups})"
        return f"SELECT '{name}' AS claim_id, coalesce(max(rank) = {form.rank}, false) AS verdict, coalesce(max(hits), 0)::BIGINT AS hits, coalesce(max(seen), 0)::BIGINT AS seen FROM ({ranked}) WHERE {where}"
    levels, inner = _keys(form), _innermost(form)
    hits = ", ".join(f"count(*) FILTER (coalesce({p.sql}, false)) AS h{i}" for i, (_, p) in enumerate(inner.tallies))
    ok = " AND ".join(t.sql(f"h{i}", "n") for i, (t, _) in enumerate(inner.tallies))
    keys = ", ".join(levels[-1])
    sql = f"SELECT {keys}, {ok} AS ok FROM (SELECT {keys}, {hits}, count(*) AS n FROM ({rows}) GROUP BY {keys})"
    tests, f = [], form
    while isinstance(f, Nested):
        tests.append(f.outer)
        f = f.inner
    for level, test in zip(reversed(levels[:-1]), reversed(tests[1:]), strict=True):
        keys = ", ".join(level)
        sql = f"SELECT {keys}, {test.sql('h', 'n')} AS ok FROM (SELECT {keys}, count(*) FILTER (ok) AS h, count(*) AS n FROM ({sql}) GROUP BY {keys})"
    return f"SELECT '{name}' AS claim_id, {tests[0].sql('hits', 'seen')} AS verdict, hits, seen FROM (SELECT count(*) FILTER (ok) AS hits, count(*) AS seen FROM ({sql}))"
