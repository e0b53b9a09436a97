"""Relevance: three signals, fused by reciprocal ranks. The order never drops a row."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkverdict.functions.truth import Pred
from sparkverdict.operators.ranking import class_rank
from sparkverdict.plans.claims import Claim, Nested, RankIs
from sparkverdict.session import written
from sparkverdict.sources.relations import stems

RRF_K = 60
#: Words of a sentence that the similarity filter reads at once.
WINDOW = 32


@dataclass(frozen=True)
class RelevanceSpec:
    query: str
    include: tuple[str, ...] = ()
    exclude: tuple[str, ...] = ()


def describe(claim: Claim) -> dict[str, object]:
    """What a relevance prompt is written from: the aggregate's prompts, its filter, and its comparison."""
    form = claim.form
    while isinstance(form, Nested):
        form = form.inner
    phi = form.phi
    test = None if isinstance(form, RankIs) else form.test
    return {"map": phi.name, "columns": phi.columns, "filter": claim.semantic_scope.name if claim.semantic_scope else None, "aggregate": getattr(test, "kind", "rank"), "comparison": test}


def spec_for(pred: Pred) -> RelevanceSpec:
    """The words registered beside the test; a served model would write them from describe()."""
    return RelevanceSpec(" ".join(pred.include) or pred.name, pred.include, pred.exclude)


def n_present(text: Column, words: tuple[str, ...]) -> Column:
    return sum((F.lower(text).contains(w.lower()).cast("int") for w in words), F.lit(0))


def n_absent(text: Column, words: tuple[str, ...]) -> Column:
    return sum(((~F.lower(text).contains(w.lower())).cast("int") for w in words), F.lit(0))


def query_stems(query: str) -> list[str]:
    """The distinct five-letter stems of a query, as `stems` makes them of a text."""
    return sorted({w[:5] for w in re.split(r"[\W_]+", query.lower()) if w})


def text_cosine(tokens: Column, query: str) -> Column:
    """Cosine of two bags of distinct stems: common ones over the root of both sizes. The offline stand-in for embeddings."""
    q = query_stems(query)
    bag = F.array_distinct(tokens)
    common = F.size(F.array_intersect(bag, F.array(*[F.lit(w) for w in q]))) if q else F.lit(0)
    return F.coalesce(F.try_divide(common.cast("double"), F.sqrt(F.size(bag) * F.lit(float(max(1, len(q)))))), F.lit(0.0))


def cosine(a: Column, b: list[float]) -> Column:
    """Inner product of unit vectors."""
    return F.aggregate(F.zip_with(a, F.array(*[F.lit(float(x)) for x in b]), lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)


def rrf(df: DataFrame, key: str, signals: list[str], k: int = RRF_K, out: str = "rel_score") -> DataFrame:
    """key and the sum of 1 / (k + rank) over the signals; larger signals rank first, ties by key."""
    ranked = None
    for i, s in enumerate(signals):
        one = class_rank(df.select(key, s), s, key, f"_r{i}").select(key, f"_r{i}")
        ranked = one if ranked is None else ranked.join(one, key)
    score = sum((1 / (F.lit(float(k)) + F.col(f"_r{i}")) for i in range(1, len(signals))), 1 / (F.lit(float(k)) + F.col("_r0")))
    return ranked.select(key, score.alias(out))


def relevance_scores(df: DataFrame, key: str, text: str, spec: RelevanceSpec, k: int = RRF_K) -> DataFrame:
    """key, rel_score of every row."""
    t = F.coalesce(F.col(text).cast("string"), F.lit(""))
    signals = df.select(key, text_cosine(stems(t), spec.query).alias("s_cos"), n_present(t, spec.include).alias("s_in"), n_absent(t, spec.exclude).alias("s_out"))
    signals = written(signals, "signals")  # each rank below reads it, the texts are read once
    # a signal without words is the same for all rows and would only rank them by key
    used = ["s_cos"] + ["s_in"] * bool(spec.include) + ["s_out"] * bool(spec.exclude)
    return rrf(signals, key, used, k)


def nearest_cosine(tokens: Column, query: str) -> Column:
    """Cosine of a bag of distinct stems with the nearest word of the query: the words are alternatives, any one will do."""
    bag = F.array_distinct(tokens)
    near = F.arrays_overlap(bag, F.array(*[F.lit(w) for w in query_stems(query)])) if query_stems(query) else F.lit(False)
    return F.when(near, F.try_divide(F.lit(1.0), F.sqrt(F.size(bag)))).otherwise(F.lit(0.0))


def similarity_column(text: Column, query: str, granularity: str = "sentence") -> Column:
    """The largest cosine of a sentence (or of the whole text) with the query's nearest word. Sentences of more than
    WINDOW words count window by window, as an encoder of bounded input would read them."""
    if granularity == "document":
        return nearest_cosine(stems(text), query)
    parts = F.filter(F.split(F.coalesce(text, F.lit("")), r"\n|(?<=[.!?])\s+"), lambda s: F.length(F.trim(s)) > 0)
    starts = lambda t: F.sequence(F.lit(0), F.floor(F.greatest(F.size(t) - 1, F.lit(0)) / WINDOW).cast("int"))
    windows = F.flatten(F.transform(F.transform(parts, stems), lambda t: F.transform(starts(t), lambda i: F.slice(t, i * WINDOW + 1, WINDOW))))
    return F.coalesce(F.array_max(F.transform(windows, lambda t: nearest_cosine(t, query))), F.lit(-1.0))


def prefilter(df: DataFrame, text: str, spec: RelevanceSpec, threshold: float = 0.15, granularity: str = "sentence") -> DataFrame:
    """Rows with some sentence at least as close to the query as the threshold."""
    return df.filter(similarity_column(F.col(text), spec.query, granularity) >= threshold)


def sweep(scored: DataFrame, score: str, selected: str, thresholds: list[float]) -> DataFrame:
    """threshold, n_pos, kept_pos, n_rows, dropped: recall and filter rate of each threshold, as counts."""
    at = scored.sparkSession.createDataFrame([(float(x),) for x in thresholds], "threshold double")
    # a handful of thresholds, a size that does not grow
    pairs = scored.join(F.broadcast(at), how="cross")
    passed = F.col(score) >= F.col("threshold")
    return pairs.groupBy("threshold").agg(
        F.count_if(F.col(selected)).alias("n_pos"), F.count_if(F.col(selected) & passed).alias("kept_pos"), F.count(F.lit(1)).alias("n_rows"), F.count_if(~passed).alias("dropped")
    )
