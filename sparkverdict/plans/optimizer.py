"""Planning decisions: which order feeds an aggregate, error budgets, fusion, and what a plan knows about sizes."""

from __future__ import annotations

from dataclasses import dataclass, replace

from sparkverdict.operators.confseq import bonferroni
from sparkverdict.plans.claims import Claim, Nested, Quantified, RankIs, Test


@dataclass(frozen=True)
class VerifyOptions:
    early_stop: bool = True
    relevance: bool = True
    estimate: bool = True
    fusion: bool = True
    similarity: bool = True
    cache: bool = True
    alpha: float = 0.05
    eps: float = 0.05
    threshold: float = 0.15
    batch: int = 32
    max_wave: int = 1 << 20
    growth: int = 2
    small_k: int = 10
    max_fused: int = 4
    seed: int = 7
    interval: str = "betting"
    #: 'sorted' reads groups in order and stops inside them, 'hash' aggregates every row.
    group_exec: str = "sorted"
    #: 'known' divides alpha by the number of groups, 'arrival' halves it from group to group, for any number of groups.
    budget: str = "known"
    #: 'unknown' lets a semantic filter's rows arrive uncounted, 'after_filter' runs the whole filter first and counts them.
    cardinality: str = "unknown"
    top_k: int | None = None
    rrf_k: int = 60

    @staticmethod
    def all() -> VerifyOptions:
        return VerifyOptions()

    @staticmethod
    def none() -> VerifyOptions:
        return VerifyOptions(False, False, False, False, False, False)

    @staticmethod
    def exact() -> VerifyOptions:
        """Everything whose verdict is certain: no estimation, no similarity filter."""
        return VerifyOptions(estimate=False, similarity=False)

    def without(self, name: str) -> VerifyOptions:
        """One optimization off. Ordering and estimation exist only for early stopping and go with it."""
        off = {"early_stop": ("early_stop", "relevance", "estimate")}.get(name, (name,))
        return replace(self, **dict.fromkeys(off, False))


def choose_order(test: Test, size_known: bool, small_k: int = 10) -> str:
    """'relevance' where few hits settle a true claim, 'estimate' where an interval does, 'none' where neither helps."""
    if test.kind == "exists":
        return "relevance"
    if test.kind in ("forall", "share"):
        return "estimate"
    if test.op in (">=", ">"):
        return "relevance" if not size_known or test.value <= small_k else "estimate"
    return "estimate" if size_known else "none"


def order_for(form: Quantified, size_known: bool, options: VerifyOptions) -> str:
    """One order per aggregate: estimation wins where its tallies disagree; options may forbid either."""
    wanted = {choose_order(t, size_known, options.small_k) for t, _ in form.tallies}
    order = "estimate" if "estimate" in wanted else ("relevance" if "relevance" in wanted else "none")
    allowed = options.early_stop and {"estimate": options.estimate, "relevance": options.relevance, "none": True}[order]
    return order if allowed else "none"


@dataclass(frozen=True)
class Plan:
    """What the optimizer decided for a claim, in the order of its rules."""

    claim: Claim
    options: VerifyOptions
    calls_per_row: int
    size_known: bool
    inner_order: str
    outer_order: str
    alpha_inner: float | None
    alpha_outer: float | None
    similarity: bool
    stops: bool

    def explain(self) -> str:
        c = self.claim
        lines = [f"claim {c.claim_id} over {c.relation}", f"  check {c.form}"]
        if self.outer_order != "-":
            lines.append(f"  aggregate groups: order={self.outer_order} alpha={self.alpha_outer}")
        lines.append(f"  aggregate rows: order={self.inner_order} alpha={self.alpha_inner} stops={self.stops} sizes={'known' if self.size_known else 'unknown'}")
        if self.similarity:
            lines.append(f"  similarity filter: threshold={self.options.threshold}")
        lines.append(f"  semantic stage: {self.calls_per_row} call(s) a row, batches of {self.options.batch}")
        lines.append(f"  scan {c.relation}" + (f" where {c.scope.name}" if c.scope else ""))
        return "\n".join(lines)


def semantic_prompts(claim: Claim) -> tuple[int, int]:
    """Semantic filters and maps of the claim's query."""
    form = claim.form
    while isinstance(form, Nested):
        form = form.inner
    maps = {p.name.removeprefix("not_") for p in ([form.phi] if isinstance(form, RankIs) else [p for _, p in form.tallies]) if p.semantic}
    return int(claim.semantic_scope is not None), len(maps)


def plan(claim: Claim, options: VerifyOptions, groups: int | None = None) -> Plan:
    filters, maps = semantic_prompts(claim)
    prompts = filters + maps
    # a fused filter hides how many rows reach the aggregate; unfused, the filter may run first and be counted
    first = bool(filters) and options.cardinality == "after_filter"
    size_known = filters == 0 or first
    calls = (filters + -(-maps // options.max_fused) if first else -(-prompts // options.max_fused)) if options.fusion else prompts
    form, ranked = claim.form, isinstance(claim.form, RankIs)
    outer, inner = "-", form
    if isinstance(form, Nested):
        while isinstance(inner, Nested):
            inner = inner.inner
        outer = order_for(Quantified(form.outer, form_phi(form)), True, options)
    inner_order = "none" if ranked else order_for(inner, size_known, options)
    operators = (inner_order == "estimate") + (outer == "estimate")
    tallies = 1 if ranked else len(inner.tallies)
    m = groups if groups and options.budget == "known" else 1
    return Plan(
        claim, options, calls, size_known, inner_order, outer,
        bonferroni(options.alpha, operators, tallies, m if outer != "-" else 1) if inner_order == "estimate" else None,
        bonferroni(options.alpha, operators, 1, 1) if outer == "estimate" else None,
        bool(options.similarity and claim.semantic_scope is not None and claim.semantic_scope.include),
        options.early_stop and not ranked,
    )


def form_phi(form: Nested):
    while isinstance(form, Nested):
        form = form.inner
    return form.phi
