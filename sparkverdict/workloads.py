"""The benchmark claims restated over the given tables, the scale-up set, and one claim per form and comparison."""

from __future__ import annotations

from fractions import Fraction

from sparkverdict.functions import truth as t
from sparkverdict.plans.claims import EXISTS, FORALL, OPS, Claim, Nested, Quantified, RankIs, count, share

EN, FR = t.symbolic("lang", "=", "en"), t.symbolic("lang", "=", "fr")
SRC, ENT = ("source",), ("entity",)
HALF, FIFTH = Fraction(1, 2), Fraction(1, 5)


def _q(test, phi, *also):
    return Quantified(test, phi, tuple(also))


def benchmark() -> dict[str, Claim]:
    d, g = "documents", "dialogs"
    rows = [
        Claim("c01", d, _q(count("<", 5), t.abuse), EN, None, False, "a handful of English documents are abusive"),
        Claim("c02", d, _q(EXISTS, t.secret), EN, None, True, "some English document leaks a secret"),
        Claim("c03", d, _q(share(">=", 0.1), t.lic), EN, t.abuse, False, "a licence line is common among abusive documents"),
        Claim("c04", d, _q(FORALL, ~t.abuse), FR, None, True, "no French document is abusive"),
        Claim("c05", d, Nested(EXISTS, SRC, _q(FORALL, ~t.abuse)), EN, None, False, "some source is free of abuse", "compare"),
        Claim("c06", d, Nested(share("<", HALF), SRC, _q(count(">=", 2), t.abuse)), EN, None, False, "a minority of sources has multiple abusive documents", "compare"),
        Claim("c07", d, Nested(share(">", HALF), SRC, _q(EXISTS, t.abuse)), EN, None, True, "most sources have an abusive document", "compare"),
        Claim("c08", d, Nested(FORALL, SRC, _q(count(">=", 2), t.long)), None, None, True, "every source has multiple long documents", "compare"),
        Claim("c09", d, RankIs(SRC, ("src6",), 1, t.long), None, ~t.grid, True, "source 6 has the largest share of long texts", "rank"),
        Claim("c10", d, RankIs(SRC, ("src17",), 2, t.long), None, ~t.grid, True, "source 17 comes second", "rank"),
        Claim("c11", d, RankIs(SRC, ("src17",), 1, t.long), None, ~t.grid, False, "source 17 comes first", "rank"),
        Claim("c12", d, RankIs(SRC, ("src6",), 2, t.long), None, ~t.grid, False, "source 6 comes second", "rank"),
        Claim("c13", d, _q(count(">", 5), t.lic), EN, None, True, "more than a handful of English documents has a licence line"),
        Claim("c14", d, _q(EXISTS, t.abuse), FR, None, False, "some French document is abusive"),
        Claim("c15", d, _q(share(">", HALF), ~t.long), EN, None, True, "a majority of English documents is short"),
        Claim("c16", d, _q(FORALL, t.mit), None, t.lic, False, "all licence lines name one licence"),
        Claim("c17", g, _q(count("==", 60), t.dlg_long), None, None, False, "sixty dialogs are long"),
        Claim("c18", g, _q(count("!=", 60), t.dlg_long), None, None, True, "not sixty dialogs are long"),
        Claim("c19", g, _q(share("==", 0.1), t.dlg_sys), None, None, False, "a tenth of the dialogs opens with a system turn"),
        Claim("c20", g, _q(share("!=", 0.1), t.dlg_sys), None, None, True, "not a tenth does"),
        Claim("c21", g, Nested(count("==", 3), ENT, _q(share(">", HALF), t.dlg_6)), None, None, True, "three companies have mostly long exchanges", "compare"),
        Claim("c22", g, Nested(count("==", 2), ENT, _q(FORALL, t.dlg_long)), None, None, False, "two companies have only long dialogs", "compare"),
        Claim("c23", g, Nested(EXISTS, ENT, _q(share(">=", FIFTH), t.dlg_6, (share(">=", FIFTH), ~t.dlg_6))), None, None, True, "one company is mixed", "compare"),
        Claim("c24", g, Nested(FORALL, ENT, _q(EXISTS, t.dlg_abuse)), None, None, False, "every company has an abusive dialog", "compare"),
        Claim("c25", g, RankIs(ENT, (3,), 1, t.dlg_6, "count"), None, None, True, "company 3 has most long exchanges", "rank"),
        Claim("c26", g, RankIs(ENT, (5,), 2, t.dlg_6, "count"), None, None, True, "company 5 comes second", "rank"),
        Claim("c27", g, RankIs(ENT, (5,), 1, t.dlg_6, "count"), None, None, False, "company 5 comes first", "rank"),
        Claim("c28", g, RankIs(ENT, (3,), 2, t.dlg_6, "count"), None, None, False, "company 3 comes second", "rank"),
        Claim("c29", g, _q(count("==", 51), t.dlg_6), None, None, True, "51 dialogs have six turns or more"),
        Claim("c30", g, _q(count("<", 48), t.dlg_6), None, None, False, "fewer than 48 do"),
        Claim("c31", g, _q(share("<", 0.1), t.dlg_sys), None, None, False, "fewer than a tenth opens with a system turn"),
        Claim("c32", g, _q(share("<", 0.25), t.dlg_sys), None, None, True, "fewer than a quarter does"),
    ]
    return {c.claim_id: c for c in rows}


def scale_up() -> dict[str, Claim]:
    rows = [
        Claim("s1", "events", Nested(FORALL, ("user_id",), _q(count(">=", 2), t.err)), text="every user met multiple errors"),
        Claim("s2", "events", _q(share(">", 0.15), t.err), text="more than 15 % of the events are errors"),
        Claim("s3", "lineitem", _q(share("==", Fraction(1, 3)), t.ret), text="a third of the lines was returned"),
        Claim("s4", "lineitem", Nested(FORALL, ("l_suppkey",), _q(share(">", 0.2), t.ret)), text="every supplier had a fifth returned"),
        Claim("s5", "lineitem", RankIs(("l_suppkey",), (87,), 1, t.ret), text="supplier 87 has the largest share of returns"),
        Claim("s6", "lineitem", _q(FORALL, t.positive_quantity), text="all quantities are positive"),
        Claim("s7", "customers", Nested(FORALL, ("r_name",), Nested(FORALL, ("n_name",), _q(share(">", HALF), t.rich))), text="in every region every nation's customers are mostly in credit"),
        Claim("s8", "pages", _q(EXISTS, t.page_amp), text="some page's text has a copyright sign"),
    ]
    return {c.claim_id: c for c in rows}


def kinds() -> dict[str, Claim]:
    """One claim per form and comparison, over documents and dialogs."""
    out: dict[str, Claim] = {}
    names = dict(zip(OPS, ("ge", "gt", "le", "lt", "eq", "ne"), strict=True))
    out["k1_exists"] = Claim("k1_exists", "documents", _q(EXISTS, t.card))
    out["k2_forall"] = Claim("k2_forall", "documents", _q(FORALL, t.long))
    out["k2_none"] = Claim("k2_none", "documents", _q(FORALL, ~t.secret), EN)
    for op, n in names.items():
        out[f"k3_{n}"] = Claim(f"k3_{n}", "documents", _q(count(op, 39), t.lic))
        out[f"k4_{n}"] = Claim(f"k4_{n}", "dialogs", _q(share(op, 0.24), t.dlg_sys))
        out[f"k6_{n}"] = Claim(f"k6_{n}", "documents", Nested(count(op, 19), SRC, _q(count(">=", 2), t.abuse)), EN)
    out["k5_count"] = Claim("k5_count", "documents", RankIs(SRC, ("src6",), 1, t.long, "count"))
    out["k5_share"] = Claim("k5_share", "documents", RankIs(SRC, ("src6",), 1, t.long, "share"))
    out["k5_asc"] = Claim("k5_asc", "documents", RankIs(SRC, ("src6",), 20, t.long, "share", False))
    out["k5_missing"] = Claim("k5_missing", "documents", RankIs(SRC, ("nowhere",), 1, t.long))
    out["k7_deep"] = Claim("k7_deep", "documents", Nested(FORALL, ("lang",), Nested(share(">=", HALF), SRC, _q(EXISTS, t.long))))
    out["k8_compound"] = Claim("k8_compound", "dialogs", Nested(EXISTS, ENT, _q(share(">=", FIFTH), t.dlg_long, (share(">=", FIFTH), ~t.dlg_long))))
    out["k9_scope"] = Claim("k9_scope", "documents", _q(share("<", HALF), t.mit), EN, t.lic)
    out["k9_empty"] = Claim("k9_empty", "documents", _q(share("<", HALF), t.mit), t.symbolic("lang", "=", "xx"))
    return out


def all_claims() -> dict[str, Claim]:
    return benchmark() | scale_up() | kinds()
