"""Per-row tests. Each is a column, an equal SQL text and an equal Python function, so that every engine can mirror it.

A semantic test stands for a model's answer: one evaluation of one row is one call. Nulls answer false.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Pred:
    name: str
    column: Callable[[], Column]
    sql: str
    python: Callable[[dict], bool]
    columns: tuple[str, ...]
    semantic: bool = True
    #: Words that speak for and against a hit, for relevance order and similarity filters.
    include: tuple[str, ...] = ()
    exclude: tuple[str, ...] = ()
    parts: tuple[Pred, ...] = field(default=())

    def __invert__(self) -> Pred:
        return Pred(f"not_{self.name}", lambda: ~self.safe(), f"NOT coalesce({self.sql}, false)", lambda r: not self.answer(r), self.columns, self.semantic, self.exclude, self.include, self.parts)

    def __and__(self, other: Pred) -> Pred:
        return Pred(
            f"{self.name}_and_{other.name}", lambda: self.safe() & other.safe(), f"(coalesce({self.sql}, false) AND coalesce({other.sql}, false))",
            lambda r: self.answer(r) and other.answer(r), tuple(dict.fromkeys((*self.columns, *other.columns))), self.semantic or other.semantic,
            self.include + other.include, self.exclude + other.exclude, (self, other),
        )

    def __or__(self, other: Pred) -> Pred:
        return Pred(
            f"{self.name}_or_{other.name}", lambda: self.safe() | other.safe(), f"(coalesce({self.sql}, false) OR coalesce({other.sql}, false))",
            lambda r: self.answer(r) or other.answer(r), tuple(dict.fromkeys((*self.columns, *other.columns))), self.semantic or other.semantic,
            self.include + other.include, self.exclude + other.exclude, (self, other),
        )

    def safe(self) -> Column:
        return F.coalesce(self.column(), F.lit(False))

    def answer(self, row: dict) -> bool:
        try:
            return bool(self.python(row))
        except (TypeError, AttributeError):  # a null attribute
            return False


def contains_any(name: str, column: str, words: tuple[str, ...], lower: bool = True, exclude: tuple[str, ...] = ()) -> Pred:
    c = (lambda: F.lower(column)) if lower else (lambda: F.col(column))
    text = f"lower({column})" if lower else column

    def col() -> Column:
        out = c().contains(words[0])
        for w in words[1:]:
            out = out | c().contains(w)
        return out

    def py(r: dict) -> bool:
        t = r[column].lower() if lower else r[column]
        return any(w in t for w in words)

    return Pred(name, col, "(" + " OR ".join(f"contains({text}, '{w}')" for w in words) + ")", py, (column,), True, tuple(w.lower() for w in words), exclude)


def compare(name: str, column: str, op: str, value: float | str, semantic: bool = True) -> Pred:
    literal = f"'{value}'" if isinstance(value, str) else str(value)
    ops = {">": lambda a: a > value, ">=": lambda a: a >= value, "<": lambda a: a < value, "<=": lambda a: a <= value, "=": lambda a: a == value, "<>": lambda a: a != value}
    return Pred(name, lambda: ops[op](F.col(column)), f"{column} {op} {literal}", lambda r: ops[op](r[column]), (column,), semantic)


INSULTS = ("idiot", "moron", "scum", "pathetic", "worthless")
abuse = contains_any("abuse", "text", INSULTS)
lic = contains_any("lic", "text", ("licens", "copyright"))
mit = contains_any("mit", "text", ("MIT License",), lower=False)
secret = contains_any("secret", "text", ('token = "',), lower=False)
grid = contains_any("grid", "text", (" | ",), lower=False)
card = Pred("card", lambda: F.col("text").rlike("[0-9]{16}"), "regexp_matches(text, '[0-9]{16}')", lambda r: __import__("re").search("[0-9]{16}", r["text"]) is not None, ("text",))
long = compare("long", "n_chars", ">", 2000)
dlg_long = Pred("dlg_long", lambda: F.length("text_all") > 1500, "length(text_all) > 1500", lambda r: len(r["text_all"]) > 1500, ("text_all",))
dlg_6 = compare("dlg_6", "n_turns", ">=", 6)
dlg_sys = compare("dlg_sys", "first_role", "=", "system")
dlg_abuse = contains_any("dlg_abuse", "text_all", INSULTS)
err = compare("err", "event_type", "=", "error")
ret = compare("ret", "l_returnflag", "=", "R")
positive_quantity = compare("positive_quantity", "l_quantity", ">", 0)
rich = compare("rich", "c_acctbal", ">", 0)
page_form = Pred(
    "page_form", lambda: F.regexp_replace("html", "<[^>]*>", " ").contains("©"), "contains(regexp_replace(html, '<[^>]*>', ' ', 'g'), '©')",
    lambda r: "©" in __import__("re").sub("<[^>]*>", " ", r["html"]), ("html",),
)
page_amp = Pred(
    "page_amp", lambda: F.regexp_replace("html", "<[^>]*>", " ").contains("&copy;"), "contains(regexp_replace(html, '<[^>]*>', ' ', 'g'), '&copy;')",
    lambda r: "&copy;" in __import__("re").sub("<[^>]*>", " ", r["html"]), ("html",),
)

def symbolic(column: str, op: str, value: float | str) -> Pred:
    return compare(f"{column}_{value}", column, op, value, semantic=False)
