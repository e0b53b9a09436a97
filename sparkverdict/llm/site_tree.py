"""Main text of web pages by site style trees.

The pages of a host are merged into one style tree: its nodes are element paths (tags with their classes and ids from the
root down). Each page says which sequence of child styles a node has (presentation) and which texts stand right in it
(content). Values that change from page to page are folded first: letter case, the text of a block that is all links (a
menu entry), what a copyright line says, digits in classes and ids. A node of m pages is important by the entropy of its
presentations (base m) and by its contents: a text on k of the m pages has the entropy log_m k, and the node's content
importance is one less the mean over its texts. Copies of whole pages repeat everything, so content importance is taken
relative to that of the whole pages, and few pages prove little, so it is mixed with `prior_pages` pages of full
importance. A node whose presentation and content are both of low importance is the same everywhere, and its branch is
taken out. Hosts share templates, so the trees of all hosts are merged once more by style, a host counting as a page counts
before: a node is low on a host where its host's tree or the tree of all hosts says so.

Two rules of the language stand beside the trees, for what no repetition can tell (a host's only page, comments): elements
that by their tag, role, class or id are menus, headers, footers, sidebars, notices, adverts, forms or reader comments go,
and where a page marks its article or main element, only that is read. Inside it the element `header`, headings and
sections are parts of the article. `Rules(named=False, marked=False)` leaves the trees alone.

Both sums that a node needs (over presentations and over texts) are aggregates of counts, so a host with a third of all
pages is merged by partial aggregation. The low nodes of a host, bounded by its templates, are joined back by host.

Defined cases: a null or empty page has the empty text; a null url has no host and only the tree of all hosts; pages
without any markup are one block; unclosed comments, tags and scripts run to the end; very long and very deep pages take
linear time; repeated rows are extracted alike (and count as pages); there are no ties; an empty table gives an empty
result; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from html import unescape

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from sparkverdict.llm.common import materialise, ship_package

#: Elements of HTML by their kind.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp iframe noembed noframes".split())
BLOCK = frozenset(
    "address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form frameset h1 h2 h3 h4 h5 h6 "
    "head header hgroup hr html legend li main menu nav ol option p pre search section summary table tbody tfoot thead title tr ul".split()
)
NAMED = frozenset("nav footer aside menu".split())
NEVER_MAIN = frozenset("form button select datalist dialog head noscript template object svg canvas audio video map iframe math script style textarea title xmp noembed noframes".split())
CLOSES_P = BLOCK - {"br", "body", "html", "head", "option", "caption", "legend", "summary", "title", "tbody", "thead", "tfoot", "tr"}
SAME_LEVEL = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}
SCOPES = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr", "table"), "th": ("tr", "table"), "option": ("select", "datalist")}
SALTS = 64
#: Parts of classes, ids and roles that say that an element is not the main text. The first are looked for
#: as the first or last part of a name (site-footer, comment-list), the second as a whole name or with such a place or kind.
CHROME = frozenset(
    "ad ads advert adverts advertisement advertising adsense sponsor sponsored promo promoted breadcrumb breadcrumbs nav navbar navigation menu sidebar footer cookie cookies consent gdpr popup modal "
    "newsletter subscribe subscription comment comments commentlist disqus share sharing pagination pager toolbar masthead widget login signup skip".split()
)
CHROME_WHOLE = frozenset("related recommended social notice notices search banner reply replies respond alert overlay complementary contentinfo dialog header".split())
PLACES = frozenset("site page top bottom global area articles bar block box buttons container form icons left link links list panel posts right stories wrapper".split())
MAIN_HINT = re.compile(r"(?:^|[\s\"'])(?:main|articleBody)(?:$|[\s\"'])")

_TOKEN = re.compile(
    r"<!--(?:.*?-->|.*)|<!\[CDATA\[(?P<cdata>.*?)\]\]>|<[!?][^>]*>?|</(?P<end>[A-Za-z][^\s>/]*)[^>]*>?"
    r"|<(?P<start>[A-Za-z][^\s>/]*)(?P<attrs>(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>|<(?P<start2>[A-Za-z][^\s>/]*)(?P<attrs2>[^>]*)>?|(?P<text>[^<]+|<)",
    re.S,
)
_DIGITS = re.compile(r"\d+")
_COPYRIGHT = re.compile(r"©|\(c\)\s*\d{4}|copyright\s*(?:©|\(c\)|\d{4})")
_MASK = (1 << 64) - 1
#: Headings are never chrome by their names, nor are the outermost elements.
_NO_HINT = frozenset("html body h1 h2 h3 h4 h5 h6".split())
_ATTR = re.compile(r"""\b(class|id|role|itemprop|hidden|aria-hidden)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)


@dataclass(frozen=True)
class Rules:
    #: So many pages of full importance are added to those of a node.
    prior_pages: int = 20
    #: A node is taken out where both importances are below this ...
    low: float = 0.8
    #: ... or below this where the node is inside a marked article.
    low_inside: float = 0.1
    #: Whether elements go by their names, and whether a marked article is read alone.
    named: bool = True
    marked: bool = True


@dataclass
class Page:
    blocks: list[tuple[int, bool, str]]
    presentations: dict[int, list[int]]
    contents: set[tuple[int, int]]
    inside: dict[int, bool]


class Element:
    """An open element: its node, whether its text goes, whether it is in a marked article, its children's styles."""

    __slots__ = ("tag", "node", "gone", "inside", "children")

    def __init__(self, tag: str, node: int, gone: bool, inside: bool) -> None:
        self.tag, self.node, self.gone, self.inside, self.children = tag, node, gone, inside, []


def _digest(x: str, seed: int = 0) -> int:
    h = xxhash.xxh64_intdigest(x.encode("utf-8", "replace"), seed)
    return h - (1 << 64) if h >> 63 else h


def _attributes(raw: str) -> dict[str, str]:
    return {m[1].lower(): (m[2] or "").strip("\"'") for m in _ATTR.finditer(raw)} if raw.strip() else {}


@lru_cache(1 << 14)
def chrome_name(names: str, inside: bool) -> bool:
    """Whether a class, id or role says that its element is not the main text; `inside` a marked article."""
    for name in names.lower().replace("_", "-").split():
        parts = [x for x in re.sub(r"\d+", "", name).split("-") if x]
        if not parts or (inside and parts[-1] == "header"):
            continue
        if parts[0] in CHROME or parts[-1] in CHROME:
            return True
        whole = [x for x in parts if x in CHROME_WHOLE]
        if whole and all(x in CHROME_WHOLE or x in PLACES for x in parts) and not (inside and whole == ["header"]):
            return True
    return False


def folded(text: str, linked: bool) -> str:
    """A block's text as a feature of its node: what changes from page to page in one template is left out."""
    if linked:
        return "\0link"
    text = text.lower()
    return "\0copyright" if _COPYRIGHT.match(text) else text


def parse(html: str | None, low: frozenset[int] | set[int] = frozenset(), named: bool = True) -> Page:
    """Blocks of text in page order (node, whether inside a marked article, text) and what the style tree needs."""
    html = html or ""
    page = Page([], {}, set(), {})
    stack = [Element("", 0, False, False)]
    count: Counter = Counter()  # open elements by tag
    buffer: list[str] = []
    links, plain = 0, False  # open links, and whether the buffer has text outside of links

    def flush() -> None:
        nonlocal plain
        if buffer:
            text = " ".join("".join(buffer).split())
            buffer.clear()
            top = stack[-1]
            if text:
                page.contents.add((top.node, _digest(folded(text, not plain))))
                if not top.gone:
                    page.blocks.append((top.node, top.inside, text))
        plain = False

    def close() -> None:
        top = stack.pop()
        count[top.tag] -= 1
        page.presentations.setdefault(top.node, []).append(_digest("/".join(top.children)))

    def open_(tag: str, raw: str) -> None:
        above = stack[-1]
        found = _attributes(raw)
        style = tag + "".join(f".{c}" for c in sorted(set(found.get("class", "").split()))) + (f"#{found['id']}" if found.get("id") else "")
        style = _DIGITS.sub("0", style)
        above.children.append(style)
        node = _digest(style, above.node & _MASK)
        marked = tag in ("article", "main") or bool(MAIN_HINT.search(f"{found.get('role', '')} {found.get('itemprop', '')}"))
        chrome = False
        if named:
            says = tag not in _NO_HINT and any(chrome_name(found[x], above.inside) for x in ("class", "id", "role") if found.get(x))
            # an article inside the article with a comment's name is a comment; the marked one itself is none
            chrome = tag in NAMED or (tag == "header" and not above.inside) or (says and (above.inside or not marked))
        gone = above.gone or chrome or tag in NEVER_MAIN or "hidden" in found or found.get("aria-hidden", "").lower() == "true" or node in low
        stack.append(Element(tag, node, gone, above.inside or (marked and not gone)))
        count[tag] += 1
        page.inside[node] = stack[-1].inside

    def close_until(tags: tuple[str, ...], scopes: tuple[str, ...]) -> None:
        if not any(count[t] for t in tags):
            return
        for i in range(len(stack) - 1, 0, -1):
            if stack[i].tag in tags:
                flush()
                while len(stack) > i:
                    close()
                return
            if stack[i].tag in scopes:
                return

    at, size = 0, len(html)
    while at < size:
        m = _TOKEN.match(html, at)
        at = m.end()
        if m["text"] is not None:
            text = unescape(m["text"])
            buffer.append(text)
            plain = plain or (not links and not text.isspace())
        elif m["cdata"] is not None:
            buffer.append(m["cdata"])
            plain = plain or not links
        elif m["end"]:
            tag = m["end"].lower()
            if tag in BLOCK:
                flush()
            elif tag in ("td", "th"):
                buffer.append(" ")
            elif tag == "a":
                links = max(0, links - 1)
            close_until((tag,), ("article",) if tag in ("p", "li", "b", "i", "span") else ())
        elif m["start"] or m["start2"]:
            tag, raw = (m["start"] or m["start2"]).lower(), m["attrs"] if m["start"] else m["attrs2"]
            if tag in CLOSES_P:
                close_until(("p",), ("article", "main", "section", "div", "td", "th", "li", "blockquote", "body", "button"))
            if tag in SAME_LEVEL:
                close_until(SAME_LEVEL[tag], SCOPES[tag])
            if tag in BLOCK:
                flush()
                links = 0
            elif tag in ("td", "th", "img"):
                buffer.append(" ")
            elif tag == "a":
                links = 1
            if tag in VOID:
                continue
            if tag in RAW:
                end = re.compile(rf"</{tag}(?=[\s>/])[^>]*>?", re.I).search(html, at)
                at = end.end() if end else size
                stack[-1].children.append(tag)
                continue
            if tag not in BLOCK and tag not in NEVER_MAIN and "class" not in raw and "id" not in raw and "hidden" not in raw:
                continue  # inline markup is no node
            if tag not in BLOCK and (tag in NEVER_MAIN or (named and any(chrome_name(x, stack[-1].inside) for x in _attributes(raw).values() if x))):
                flush()
            open_(tag, raw)
    flush()
    while len(stack) > 1:
        close()
    return page


def main_text(html: str | None, low: frozenset[int] | set[int] = frozenset(), rules: Rules = Rules()) -> str:
    blocks = parse(html, low, rules.named).blocks
    if rules.marked and any(inside for _, inside, _ in blocks):
        blocks = [b for b in blocks if b[1]]
    return "\n".join(text for _, _, text in blocks)


def _style_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(host, node, kind, feature, pages), summed over the batch. Kinds: 0 a text, 1 a presentation, 2 one inside a marked
    article, 3 the whole page (at node 0)."""
    from sparkverdict.llm.site_tree import _digest, parse

    for batch in batches:
        counts: Counter = Counter()
        for host, html in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
            html = html.as_py()
            page = parse(html, named=False)
            counts[host, 0, 3, _digest(html or "")] += 1
            for node, seen in page.presentations.items():
                counts[host, node, 2 if page.inside.get(node) else 1, _digest(repr(seen))] += 1
            for node, text in page.contents:
                counts[host, node, 0, text] += 1
        columns = list(zip(*counts, strict=True)) if counts else [[], [], [], []]
        kinds = (pa.string(), pa.int64(), pa.int32(), pa.int64(), pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip([*columns, list(counts.values())], kinds, strict=True)], names=["host", "node", "kind", "feature", "pages"])


def with_host(pages: DataFrame) -> DataFrame:
    host = F.lower(F.regexp_extract(F.col("url").cast("string"), r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]+)", 1))
    return pages.select("page_id", F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"), F.when(F.length(host) > 0, host).alias("host"))


def style_features(pages: DataFrame) -> DataFrame:
    """host, node, kind, feature and k, the pages of the host that have the feature at the node."""
    ship_package(pages.sparkSession)
    rows = pages.select("host", "html").mapInArrow(_style_rows, "host string, node long, kind int, feature long, pages long")
    return rows.groupBy("host", "node", "kind", "feature").agg(F.sum("pages").alias("k"))


def importances(features: DataFrame, *site: str, prior_pages: int = Rules.prior_pages) -> DataFrame:
    """The site's columns, node, inside, m (pages), presentation and content importance of each style node with text."""
    styled, whole, k = F.col("kind").isin(1, 2), F.col("kind") == 3, F.col("k").cast("double")
    over = lambda c, x: F.sum(F.when(c, x).otherwise(0.0))
    sums = features.groupBy(*site, "node").agg(
        over(styled, k).alias("m"), over(styled, k * F.log(k)).alias("klogk"),
        over(F.col("kind") == 0, F.log(k)).alias("logk"), F.count(F.when(F.col("kind") == 0, 1)).alias("texts"),
        over(whole, k).alias("pages"), over(whole, F.log(k)).alias("logp"), F.count(F.when(whole, 1)).alias("distinct"),
        F.bool_or(F.col("kind") == 2).alias("inside"),
    )
    def content(log_sum: str, n: str, m: Column) -> Column:
        return F.when(m > 1, 1 - F.col(log_sum) / F.col(n) / F.log(m)).otherwise(F.lit(1.0))

    copies = sums.filter("pages > 0").select(*site, content("logp", "distinct", F.col("pages")).alias("whole"))
    nodes = sums.filter("texts > 0 and m > 0")
    joined = nodes.join(copies, [*site]) if site else nodes.crossJoin(F.broadcast(copies))  # without a site: one row
    own = content("logk", "texts", F.col("m"))
    relative = F.when(F.col("whole") > 1e-9, F.least(F.lit(1.0), own / F.col("whole"))).otherwise(F.lit(1.0))
    entropy = F.when(F.col("m") > 1, 1 - F.col("klogk") / F.col("m") / F.log("m")).otherwise(F.lit(1.0))
    mixed = lambda x: (prior_pages + F.col("m") * x) / (prior_pages + F.col("m"))
    return joined.select(*site, "node", "inside", "m", mixed(entropy).alias("presentation"), mixed(relative).alias("content"))


def low_nodes(features: DataFrame, rules: Rules = Rules()) -> DataFrame:
    """host and the array of its nodes whose branches go, by its own tree or the tree of all hosts; host null: the pages
    without a host, which have the latter only."""
    limit = F.when(F.col("inside"), F.lit(rules.low_inside)).otherwise(F.lit(rules.low))
    is_low = (F.col("presentation") < limit) & (F.col("content") < limit)
    own = importances(features.filter(F.col("host").isNotNull()), "host", prior_pages=rules.prior_pages).filter(is_low).select("host", "node")
    # in the tree of all hosts each host counts once per feature, so that no large host speaks for the others
    every = features.groupBy("node", "kind", "feature").agg(F.count(F.lit(1)).alias("k"))
    common = importances(every, prior_pages=rules.prior_pages).filter(is_low).select("node")
    # a style may stand on most hosts: its one row is copied SALTS times and the hosts that have it are spread over them
    spread = features.filter("kind in (1, 2)").select("host", "node").distinct().withColumn("salt", F.pmod(F.xxhash64("host"), F.lit(SALTS)).cast("int"))
    shared = spread.join(common.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), ["node", "salt"]).select("host", "node")
    return own.union(shared).groupBy("host").agg(F.collect_set("node").alias("low"))


def _extract(rules: Rules):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from sparkverdict.llm.site_tree import main_text

        for batch in batches:
            texts = [main_text(html.as_py(), frozenset(low.as_py() or ()), rules) for html, low in zip(batch.column(2), batch.column(3), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(x) for x in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return run


def extract(pages: DataFrame, rules: Rules = Rules()) -> DataFrame:
    """page_id, url, text, n_chars for every page."""
    hosted = with_host(pages)
    features = materialise(style_features(hosted), "style-features")
    low = low_nodes(features, rules)
    # a host may have a third of all pages: its one row of low nodes is copied SALTS times and its pages spread over the copies
    salted = low.select(F.col("host").alias("_host"), F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("_salt"), "low")
    spread = hosted.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int"))
    rows = spread.join(salted, (F.col("salt") == F.col("_salt")) & F.col("host").eqNullSafe(F.col("_host")), "left").select(F.col("page_id").cast("long").alias("page_id"), "url", "html", "low")
    return rows.mapInArrow(_extract(rules), "page_id long, url string, text string, n_chars long")
