"""Main text of web pages by removal of each site's template.

Every element's subtree is hashed from its tags and texts; Spark counts, host by host,
with how many different remainders of a page each hash occurs; subtrees that
recur with many are the site's template and go, however large the host is.
Copies of a page have one remainder, so what they share is no template.  What the markup itself names as not the
article (menus, headers, footers, sidebars, notices, adverts, forms, scripts,
styles, comments) goes on every page, also on hosts with few pages.

Text in an ``article`` or ``main`` element is the page's own: there a recurring
subtree only goes if most of it is links, since copies of an article, or a
paragraph that many articles carry, are no template.  Without such an element
everything outside the template is the text, unless all of the page recurs; then
the page is a copy of others and again only recurring links go.

Counts are summed by (host, hash) on the map side, so a host with a third of all
pages is no hot key; hits return to their pages by page_id.

Defined results: null and empty pages have an empty text; a page without page_id
or with a URL that names no host is cleaned by markup alone; rows that repeat a
page_id share their hits and keep a row each; very long and very deep pages take
time in proportion; an element that never closes reaches to the end of what holds
it; an empty table gives an empty table; other columns pass, but for ``text`` and
``n_chars``, which are replaced.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from nearfield.llm.common import discard, keep, pieces

#: A subtree is template if it is on pages of its host with this many different remainders.
MIN_PAGES = 8

#: Elements by their part in HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = "script|style|title|textarea|noscript|template|iframe|svg|object|select|math"
BLOCKS = frozenset(
    "address article aside blockquote body br button canvas caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead title tr ul".split()
)
#: Start tags that end an open element of the same group.
ENDS = {"p": frozenset(BLOCKS - {"br", "button", "canvas", "body", "html", "head", "caption", "td", "th", "tr", "tbody", "thead", "tfoot", "option", "optgroup", "legend", "title"})} | {
    "li": frozenset({"li"}),
    "dt": frozenset({"dt", "dd"}),
    "dd": frozenset({"dt", "dd"}),
    "tr": frozenset({"tr", "tbody", "tfoot"}),
    "td": frozenset({"td", "th", "tr", "tbody", "tfoot"}),
    "th": frozenset({"td", "th", "tr", "tbody", "tfoot"}),
    "option": frozenset({"option", "optgroup"}),
    "head": frozenset({"body"}),
}
#: Elements and roles that are not the article.
ASIDE_TAGS = frozenset("head title nav header footer aside form button dialog menu canvas audio video input datalist".split())
ASIDE_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar note".split())
#: A heuristic, not a standard: parts of class names and ids that tell what is not the article.
ASIDE_NAMES = frozenset(
    "ad ads adv advert adverts advertisement advertising sponsor sponsored promo promotion banner nav navbar navigation menu breadcrumb breadcrumbs header masthead footer sidebar aside comment comments reply replies disqus respond cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription share sharing social related recommended recommendations widget toolbar pagination pager login signup search form copyright".split()
)

_TOKEN = re.compile(
    rf"<!--.*?(?:-->|\Z)|<(?P<raw>{RAW})\b(?:\"[^\"]*\"|'[^']*'|[^'\">])*>.*?(?:</(?P=raw)\s*>|\Z)"
    r"|<(?P<close>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<attrs>(?:\"[^\"]*\"|'[^']*'|[^'\">])*+)>|<[!?][^>]*>|</?[a-zA-Z!?][^>]*\Z|<[/!?]\Z",
    re.S | re.I,
)
_ATTR = re.compile(r"""\b(class|id|role|hidden)\b(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I)
_PROSE = frozenset("p h1 h2 h3 h4 h5 h6 blockquote pre b i em strong code td th tr table li dd dt".split())


class Page:
    """The element tree of a page: parents come before their children.

    One pass over the source, and sums over the elements after it: time and memory
    are linear in the page, however deep its elements nest.
    """

    def __init__(self, html: str):
        self.tags, self.parents, self.aside = ["#"], [-1], [False]
        #: In page order: (element, text) or (element, None) where a block begins or ends.
        self.items: list[tuple[int, str | None]] = []
        #: What each element is made of: its start tag, its texts and the places of its children.
        self.made: list[list[str | int]] = [[]]
        self._stack, self._open, self._blocks = [0], Counter(), []
        at = 0
        for m in _TOKEN.finditer(html):
            if m.start() > at:
                self._text(html[at : m.start()])
            at = m.end()
            tag = m["tag"]
            if m["raw"] or not tag:
                continue
            if m["close"]:
                self._close(tag.lower())
            else:
                self._start(tag.lower(), m["attrs"])
        if at < len(html):
            self._text(html[at:])

    def _text(self, text: str) -> None:
        self.items.append((self._stack[-1], text))
        self.made[self._stack[-1]].append(text)

    def _start(self, tag: str, attrs: str) -> None:
        stack = self._stack
        while len(stack) > 1 and tag in ENDS.get(self.tags[stack[-1]], ()):
            self._pop()
        if tag in BLOCKS:
            # Unclosed inline elements in a paragraph end with it.
            if tag in ENDS["p"] and self._blocks and self.tags[self._blocks[-1]] == "p":
                paragraph = self._blocks[-1]
                while self._pop() != paragraph:
                    pass
            self.items.append((stack[-1], None))
        if tag in VOID:
            self.made[stack[-1]].append(f"<{tag}>")
            return
        e = len(self.tags)
        self.tags.append(tag)
        self.parents.append(stack[-1])
        self.aside.append(_is_aside(tag, attrs))
        self.made.append([f"<{tag}{attrs}>"])
        self.made[stack[-1]].append(e)
        if not attrs.endswith("/"):
            stack.append(e)
            self._open[tag] += 1
            if tag in BLOCKS:
                self._blocks.append(e)

    def _pop(self) -> int:
        e = self._stack.pop()
        self._open[self.tags[e]] -= 1
        if self._blocks and self._blocks[-1] == e:
            self._blocks.pop()
        return e

    def _close(self, tag: str) -> None:
        if self._open[tag]:
            while self.tags[self._pop()] != tag:
                pass
        if tag in BLOCKS:
            self.items.append((self._stack[-1], None))

    def hashes(self) -> list[int]:
        """A hash of each element from its tag, its texts and its children's hashes; 0 for the root and its outermost parts."""
        out = [0] * len(self.tags)
        for e in range(len(self.tags) - 1, -1, -1):
            parts = (x.encode("utf-8", "surrogatepass") if isinstance(x, str) else out[x].to_bytes(8, "little", signed=True) for x in self.made[e])
            out[e] = xxhash.xxh3_64_intdigest(b"\0".join(parts)) - 2**63
        return [0 if t in ("#", "html", "body", "head") else h for t, h in zip(self.tags, out, strict=True)]

    def remainders(self) -> list[int]:
        """For each element, a sum of hashes of the page's text outside it; asides don't count."""
        gone, inner = self.aside[:], [0] * len(self.tags)
        for e in range(1, len(self.tags)):
            gone[e] = gone[e] or gone[self.parents[e]]
        for e, t in self.items:
            if t is not None and not gone[e] and (t := t.strip()):
                inner[e] += xxhash.xxh3_64_intdigest(t.encode("utf-8", "surrogatepass"))
        for e in range(len(self.tags) - 1, 0, -1):
            inner[self.parents[e]] += inner[e]
        return [(inner[0] - n) % 2**64 - 2**63 for n in inner]

    def weights(self) -> tuple[list[int], list[int]]:
        """Letters of text in each subtree, and of those within links."""
        text, link = [0] * len(self.tags), [0] * len(self.tags)
        inside = [False] * len(self.tags)
        for e in range(1, len(self.tags)):
            inside[e] = self.tags[e] == "a" or inside[self.parents[e]]
        for e, t in self.items:
            if t is not None:
                n = len(t.strip())
                text[e] += n
                link[e] += n * inside[e]
        for e in range(len(self.tags) - 1, 0, -1):
            text[self.parents[e]] += text[e]
            link[self.parents[e]] += link[e]
        return text, link


def _is_aside(tag: str, attrs: str) -> bool:
    if tag in ASIDE_TAGS:
        return True
    if not attrs or tag in ("html", "body", "article", "main"):
        return False
    for name, a, b, c in _ATTR.findall(attrs):
        name, value = name.lower(), (a or b or c).lower()
        if name == "hidden" or name == "role" and value in ASIDE_ROLES or name in ("class", "id") and not ASIDE_NAMES.isdisjoint(re.split(r"[\s_:-]+", value)):
            return True
    return False


def main_text(html: str | None, template: set[int] = frozenset()) -> str:
    """The text of a page without what its markup or its site's template sets aside."""
    if not html:
        return ""
    page = Page(html)
    n = len(page.tags)
    gone = page.aside[:]
    for e in range(1, n):
        gone[e] = gone[e] or gone[page.parents[e]]
    own = _own(page, gone)
    if template:
        text, link = page.weights()
        recurs = [h in template for h in page.hashes()]
        inside = [False] * n
        for e in range(1, n):
            inside[e] = e in own or inside[page.parents[e]]
        if not own:
            # A page of which all recurs is a copy of others.
            covered, above = 0, [False] * n
            for e in range(1, n):
                above[e] = recurs[page.parents[e]] or above[page.parents[e]]
                if recurs[e] and not gone[e] and not above[e]:
                    covered += text[e]
            left = sum(len(t.strip()) for e, t in page.items if t is not None and not gone[e])
            inside = [100 * covered >= 99 * left] * n
        for e in range(1, n):
            if recurs[e] and (not inside[e] or (page.tags[e] not in _PROSE and 2 * link[e] > text[e])):
                gone[e] = True
            gone[e] = gone[e] or gone[page.parents[e]]
        own = _own(page, gone)
    within = [False] * n
    for e in range(1, n):
        within[e] = e in own or within[page.parents[e]]
    parts = [" " if t is None else unescape(t) for e, t in page.items if not gone[e] and (within[e] or not own)]
    return " ".join("".join(parts).split())


def _own(page: Page, gone: list[bool]) -> set[int]:
    """The elements that hold the article: the articles, or else main."""
    for tag in ("article", "main"):
        found = {e for e in range(1, len(page.tags)) if page.tags[e] == tag and not gone[e]}
        if found:
            return found
    return set()


def _subtrees(pages: DataFrame) -> DataFrame:
    """Distinct subtree hashes of each page with the page's remainder, for subtrees with text.

    What the markup sets aside goes anyway and is left out; ``may`` says whether
    the subtree would go if it is template.
    """

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            index, out, rests, may_go = [], [], [], []
            for i, html in enumerate(batch.column(2).to_pylist()):
                page = Page(html or "")
                text, link = page.weights()
                gone, inside = page.aside[:], [False] * len(page.tags)
                for e in range(1, len(page.tags)):
                    gone[e] = gone[e] or gone[page.parents[e]]
                own = _own(page, gone)
                found: dict[int, tuple[int, bool]] = {}
                for e, (h, rest) in enumerate(zip(page.hashes(), page.remainders(), strict=True)):
                    inside[e] = e in own or e > 0 and inside[page.parents[e]]
                    if text[e] and h and not gone[e]:
                        may = not inside[e] or (page.tags[e] not in _PROSE and 2 * link[e] > text[e])
                        found[h] = (rest, may or h in found and found[h][1])
                out += found
                rests += [rest for rest, _ in found.values()]
                may_go += [may for _, may in found.values()]
                index += [i] * len(found)
            take = pa.array(index, pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0).take(take), batch.column(1).take(take), pa.array(out, pa.int64()), pa.array(rests, pa.int64()), pa.array(may_go, pa.bool_())], ["page_id", "host", "hash", "rest", "may"])

    return pages.select("page_id", "host", "html").mapInArrow(rows, T.StructType([pages.schema["page_id"], pages.schema["host"], T.StructField("hash", T.LongType()), T.StructField("rest", T.LongType()), T.StructField("may", T.BooleanType())]))


def extract(pages: DataFrame, min_pages: int = MIN_PAGES) -> DataFrame:
    """``pages`` with ``text`` and ``n_chars``."""
    hosted = pages.select("page_id", "html", F.xxhash64(F.lower(F.regexp_extract("url", r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1))).alias("host"), "url")
    named = hosted.where(F.col("page_id").isNotNull() & F.col("url").rlike("^[A-Za-z][A-Za-z0-9+.-]*://[^/:?#]"))
    rows = keep(_subtrees(named))
    often = rows.groupBy("host", "hash").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= min_pages).select("host", "hash")
    recurring = keep(rows.join(often, ["host", "hash"], "left_semi"))
    discard(rows)
    template = recurring.groupBy("host", "hash").agg(F.count_distinct("rest").alias("n")).where(F.col("n") >= min_pages).select("host", "hash")
    hits = keep(recurring.where("may").join(template, ["host", "hash"], "left_semi").groupBy(F.col("page_id").alias("_hit_id")).agg(F.collect_set("hash").alias("_hits")))
    discard(recurring)
    base = pages.drop("text", "n_chars")
    met = base.join(hits, F.col("page_id") == F.col("_hit_id"), "left").drop("_hit_id")
    schema = T.StructType([*base.schema.fields, T.StructField("text", T.StringType()), T.StructField("n_chars", T.LongType())])

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in pieces(batches):
            at = batch.schema.get_field_index("_hits")
            texts = [main_text(h, set(x or ())) for h, x in zip(batch.column("html").to_pylist(), batch.column(at).to_pylist(), strict=True)]
            columns = [c for i, c in enumerate(batch.columns) if i != at]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], schema.names)

    return met.mapInArrow(clean, schema)


#: The same rows in DuckDB SQL, for pages that mark their article and use the five basic references and those of the footers.
PAGES_SQL = r"""
WITH article AS (
  SELECT page_id, url, regexp_extract(coalesce(html, ''), '(?s)<article[^>]*>(.*?)(?:</article>|\z)', 1) AS a FROM pages
), bare AS (
  SELECT page_id, url, regexp_replace(regexp_replace(regexp_replace(a, '(?s)<[a-zA-Z/!][^>]*\z', ''), '</?b>', '', 'g'), '<[^>]*>', ' ', 'g') AS a FROM article
), plain AS (
  SELECT page_id, url, replace(replace(regexp_replace(replace(regexp_replace(replace(replace(a, '&lt;', '<'), '&gt;', '>'), '&quot;?', '"', 'g'), '&#39;', ''''), '&amp;?', chr(1), 'g'), chr(1), '&'), chr(9), ' ') AS a FROM bare
)
SELECT page_id, url, trim(regexp_replace(a, '\s+', ' ', 'g')) AS text, length(trim(regexp_replace(a, '\s+', ' ', 'g')))::BIGINT AS n_chars FROM plain
"""
