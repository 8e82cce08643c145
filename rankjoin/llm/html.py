"""HTML extraction by equivalence-class template deduction.

Tokens of a page are starts and ends of its elements (by path: tag, class and id from the root down) and its
texts with their paths. Tokens that occur equally often on every page of a host,
so with one occurrence vector, form an equivalence class. Classes that hold at least `CLASS`
elements and texts and that at least `SUPPORT` of the host's pages hold are part of the host's template if
they are ordered and nested on all pages; occurrences of other tokens are told apart by the classes around them, and classes are
built anew until nothing changes (`llm/classes.py`). Texts inside an article must be on all pages, as copies of an article on some
pages are no template; if all of an article is on all pages, it stays. The pages' tokens are written once for the rounds, and the
last pass parses the pages again and goes through the rounds of their host.

What the template leaves over are its slots. A page's text is that of all slots in its
article or main element; without one, of all slots of the page. Slots in menus, headers, footers, sidebars,
notices, adverts, forms and comments (by tag, role, class or id) never count, nor do
scripts, styles and markup.

Blocks are cut at block-level tags; character references are decoded, white space
becomes one space, blocks are trimmed and joined in page order by an empty line.

Defined results: null html is empty and gives an empty text; a null url is a host of its own; unclosed
comments and scripts reach to the end, as in browsers; repeated rows get equal texts; a host with
fewer than `PAGES` pages has no template; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rankjoin.llm.classes import ARTICLE, CLOSE, OPEN, TEXT, prepared, rounds, signed, template, with_host
from rankjoin.llm.common import releasing, runs, table, written

BATCH_CHARS = 4_000_000

# Elements of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title iframe noembed noframes xmp".split())
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead tr ul".split())
ALONE = {"li": ("ul", "ol", "menu"), "dt": ("dl",), "dd": ("dl",), "tr": ("table",), "td": ("tr",), "th": ("tr",), "option": ("select",)}
# What marks text that is not the article.
DROP_TAGS = frozenset("nav footer aside form button select textarea dialog menu template noscript object canvas svg audio video head iframe script style title".split())
DROP_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar toolbar form".split())
DROP_WORDS = frozenset("ad ads adbox adslot advert adverts advertisement advertising sponsor sponsored sponsors promo promotion banner cookie cookies consent gdpr notice notices alert newsletter subscribe subscription signup paywall sidebar side-bar menu nav navbar navigation breadcrumb breadcrumbs footer masthead topbar toolbar comment comments commentlist respond replies reply disqus related recommended recommendations share sharing social popup modal overlay pagination pager widget widgets login search skip-link".split())
KEEP_TAGS = frozenset(("article", "main"))
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())

_TAG = re.compile(r"""<(?:!--|[!?]|(/?)([a-zA-Z][^\s/<>]*+)((?:[^<>"']++|"[^"<]*+"|'[^'<]*+')*+)>|(/?)([a-zA-Z][^\s/<>]*+)[^<>]*+>)""")
_ATTRIBUTE = re.compile(r"""\b(class|id|role)\s*+=\s*+(?:"([^"]*+)"|'([^']*+)'|([^\s"'>]++))""", re.I)
_WORD = re.compile(r"[a-z]+(?:-[a-z]+)*")


def _marked(name: str, attributes: str, inside: bool) -> tuple[bool, str]:
    """Whether an element is none of the article, and its class and id for paths."""
    drop, label = name in DROP_TAGS or (name == "header" and not inside), ""
    if attributes and "=" in attributes:
        for key, *values in _ATTRIBUTE.findall(attributes):
            value = next((v for v in values if v), "").lower()
            if key.lower() == "role":
                drop |= value.strip() in DROP_ROLES
                inside |= value.strip() in ("main", "article")
            else:
                label += f".{value}"
                if inside and key.lower() == "id" and (name in HEADINGS or (name == "section" and value not in DROP_WORDS)):
                    continue  # an anchor in an article
                if name not in KEEP_TAGS and name not in ("body", "html"):
                    for word in _WORD.findall(value.replace("_", "-")):
                        if word in DROP_WORDS or (name not in ("p", "span") and not DROP_WORDS.isdisjoint(word.split("-"))):
                            drop = True
    return drop, label


class Page:
    """One parsed page: blocks (inside article, text) and roles (its tokens in page order, one text token per block)."""

    def __init__(self, html: str) -> None:
        self.blocks: list[tuple[bool, str]] = []
        self._roles: list[int] = []  # 0: a text that turned out empty
        self._hashes: dict[str, int] = {}
        self._text: list[str] = []
        self._at = (False, "", 0)
        # name, path, dropped, inside the article
        self._stack: list[tuple[str, str, bool, bool]] = [("", "", False, False)]
        self._read(html)
        self._cut()
        for _, path, _, _ in self._stack[:0:-1]:
            self._token(path, CLOSE)
        self.roles = [r for r in self._roles if r]

    def _token(self, path: str, kind: int) -> None:
        h = self._hashes.get(path)
        if h is None:
            h = self._hashes[path] = _hash(path)
        self._roles.append(h | kind)

    def _cut(self) -> None:
        if self._text:
            if text := " ".join(unescape("".join(self._text)).split()):
                inside, path, at = self._at
                self.blocks.append((inside, text))
                self._roles[at] = _hash(f"{path}\n{text}") | (ARTICLE if inside else TEXT)
            self._text = []

    def _add(self, text: str) -> None:
        _, path, drop, inside = self._stack[-1]
        if not drop:
            if not self._text:
                self._at = inside, path, len(self._roles)
                self._roles.append(0)
            self._text.append(text)

    def _close(self, name: str, until: tuple[str, ...]) -> None:
        """Close the nearest open element of this name, unless one of `until` stands above it."""
        for k in range(len(self._stack) - 1, 0, -1):
            if self._stack[k][0] == name:
                for _, path, _, _ in self._stack[: k - 1 : -1]:
                    self._token(path, CLOSE)
                del self._stack[k:]
                return
            if self._stack[k][0] in until:
                return

    def _open(self, name: str, attributes: str) -> None:
        if name in BLOCK:
            self._cut()
            if name != "option" and len(self._stack) > 1:
                self._close("p", ("article", "section", "div", "td", "th", "li", "body", "blockquote", "main", "aside", "button", "table"))
        if name in ALONE:
            self._close(name, ALONE[name])
        if name in VOID:
            if name in ("br", "hr", "img", "wbr"):
                self._add(" " if name != "wbr" else "")
            return
        _, path, drop, inside = self._stack[-1]
        bad, label = _marked(name, attributes, inside)
        inside |= name in KEEP_TAGS or "main" in attributes and bool(re.search(r"role\s*=\s*[\"']?(?:main|article)", attributes))
        path = f"{path}/{name}{label}" if len(self._stack) < 64 else path
        self._token(path, OPEN)
        self._stack.append((name, path, drop or bad, inside))

    def _read(self, html: str) -> None:
        at, size, low = 0, len(html), None
        while at < size:
            m = _TAG.search(html, at)
            if m is None:
                self._add(html[at:])
                return
            if m.start() > at:
                self._add(html[at : m.start()])
            at = m.end()
            if m.group() == "<!--":
                end = html.find("-->", at)
                at = size if end < 0 else end + 3
                continue
            name = m[2] or m[5]
            if name is None:  # a declaration or processing instruction
                end = html.find(">", at)
                at = size if end < 0 else end + 1
                continue
            name = name.lower()
            if m[1] or m[4]:
                if name in BLOCK:
                    self._cut()
                self._close(name, ())
                continue
            self._open(name, m[3] or "")
            if name in RAW:
                low = html.lower() if low is None else low
                end = low.find(f"</{name}", at) if len(low) == size else html.find(f"</{name}", at)
                at = size if end < 0 else end

    def main_text(self, found: set[int]) -> str:
        """Blocks of the page whose roles do not stand at the places found."""
        texts = (i for i, r in enumerate(self.roles) if r & 2)
        slots = [(inside, text, i not in found) for (inside, text), i in zip(self.blocks, texts, strict=True)]
        article = [s for s in slots if s[0]]
        left = [s[1] for s in article or slots if s[2]]
        if article and not left:  # the same article on every page
            left = [s[1] for s in article]
        return "\n\n".join(left)


def _hash(text: str) -> int:
    """Hash of a path or text, its two lowest bits clear."""
    return signed(xxhash.xxh64_intdigest(text)) & ~3


def host(url: Column) -> Column:
    return F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), r"^(?:[a-zA-Z][a-zA-Z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]*)", 1))


def templates(pages: DataFrame) -> DataFrame:
    """host, n, roles, rounds: the rounds that lead to each host's template."""

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch.column(2).to_pylist()
            for a, b in runs((len(x or "") for x in texts), BATCH_CHARS):
                roles = [Page(x or "").roles for x in texts[a:b]]
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), batch.column(1).slice(a, b - a), pa.array(roles, pa.list_(pa.int64()))], names=["host", "key", "roles"])

    keyed = pages.select(host(F.col("url")).alias("host"), F.xxhash64("page_id", "url", "html").alias("key"), "html")
    return rounds(written(keyed.mapInArrow(work, "host string, key long, roles array<long>"), "tokens"))


def main_texts(pages: DataFrame) -> DataFrame:
    """page_id, url, text of every row of pages (page_id, url, html)."""
    found = written(templates(pages), "templates")
    rows = with_host(pages.select("page_id", "url", "html", host(F.col("url")).alias("host")), found, "left").select("page_id", "url", "html", "host", "rounds")
    schema = T.StructType([pages.schema["page_id"], pages.schema["url"], T.StructField("text", T.StringType(), False)])

    @releasing
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            known: dict[str, tuple] = {}  # of this batch
            sizes = [len(x or "") for x in batch.column(2).to_pylist()]
            for a, b in runs(sizes, BATCH_CHARS):
                part = batch.slice(a, b - a)
                texts = []
                for k, (html, name) in enumerate(zip(part.column(2).to_pylist(), part.column(3).to_pylist(), strict=True)):
                    if name not in known:
                        known[name] = prepared([(r["classes"], r["spare"]) for r in part.column(4)[k].as_py() or ()])
                    page = Page(html or "")
                    texts.append(page.main_text(template(page.roles, *known[name])))
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string())], names=["page_id", "url", "text"])

    return rows.mapInArrow(work, schema)


def op4_main_text(spark, sf_dir: str) -> DataFrame:
    """The main text of every page."""
    return main_texts(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))
