"""Main text of web pages, with site templates found in Spark and removed.

A first pass hashes the element subtrees that may be template (all outside an article,
and inside it those that are not headings, paragraphs or quotes) together with the
page's host; Spark counts in how many different pages of its host each occurs.  Subtrees
in many pages are template, and the second pass leaves them out, besides what says itself
by tag, role or class that it is no main text.  A subtree's hash is made of its own
markup and its children's hashes, so a page is read once, however deep it nests.  The
list of template hashes is broadcast when it is below a stated size, else joined to the
pages.

Defined results: null html is empty and gives an empty text; a null url, and one without
a host, has the empty host; null or repeated page_id keep their rows; pages of equal html
on one host count as one page, so copies don't make a template; broken or unclosed markup
is closed as browsers do for paragraphs, items and cells, and a tag that never ends is
text; very long pages are read in time proportional to their length; an empty table gives
no rows; other columns are not read.
"""

from __future__ import annotations

import html as references
import re
from collections.abc import Iterator
from urllib.parse import urlsplit

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .session import written

MANY_PAGES = 5
MANY_SHARE = 0.1
BROADCAST_HASHES = 200_000

# Tags by what they do to text.
RAW = frozenset("script style noscript template iframe textarea select svg math object canvas xmp noembed noframes".split())
DROPPED = frozenset("head nav footer aside form menu dialog button title datalist".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset(
    "html body main article section div p h1 h2 h3 h4 h5 h6 ul ol li dl dt dd pre blockquote figure figcaption "
    "table caption thead tbody tfoot tr header footer nav aside form menu dialog details summary address hr "
    "fieldset legend hgroup center head title".split()
)
KEPT_IN_ARTICLE = frozenset("article p h1 h2 h3 h4 h5 h6 pre blockquote li dt dd figcaption td th tr tbody thead".split())
# A start tag (key) ends these open elements.
ENDS = {
    **dict.fromkeys(
        "address article aside blockquote center details dialog div dl fieldset figcaption figure footer form h1 h2 h3 "
        "h4 h5 h6 header hgroup hr main menu nav ol p pre section table ul".split(), ("p",)
    ),
    "li": ("li", "p"), "dt": ("dt", "dd", "p"), "dd": ("dt", "dd", "p"), "tr": ("tr", "td", "th"),
    "td": ("td", "th"), "th": ("td", "th"), "tbody": ("thead", "tbody", "tr", "td", "th"),
    "tfoot": ("tbody", "tr", "td", "th"), "body": ("head",), "option": ("option",),
}
# Elements that such an end does not reach beyond.
WALLS = frozenset("html body main article section div table ul ol dl td th blockquote aside nav footer header form".split())
DROPPED_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form".split())
DROPPED_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense adbox sponsor sponsored promo promotion banner cookie "
    "cookies consent gdpr notice notices notification alert newsletter subscribe subscription signup login sidebar "
    "sidenav comment comments commentlist respond reply replies disqus discussion share sharing social related "
    "recommended breadcrumb breadcrumbs menu nav navbar navigation topbar footer pagination pager popup modal overlay "
    "widget toolbar masthead skip paywall form".split()
)
HEADER_WORDS = frozenset(("header", "masthead"))
# Words that say nothing beside one of the above, as in "comments-list".
NEUTRAL_WORDS = frozenset("area bar block body bottom box button buttons container content group inner item items js left link links list main outer panel right section site top wrap wrapper".split())

_NAME = re.compile(r"/?([a-zA-Z][a-zA-Z0-9:-]*)")
_RAW_END = {tag: re.compile(f"</{tag}", re.I | re.A) for tag in RAW}
_PLAIN = re.compile(r"[^>\"']*")
_ATTR = re.compile(r"\b(class|id|role|hidden|style|aria-hidden)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_WORDS = re.compile(r"[a-z]+")


def host_of(url: str | None) -> str:
    try:
        return (urlsplit(url or "").hostname or "").lower()
    except ValueError:
        return ""


def _says_dropped(tag: str, attrs: str, in_article: bool) -> bool:
    if tag in DROPPED or (tag == "header" and not in_article):
        return True
    if not attrs or attrs.isspace() or tag in ("html", "body", "main", "article") and not _COMMENT.search(attrs):
        return False
    for m in _ATTR.finditer(attrs):
        name, value = m[1].lower(), (m[2] or m[3] or m[4] or "").lower()
        if name == "hidden" or name == "aria-hidden" and value == "true" and tag not in ("a", "b", "i", "span"):
            return True
        if name == "style" and "display:none" in value.replace(" ", ""):
            return True
        if name == "role" and value in DROPPED_ROLES and not (in_article and value == "banner"):
            return True
        if name in ("class", "id"):
            if not in_article:
                words = set(_WORDS.findall(value))
                if words & DROPPED_WORDS or words & HEADER_WORDS:
                    return True
            elif any(_all_dropped(name_) for name_ in value.split()):
                return True
    return False


def _all_dropped(name: str) -> bool:
    """Inside an article: a class or id drops its element only if none of its words says otherwise."""
    words = set(_WORDS.findall(name))
    return bool(words & DROPPED_WORDS) and words <= DROPPED_WORDS | NEUTRAL_WORDS


_COMMENT = re.compile(r"\b(comments?|replies|reply|related|teaser)\b", re.I)


def tokens(source: str) -> Iterator[tuple[str, str | None, str, int, int]]:
    """``(kind, tag, attributes, start, end)`` of all markup, in time proportional to the source.

    kind: ``<`` a start tag, ``/`` an end tag, ``!`` what holds no text.  A ``<`` that no
    ``>`` follows is text; a quote that isn't closed ends with the tag.
    """
    last = source.rfind(">")
    quotes = {q: source.rfind(q) for q in "\"'"}
    ends: dict[str, int] = {}  # place of a raw element's next end tag, as last found

    def tag_end(at: int) -> int:
        begin = at
        while True:
            at = _PLAIN.match(source, at).end()
            if at > last:
                return source.find(">", begin)
            if source[at] == ">":
                return at
            if at >= quotes[source[at]]:
                at += 1
            else:
                at = source.find(source[at], at + 1) + 1

    at = source.find("<")
    while 0 <= at < last:
        after = source[at + 1]
        if after in "!?":
            if source.startswith("<!--", at):
                close = source.find("-->", at + 4)
                stop = len(source) if close < 0 else close + 3
            else:
                stop = source.find(">", at) + 1
            yield "!", None, "", at, stop
        elif name := _NAME.match(source, at + 1):
            end = tag_end(name.end())
            tag, stop = name[1].lower(), end + 1
            if after == "/":
                yield "/", tag, "", at, stop
            elif tag in RAW:
                if ends.get(tag, 0) < stop and ends.get(tag) != -1:
                    found = _RAW_END[tag].search(source, stop)
                    ends[tag] = found.start() if found else -1
                close = ends[tag]
                stop = len(source) if close < 0 else source.find(">", close) + 1 or len(source)
                yield "!", None, "", at, stop
            else:
                yield "<", tag, source[name.end() : end], at, stop
        else:
            stop = at + 1
        at = source.find("<", stop)


class Element:
    __slots__ = ("tag", "above", "drop", "article", "main", "key", "hash")

    def __init__(self, tag: str, above: int, drop: bool, article: bool, main: bool):
        self.tag, self.above, self.drop, self.article, self.main = tag, above, drop, article, main
        self.key, self.hash = 0, None


class Page:
    """One pass over a page's tags: blocks of text with the innermost element that holds each."""

    def __init__(self, source: str, hashed: bool = True):
        self.blocks: list[tuple[str, int]] = []
        self.elements: list[Element] = []
        self._open: list[int] = []
        self._at: dict[str, list[int]] = {}  # places in _open, by tag
        self._walls: list[int] = []
        self._text: list[str] = []
        self._source, self._hashed, self._seen = source, hashed, 0
        at = 0
        for kind, tag, attrs, start, end in tokens(source):
            if start > at:
                self._text.append(source[at:start])
            at = end
            if kind == "/":
                self._close(tag, end)
            elif kind == "<":
                self._start(tag, attrs, start, end)
        self._text.append(source[at:])
        self._flush()
        self._pop(0, len(source))

    def _flush(self) -> None:
        if self._text:
            text = " ".join(references.unescape("".join(self._text)).split())
            if text:
                self.blocks.append((text, self._open[-1] if self._open else -1))
            self._text = []

    def _hash_upto(self, end: int) -> None:
        """Markup and text up to ``end`` belong to the innermost open element."""
        if self._hashed and self._open and end > self._seen:
            self.elements[self._open[-1]].hash.update(self._source[self._seen : end].encode("utf-8", "surrogatepass"))
        self._seen = max(end, self._seen)

    def _start(self, tag: str, attrs: str, start: int, end: int) -> None:
        for other in ENDS.get(tag, ()):
            at = self._at.get(other)
            if at and (not self._walls or at[-1] >= self._walls[-1]):
                self._pop(at[-1], start)
        if tag in BLOCKS:
            self._flush()
        elif tag in ("br", "td", "th", "img", "input", "wbr"):
            self._text.append("" if tag == "wbr" else " ")
        if tag in VOID or attrs.endswith("/") and tag not in BLOCKS:
            return
        above = self.elements[self._open[-1]] if self._open else None
        in_article = tag == "article" or above is not None and above.article
        # What drops an element for itself starts a block of its own, inline or not.
        drop = _says_dropped(tag, attrs, in_article)
        if drop:
            self._flush()
        self._hash_upto(start)
        me = Element(tag, self._open[-1] if self._open else -1, drop, in_article, tag == "main" or above is not None and above.main)
        if self._hashed:
            me.hash = xxhash.xxh64()
        self._at.setdefault(tag, []).append(len(self._open))
        if tag in WALLS:
            self._walls.append(len(self._open))
        self._open.append(len(self.elements))
        self.elements.append(me)

    def _close(self, tag: str, end: int) -> None:
        at = self._at.get(tag)
        if at and (tag in BLOCKS or not self._walls or at[-1] >= self._walls[-1]):
            self._pop(at[-1], end)

    def _pop(self, k: int, end: int) -> None:
        gone = [self.elements[x] for x in self._open[k:]]
        if any(x.tag in BLOCKS or x.drop for x in gone):
            self._flush()
        self._hash_upto(end)
        for x in reversed(gone):
            self._open.pop()
            self._at[x.tag].pop()
            if x.tag in WALLS:
                self._walls.pop()
            if self._hashed:
                x.key = x.hash.intdigest()
                x.hash = None
                if self._open:
                    self.elements[self._open[-1]].hash.update(x.key.to_bytes(8, "little"))

    def candidates(self) -> list[int]:
        """Elements whose subtree may be template."""
        return [
            k for k, e in enumerate(self.elements)
            if e.tag in BLOCKS and e.tag not in ("html", "body", "head", "title", "main", "article")
            and not (e.article and e.tag in KEPT_IN_ARTICLE)
        ]

    def text(self, template: set[int]) -> str:
        """Blocks of the article (else of main, else of the page) outside dropped and template elements."""
        bad = []
        for k, e in enumerate(self.elements):
            bad.append(e.drop or k in template or e.above >= 0 and bad[e.above])
        good = [(t, k) for t, k in self.blocks if k < 0 or not bad[k]]
        for region in ("article", "main"):
            inside = [t for t, k in good if k >= 0 and getattr(self.elements[k], region)]
            if inside:
                return "\n".join(inside)
        return "\n".join(t for t, _ in good)


def _keys(page: Page, host: str) -> tuple[list[int], np.ndarray]:
    which = page.candidates()
    prefix = host.encode("utf-8", "surrogatepass") + b"\0"
    keys = [xxhash.xxh64_intdigest(prefix + page.elements[k].key.to_bytes(8, "little")) for k in which]
    return which, np.array(keys, np.uint64).view(np.int64)


def template_hashes(pages: DataFrame, many: int = MANY_PAGES, share: float = MANY_SHARE) -> DataFrame:
    """``(key)``: hashes of (host, subtree) found in many different pages of the host."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hosts, names, keys, n = [], [], [], []
            for url, source in zip(*(c.to_pylist() for c in batch.columns)):
                host = host_of(url)
                hosts.append(host)
                names.append(xxhash.xxh64_intdigest((source or "").encode("utf-8", "surrogatepass")))
                keys.append(np.unique(_keys(Page(source or ""), host)[1]))
                n.append(len(keys[-1]))
            # A row without a key counts the page itself.
            of = np.repeat(np.arange(len(n)), n)
            key = pa.concat_arrays([pa.nulls(len(n), pa.int64()), pa.array(np.concatenate(keys) if keys else [], pa.int64())])
            name = np.array(names, np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays(
                [pa.array([*hosts, *(hosts[k] for k in of)], pa.string()), key, pa.array(np.r_[name, name[of]])], ["host", "key", "page"]
            )

    seen = pages.select("url", "html").mapInArrow(run, "host string, key long, page long")
    counted = written(seen.groupBy("host", "key").agg(F.count_distinct("page").alias("n")).filter(F.col("key").isNull() | (F.col("n") >= many)), "page-parts")
    per_host = counted.filter(F.col("key").isNull()).select("host", F.col("n").alias("pages"))
    often = counted.filter(F.col("key").isNotNull())
    return often.join(per_host, "host").filter(F.col("n") >= F.col("pages") * share).select("key").distinct()


def extract(pages: DataFrame, broadcast_hashes: int = BROADCAST_HASHES) -> DataFrame:
    """``(page_id, url, text, n_chars)``, one row per page."""
    spark = pages.sparkSession
    template = written(template_hashes(pages), "page-templates")
    found = template.limit(broadcast_hashes + 1).collect()
    need = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html")
    if len(found) <= broadcast_hashes:
        small = spark.sparkContext.broadcast(np.sort(np.array([r.key for r in found], np.int64)))
        source = need.withColumn("keys", F.lit(None).cast("array<long>"))
    else:
        small = None
        row = F.xxhash64("page_id", "url", "html")

        def own(batches):
            for batch in batches:
                rows, keys = [], []
                for row_, url, text in zip(*(c.to_pylist() for c in batch.columns)):
                    mine = np.unique(_keys(Page(text or ""), host_of(url))[1]).tolist()
                    rows += [row_] * len(mine)
                    keys += mine
                yield pa.RecordBatch.from_arrays([pa.array(rows, pa.int64()), pa.array(keys, pa.int64())], ["row", "key"])

        mine = need.select(row.alias("row"), "url", "html").mapInArrow(own, "row long, key long").distinct()
        listed = mine.join(template, "key").groupBy("row").agg(F.collect_list("key").alias("keys"))
        source = need.withColumn("row", row).join(listed, "row", "left").select("page_id", "url", "html", "keys")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = []
            for url, source_, keys in zip(*(batch.column(k).to_pylist() for k in (1, 2, 3))):
                known = small.value if small is not None else np.array(keys or [], np.int64)
                page = Page(source_ or "", len(known) > 0)
                template_ = set()
                if len(known):
                    which, own_keys = _keys(page, host_of(url))
                    template_ = {k for k, hit in zip(which, np.isin(own_keys, known)) if hit}
                texts.append(page.text(template_))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())],
                ["page_id", "url", "text", "n_chars"],
            )

    return source.mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op6_main_text(pages: DataFrame) -> DataFrame:
    return extract(pages)
