"""Operator 5, main text of web pages by tree scoring.

A page becomes a tree of elements and a list of text blocks in page order. Elements that are never
article text by their tag, role or class (menus, headers, footers, sidebars, notices, adverts,
forms, scripts, styles, reader comments) drop out with all they hold. Each block passes points to
its ancestors, fewer with distance: one for being there, one for each comma and up to three for
length, less by the share of its text inside links. The best container is kept whole, with those
siblings that score nearly as well and with headings just before it.

Null html is empty; a page without text gives an empty string. Character references are decoded;
white space inside a block is one space; blocks are joined by one space. Broken markup (unclosed
or stray tags) is closed as browsers close it. Pages of any length are read whole; time grows with blocks times their
depth. Repeated rows are extracted alike. Other columns are ignored; an empty table gives no rows.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .store import small_batches

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)([^>]*)>", re.S)
_ATTR = re.compile(r"\b(class|id|role|hidden|aria-hidden|style)\b(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?", re.I)
_PART = re.compile(r"[a-z]+|[A-Z][a-z]*|\d+")

# Element names and class words of HTML practice.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript template iframe noembed noframes xmp svg math".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
DROPPED_TAGS = frozenset("nav footer aside form script style noscript template iframe button select option dialog menu head object canvas svg math audio video map textarea title".split())
DROPPED_ROLES = frozenset("navigation banner contentinfo complementary search dialog alertdialog alert menu menubar form".split())
DROPPED_WORDS = frozenset("ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs comment comments consent cookie cookies disqus footer gdpr header login masthead menu modal nav navbar navigation newsletter notice overlay pagination pager paywall popup promo promotion recommended related replies reply share sharing sidebar signup skip social sponsor sponsored subscribe subscription tags toolbar topbar warning widget".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
IMPLIED = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"}), "tbody": ({"thead", "tbody", "tr", "td", "th"}, {"table"}), "tfoot": ({"thead", "tbody", "tr", "td", "th"}, {"table"})}
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
SAFE = frozenset("html body article main".split())


def _dropped(tag: str, attrs: str, inside_article: bool) -> bool:
    if tag in DROPPED_TAGS or (tag == "header" and not inside_article):
        return True
    if tag in SAFE or not attrs:
        return False
    for name, *values in _ATTR.findall(attrs):
        name, value = name.lower(), next((v for v in values if v), "")
        if name == "role" and value.lower() in DROPPED_ROLES:
            return True
        if name == "hidden" or (name == "aria-hidden" and value.lower() == "true"):
            return True
        if name == "style" and re.search(r"display\s*:\s*none", value, re.I):
            return True
        if name in ("class", "id") and any(p.lower() in DROPPED_WORDS for p in _PART.findall(value)):
            return True
    return False


class Page:
    """Kept elements (tag, parent) and text blocks (element, text, characters in links) in page order."""

    def __init__(self, source: str):
        self.tag, self.parent = ["#root"], [-1]
        self.blocks: list[tuple[int, str, int]] = []
        self._parse(source)

    def _parse(self, source: str) -> None:
        open_: list[tuple[str, int]] = [("#root", 0)]
        held: list[tuple[str, bool]] = []
        holder = at = links = 0
        drop = 0  # depth in ``open_`` at which a dropped element began; 0: none

        def flush() -> None:
            if held:
                text = " ".join(entities.unescape("".join(t for t, _ in held)).split())
                if text:
                    linked = len("".join("".join(t for t, inside in held if inside).split()))
                    self.blocks.append((holder, text, min(linked, len(text))))
                held.clear()

        def text(piece: str) -> None:
            nonlocal holder
            if piece and not drop:
                if not held:
                    holder = next(n for t, n in reversed(open_) if t not in INLINE)
                held.append((piece, links > 0))

        def shut(depth: int) -> None:
            nonlocal drop, links
            for t, _ in open_[depth:]:
                links -= t == "a"
            if any(t not in INLINE for t, _ in open_[depth:]):
                flush()
            del open_[depth:]
            if drop >= depth > 0:
                drop = 0

        def close_to(names, barriers) -> None:
            for d in range(len(open_) - 1, 0, -1):
                if open_[d][0] in names:
                    shut(d)
                    return
                if open_[d][0] in barriers:
                    return

        size = len(source)
        while at < size:
            m = _TOKEN.search(source, at)
            if not m:
                text(source[at:])
                break
            text(source[at : m.start()])
            at = m.end()
            closing, tag, attrs = (m[1], m[2], m[3]) if m[2] else (m[4], m[5], m[6])
            if not tag:
                continue
            tag = tag.lower()
            if closing:
                for d in range(len(open_) - 1, 0, -1):
                    if open_[d][0] == tag:
                        shut(d)
                        break
                    if tag in INLINE and open_[d][0] not in INLINE:
                        break
                continue
            if tag in RAW and not attrs.rstrip().endswith("/"):
                end = re.compile(rf"</{tag}\s*>", re.I).search(source, at)
                at = end.end() if end else size
                if tag not in ("svg", "math"):
                    flush()
                continue
            if tag == "br":
                text(" ")
                continue
            if tag in VOID:
                if tag not in INLINE and tag == "hr":
                    flush()
                continue
            if tag in CLOSES_P:
                close_to({"p"}, {"table", "td", "th", "button", "object"})
            if tag in HEADINGS and open_[-1][0] in HEADINGS:
                shut(len(open_) - 1)
            if tag in IMPLIED:
                close_to(*IMPLIED[tag])
            if tag not in INLINE:
                flush()
            if attrs.rstrip().endswith("/") and tag in ("path", "rect", "g", "use"):
                continue
            node = open_[-1][1]
            if not drop:
                if _dropped(tag, attrs, any(t in ("article", "main") for t, _ in open_)):
                    flush()
                    drop = len(open_)
                elif tag not in INLINE:
                    node = len(self.tag)
                    self.tag.append(tag)
                    self.parent.append(open_[-1][1])
            links += tag == "a"
            open_.append((tag, node))
        flush()

    def main_text(self) -> str:
        """The text of the best container and of the siblings that belong to it."""
        if not self.blocks:
            return ""
        points = [0.0] * len(self.tag)
        for node, text, linked in self.blocks:
            own = (1 + text.count(",") + min(len(text) / 100, 3)) * (1 - linked / len(text))
            # a paragraph or heading is no container; its parent gets all, then half, a third, ...
            up = self.parent[node] if self.tag[node] in ("p", "pre", "blockquote", "li", "td", "dd", "dt", "figcaption") or self.tag[node] in HEADINGS else node
            share = 1
            while up > 0:
                points[up] += own / share
                share += 1
                up = self.parent[up]
        for n, tag in enumerate(self.tag):
            if tag in ("article", "main"):
                points[n] = 25 + 1.5 * points[n] if points[n] else 0
            elif tag in ("ul", "ol", "li", "table", "tr", "dl"):
                points[n] *= 0.5
        best = max(range(len(points)), key=lambda n: (points[n], -n))
        if points[best] <= 0:
            keep = {n for n, *_ in self.blocks}
        else:
            keep = {best}
            above = self.parent[best]
            siblings = [n for n in range(1, len(self.tag)) if self.parent[n] == above]
            held: dict[int, list[int]] = {}
            for node, text, linked in self.blocks:
                up = node
                while up > 0 and self.parent[up] != above:
                    up = self.parent[up]
                if up > 0:
                    total = held.setdefault(up, [0, 0])
                    total[0] += len(text)
                    total[1] += linked
            for n in siblings:
                size, linked = held.get(n, (0, 0))
                if not size or n == best:
                    continue
                near = points[n] >= max(10, 0.2 * points[best])
                plain = self.tag[n] in ("p", "pre", "blockquote") and linked < 0.25 * size
                if (near and linked < 0.5 * size) or plain or (self.tag[n] in HEADINGS and n < best):
                    keep.add(n)
        kept: dict[int, bool] = {}
        for n in range(len(self.tag)):
            kept[n] = n in keep or kept.get(self.parent[n], False)
        return " ".join(text for node, text, _ in self.blocks if kept[node])


def extract(source: str | None) -> str:
    """Main text of one page."""
    return Page(source or "").main_text()


def main_texts(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars; map-only."""
    small_batches(pages.sparkSession, 500)

    def run(batches) -> Iterator:
        import pyarrow as pa

        for batch in batches:
            found = [extract(h.as_py()) for h in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found, pa.string()), pa.array([len(t) for t in found], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html").mapInArrow(run, "page_id long, url string, text string, n_chars long")


def op5_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Contract query over all pages."""
    return main_texts(spark.read.parquet(f"{sf_dir}/pages.parquet"))
