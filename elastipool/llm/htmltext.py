"""Main text of web pages by tree scoring.

A tolerant scanner builds the element tree (unclosed paragraphs and list items end where HTML says; unknown end tags are passed over). Elements
that cannot be main text (menus, headers, footers, sidebars, notices, adverts, forms, scripts, styles, reader comments; by tag, role, class or id) are set
aside, unless most of the page's paragraph text lies in one named so. A name that is also a usual name of an article's own section (``OPEN_NAMES``) sets
an element inside an article aside only if links make much of it, or it holds form controls or something named like an aside. Each remaining paragraph earns points for itself, its commas and its length, and passes them to its
ancestors: all to the parent, half to the grandparent, then a third of that share for each step; a container's points are discounted by the share of its text that is in links.
The best container is kept, with those siblings that score near it, are paragraphs, or hold paragraphs that are not mostly links.

Character references are decoded; white space inside a block becomes one space; blocks follow page order, one to a line. Null and empty pages, and pages without text,
give an empty text. Nothing is dropped by length and nothing is capped. Repeated rows are extracted alike; other columns are not read; an empty table gives an empty result.
"""

from __future__ import annotations

import re
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from elastipool.llm.common import prepare, table

OUT = "page_id long, url string, text string, n_chars long"
_MARKUP = re.compile(r"""<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|</?[a-zA-Z](?>"[^"]*"|'[^']*'|[^>"'])*+>|</?[a-zA-Z][^>]*(?:>|\Z)""", re.S)
_NAME = re.compile(r"</?([a-zA-Z][^\s/>]*)")
_ATTR = re.compile(r"""([a-zA-Z][\w:-]*)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>"']+))?""")
_TOKEN = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])")
#: Element kinds of HTML, and names of what is not main text.
RAW = {"script", "style", "textarea", "title", "noscript", "template", "iframe", "xmp", "noembed", "noframes"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
INLINE = {
    "a", "abbr", "acronym", "b", "bdi", "bdo", "big", "br", "cite", "code", "data", "del", "dfn", "em", "font", "i", "img", "ins", "kbd", "label", "mark", "q", "s",
    "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr",
}
ENDS_P = {
    "address", "article", "aside", "blockquote", "center", "details", "dialog", "div", "dl", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3",
    "h4", "h5", "h6", "header", "hr", "main", "menu", "nav", "ol", "p", "pre", "section", "table", "ul",
}
SELF_ENDING = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"tr", "table"}, "th": {"tr", "table"}, "option": {"select"}}
ASIDE_TAGS = {"nav", "footer", "header", "aside", "form", "button", "select", "svg", "canvas", "object", "menu", "dialog", "head", "math", "audio", "video"} | RAW
ASIDE_ROLES = {"navigation", "banner", "complementary", "contentinfo", "search", "form", "dialog", "alert", "alertdialog", "menu", "menubar"}
ASIDE_NAMES = {
    "ad", "ads", "adv", "advert", "adverts", "advertisement", "advertising", "adsense", "adslot", "adbox", "alert", "banner", "breadcrumb", "breadcrumbs", "captcha", "comment",
    "comments", "commentlist", "consent", "cookie", "cookies", "disqus", "discussion", "disclaimer", "footer", "foot", "gdpr", "header", "login", "masthead", "menu", "menubar", "modal", "nav",
    "navbar", "navigation", "newsletter", "notice", "notices", "notification", "overlay", "pager", "pagination", "popup", "promo", "promoted", "promotion", "recommended", "related", "remark", "replies", "reply", "respond", "search", "share",
    "sharing", "shoutbox", "sidebar", "sidebox", "signup", "social", "sponsor", "sponsored", "subscribe", "subscription", "toolbar", "topbar", "toast", "widget",
}
OPEN_NAMES = {"alert", "discussion", "disclaimer", "foot", "related", "remark", "reply", "search", "share", "sharing"}
CONTROLS = {"button", "input", "select", "textarea"}
GOOD_NAMES = {"article", "body", "content", "entry", "hentry", "main", "page", "post", "story", "text"}
TAG_POINTS = {"article": 30.0, "main": 20.0, "div": 5.0, "section": 5.0, "pre": 3.0, "td": 3.0, "blockquote": 3.0, "ol": -3.0, "ul": -3.0, "dl": -3.0, "li": -3.0, "address": -3.0}
PARAGRAPHS = {"p", "pre", "td", "blockquote", "li", "dd"}
LEAST_PARAGRAPH, STEPS = 25, 6


class Page:
    """Elements in page order: tag, parent, whether set aside, name points, and texts as (element, text)."""

    def __init__(self, html: str):
        self.tag, self.parent, self.aside, self.points, self.named, self.open_name = ["#root"], [-1], [False], [0.0], [False], [False]
        self.texts: list[tuple[int, str | None]] = []  # None: a block begins or ends
        open_, at = [0], 0
        m = _MARKUP.search(html)
        while m:
            if m.start() > at:
                self.texts.append((open_[-1], html[at : m.start()]))
            at, s = m.end(), m.group()
            name = _NAME.match(s)
            if s.startswith("<![CDATA["):
                self.texts.append((open_[-1], s[9:-3].replace("&", "&amp;")))
            elif name:
                tag = name.group(1).lower()
                if s[1] == "/":
                    self._end(open_, tag)
                else:
                    self._start(open_, tag, s, name.end())
                    if tag in RAW and not s.endswith("/>"):
                        end = re.compile(rf"</{re.escape(tag)}\s*>|\Z", re.I).search(html, at)
                        at = end.end()
                        self._end(open_, tag)
            m = _MARKUP.search(html, at)
        if at < len(html):
            self.texts.append((open_[-1], html[at:]))

    def _end(self, open_, tag):
        for k in range(len(open_) - 1, 0, -1):
            if self.tag[open_[k]] == tag:
                del open_[k:]
                if tag not in INLINE:
                    self.texts.append((open_[-1], None))
                return
            if tag in INLINE and self.tag[open_[k]] not in INLINE:
                return

    def _start(self, open_, tag, s, at):
        if tag in ENDS_P:
            for k in range(len(open_) - 1, 0, -1):
                if self.tag[open_[k]] == "p":
                    del open_[k:]
                    break
                if self.tag[open_[k]] not in INLINE:
                    break
        elif tag in SELF_ENDING:
            for k in range(len(open_) - 1, 0, -1):
                t = self.tag[open_[k]]
                if t == tag or (tag in ("dt", "dd") and t in ("dt", "dd")) or (tag in ("td", "th") and t in ("td", "th")):
                    del open_[k:]
                    break
                if t in SELF_ENDING[tag]:
                    break
        aside, points, named, open_name = tag in ASIDE_TAGS, TAG_POINTS.get(tag, 0.0), False, False
        if len(s) > at + 1:
            for m in _ATTR.finditer(s, at):
                key, value = m.group(1).lower(), (m.group(2) or "").strip("\"'")
                if key in ("class", "id"):
                    names = {x.lower() for x in _TOKEN.findall(value)}
                    bad = names & ASIDE_NAMES
                    named |= bool(bad - OPEN_NAMES)
                    open_name |= bool(bad)
                    if names & GOOD_NAMES:
                        points += 25.0
                elif key == "role" and value.lower() in ASIDE_ROLES:
                    named = True
                elif key == "hidden" or (key == "aria-hidden" and value.lower() == "true") or (key == "style" and "display:none" in value.replace(" ", "").lower()):
                    aside = True
        if tag in ("html", "body", "article", "main"):
            aside = named = open_name = False
        self.tag.append(tag)
        self.parent.append(open_[-1])
        self.aside.append(aside)
        self.named.append(named)
        self.open_name.append(open_name and not named)
        self.points.append(points)
        self.texts.append((open_[-1], " " if tag == "br" else "" if tag in INLINE else None))
        if tag not in VOID and not s.endswith("/>"):
            open_.append(len(self.tag) - 1)


def main_text(html: str | None) -> str:
    """The main text of one page."""
    if not html:
        return ""
    p = Page(html)
    n = len(p.tag)
    # what is named like an aside but holds an article or most of the paragraph text is a page's frame, not an aside
    weight, links, holds, article, busy = [0] * n, [0] * n, [False] * n, [False] * n, [False] * n
    link = [False] * n
    for e in range(1, n):
        link[e] = link[p.parent[e]] or p.tag[e] == "a"
        article[e] = article[p.parent[e]] or p.tag[e] in ("article", "main")
    p.texts = [(e, t) for e, t in p.texts if p.tag[e] not in RAW]
    for e, t in p.texts:
        weight[e] += len(t or "")
        links[e] += len(t or "") * link[e]
    for e in range(n - 1, 0, -1):
        weight[p.parent[e]] += weight[e]
        links[p.parent[e]] += links[e]
        busy[p.parent[e]] |= busy[e] or p.named[e] or p.tag[e] in CONTROLS
        holds[p.parent[e]] |= holds[e] or p.tag[e] in ("article", "main")
    for e in range(1, n):
        bad = p.named[e] or (p.open_name[e] and (not article[e] or busy[e] or 3 * links[e] >= weight[e]))
        if bad and not holds[e] and 2 * weight[e] <= weight[0]:
            p.aside[e] = True
        p.aside[e] |= p.aside[p.parent[e]]
    block = [0] * n  # the nearest block element at or above
    for e in range(1, n):
        block[e] = block[p.parent[e]] if p.tag[e] in INLINE else e
    has_block = [False] * n
    for e in range(1, n):
        if block[e] == e and p.tag[e] not in VOID:
            has_block[p.parent[e]] = True
    size, linked, told, parts = [0] * n, [0] * n, [0] * n, {}
    for e, t in p.texts:
        if p.aside[e] or not t:
            continue
        size[e] += len(t)
        told[e] += len(t.strip()) * (p.tag[block[e]] == "p" and not link[e])
        if link[e]:
            linked[e] += len(t)
        parts.setdefault(block[e], []).append(t)
    for e in range(n - 1, 0, -1):
        size[p.parent[e]] += size[e]
        linked[p.parent[e]] += linked[e]
        told[p.parent[e]] += told[e]
    score: dict[int, float] = {}
    for b, ts in parts.items():
        text = "".join(ts)
        if len(text) < LEAST_PARAGRAPH or b == 0 or not (p.tag[b] in PARAGRAPHS or not has_block[b]):
            continue
        gain = 1.0 + text.count(",") + min(len(text) // 100, 3)
        a, share = p.parent[b], 1.0
        for step in range(STEPS):
            if a <= 0:
                break
            score[a] = score.get(a, p.points[a]) + gain * share
            share = share / 2 if step == 0 else share / 3
            a = p.parent[a]
    for a in score:
        score[a] *= 1.0 - linked[a] / max(1, size[a])
    if score:
        best = max(score, key=lambda a: (score[a], -a))
    else:
        # too little text for points: the first article, main or body, or the whole page
        best = next((e for t in ("article", "main", "body") for e in range(n) if p.tag[e] == t and not p.aside[e]), 0)
    keep = {best}
    if p.tag[best] not in ("article", "main", "body"):
        least = max(10.0, 0.2 * score.get(best, 0.0))
        for e in range(1, n):
            if p.parent[e] == p.parent[best] and not p.aside[e] and e != best:
                dense = linked[e] / max(1, size[e])
                if score.get(e, 0.0) >= least or (told[e] and dense < 0.25) or (p.tag[e] in ("h1", "h2") and e < best and dense < 0.25):
                    keep.add(e)
    inside = [False] * n
    for e in range(n):
        inside[e] = e in keep or (e > 0 and inside[p.parent[e]])
    return _blocks(p, inside)


def _blocks(p: Page, inside: list[bool]) -> str:
    out, held = [], []

    def flush():
        if held:
            s = "".join(held)
            s = " ".join((unescape(s) if "&" in s else s).split())
            if s:
                out.append(s)
            held.clear()

    for e, t in p.texts:
        if t is None:
            flush()
        elif not p.aside[e] and inside[e]:
            held.append(t)
    flush()
    return "\n".join(out)


def extracted(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(page_id, url, text, n_chars) for every page; map-only."""
    prepare(pages.sparkSession)

    def run(batches):
        for b in batches:
            texts = [main_text(h) for h in b.column(2).to_pylist()]
            yield pa.RecordBatch.from_pydict({"page_id": b.column(0), "url": b.column(1), "text": pa.array(texts, pa.string()), "n_chars": pa.array([len(t) for t in texts], pa.int64())})

    return pages.select(pages[id_col].cast("long").alias("page_id"), pages[url_col].cast("string").alias("url"), pages[html_col].cast("string").alias("html")).mapInArrow(run, OUT)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extracted(table(spark, sf_dir, "pages"))
