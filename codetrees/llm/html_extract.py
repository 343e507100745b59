"""Main-text extraction from HTML by scoring the tree.

One scan over the markup keeps a stack of open elements. Text gathers in blocks (the nearest block-level element); what
lies in menus, page headers, footers, sidebars, notices, adverts, forms, scripts, styles or comments never forms blocks.
Each block earns points for being there, for its length and its commas, less its share of link text, and passes them to
its ancestors, less with each level. The container with the most points after its own link density wins; if it lies in
an <article> or <main>, that element is taken. Siblings that score well or are long, link-poor paragraphs are kept too.
Blocks are joined in page order.

Elements are furniture by tag, role or hiding attribute, or by a class or id whose last word says so ("site-footer"), or
its first word when only words of layout follow ("related-posts", not "menu-item-description"). Words behind "no", "has",
"with" and the like say how a page is laid out and do not count. A name alone never takes away the element that holds
most of a page's text: unless it names comments, such an element is judged by its score like any other.

Edge rules: null html is empty; a page without text gives an empty string; broken or unclosed markup is read leniently;
nesting of any depth and pages of any length are handled without recursion; repeated pages give repeated rows; an empty
table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import html
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from codetrees.llm.common import small_batches, tidy

# Element kinds of HTML.
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
RAW = {"script", "style", "noscript", "template", "textarea", "title", "iframe", "svg", "math", "object", "canvas", "audio", "video"}
INLINE = {"a", "abbr", "acronym", "b", "bdi", "bdo", "big", "cite", "code", "data", "del", "dfn", "em", "font", "i", "ins", "kbd", "label", "mark", "q", "rp", "rt", "ruby", "s", "samp", "small", "span", "strike", "strong", "sub", "sup", "time", "tt", "u", "var", "wbr", "br", "img"}
PARAGRAPH = {"p", "h1", "h2", "h3", "h4", "h5", "h6", "li", "blockquote", "pre", "td", "th", "dd", "dt", "figcaption", "summary"}
CLOSES_P = {"p", "div", "ul", "ol", "dl", "table", "section", "article", "aside", "header", "footer", "nav", "main", "form", "fieldset", "figure", "hr", "h1", "h2", "h3", "h4", "h5", "h6", "pre", "blockquote", "address", "details"}
# Elements, roles and class words of page furniture.
JUNK_TAGS = {"nav", "footer", "aside", "form", "button", "select", "option", "dialog", "menu", "head", "fieldset", "datalist", *RAW}
JUNK_ROLES = {"navigation", "banner", "contentinfo", "complementary", "search", "dialog", "alert", "alertdialog", "form", "menu", "menubar", "toolbar"}
JUNK_WORDS = {
    "ad", "ads", "advert", "adverts", "advertisement", "advertising", "banner", "breadcrumb", "breadcrumbs", "comment", "comments", "consent", "cookie", "cookies", "copyright", "disqus", "footer", "gdpr", "hidden", "login", "menu", "modal", "nav", "navbar", "navigation",
    "newsletter", "notice", "overlay", "pager", "pagination", "popup", "promo", "promotion", "recommended", "related", "replies", "reply", "respond", "share", "sharing", "sidebar", "signup", "skip", "social", "sponsor", "sponsored", "subscribe", "teaser", "toolbar", "widget",
}
JUNK_STARTS = ("advert", "breadcrumb", "cookie", "navbar", "newsletter", "pagination", "sidebar", "sponsor", "subscri")
JUNK_ENDS = ("banner", "cookies", "footer", "navbar", "navigation", "popup", "sidebar")
COMMENT_WORDS = {"comment", "comments", "commentlist", "disqus", "replies", "reply", "respond"}
HEADER_WORDS = {"header", "masthead"}
CONTENT_WORDS = {"article", "body", "content", "entry", "main", "post", "story", "text"}
LAYOUT_MARKS = {"no", "non", "not", "without", "has", "have", "with", "hide", "show", "enable", "disable", "is", "js"}
LAYOUT_WORDS = {
    "area", "articles", "author", "avatar", "bar", "block", "body", "bottom", "box", "btn", "button", "buttons", "col", "column", "container", "content", "count", "form", "group", "holder", "icon", "icons", "inner", "item", "items", "label", "left", "link", "links", "list", "lists", "main", "meta", "nav", "news", "outer", "panel", "placeholder", "posts",
    "primary", "right", "row", "secondary", "section", "slot", "space", "stories", "text", "thread", "title", "toggle", "top", "topics", "unit", "wrap", "wrapper", "zone",
}

TOKEN = re.compile(r"<!--.*?(?:-->|$)|<![^>]*>|<\?[^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)>", re.S)
ATTRIBUTE = re.compile(r"([^\s\"'<>/=]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
HIDES = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)
WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])")
SPACE = re.compile(r"\s+")


def attributes(source: str) -> dict[str, str]:
    """Attributes of a tag by lower-case name; of repeated ones the first."""
    out: dict[str, str] = {}
    for m in ATTRIBUTE.finditer(source):
        out.setdefault(m[1].lower(), m[2] or m[3] or m[4] or "")
    return out


def _says_junk(word: str) -> bool:
    return word in JUNK_WORDS or word in COMMENT_WORDS or word.startswith(JUNK_STARTS) or word.endswith(JUNK_ENDS)


def name_kind(names: list[str]) -> int:
    """What classes and ids say of an element: 0 nothing, 1 page furniture, 2 comments."""
    kind, header, content = 0, False, False
    for name in names:
        words = [w.lower() for w in WORDS.findall(name)]
        words = words[: next((i for i, w in enumerate(words) if w in LAYOUT_MARKS), len(words))]
        if not words:
            continue
        header, content = header or bool(HEADER_WORDS & set(words)), content or bool(CONTENT_WORDS & set(words))
        rest = all(w in LAYOUT_WORDS or _says_junk(w) for w in words[1:])
        if words[-1] in COMMENT_WORDS or words[0] in COMMENT_WORDS and rest:
            return 2
        if _says_junk(words[-1]) or _says_junk(words[0]) and rest:
            kind = 1
    return max(kind, int(header and not content))


HARD = 2


def junk_kind(tag: str, attrs: str, in_article: bool) -> int:
    """Whether an element is page furniture: 0 no, 1 by its name alone, HARD surely."""
    if tag in JUNK_TAGS or tag == "header" and not in_article:
        return HARD
    if not attrs or tag in ("html", "body"):
        return 0
    found = attributes(attrs)
    if "hidden" in found or found.get("aria-hidden", "").lower() == "true" or HIDES.search(found.get("style", "")) or found.get("role", "").lower() in JUNK_ROLES:
        return HARD
    kind = name_kind([*found.get("class", "").split(), *found.get("id", "").split()])
    return kind if tag not in ("article", "main") or kind == HARD else 0


class Page:
    """Elements as parallel lists (tag, parent, junk kind, article) and blocks as (owner, text, link characters)."""

    def __init__(self, source: str):
        self.tag, self.parent, self.junk, self.article = ["#root"], [-1], [0], [-1]
        self.blocks: list[tuple[int, str, int]] = []
        self._scan(source)

    def _scan(self, source: str) -> None:
        tag, parent, junk, article = self.tag, self.parent, self.junk, self.article
        stack, parts, links, at, end, owner = [0], [], 0, 0, len(source), 0
        open_links = 0

        def flush():
            nonlocal parts, links
            if parts:
                text = SPACE.sub(" ", "".join(parts)).strip()
                if text:
                    self.blocks.append((owner, text, min(links, len(text))))
                parts, links = [], 0

        while at < end:
            m = TOKEN.search(source, at)
            stop = m.start() if m else end
            if stop > at and junk[stack[-1]] != HARD:
                raw = source[at:stop]
                text = html.unescape(raw) if "&" in raw else raw
                if parts or not text.isspace():
                    parts.append(text)
                    links += len(text.strip()) if open_links else 0
            if not m:
                break
            at = m.end()
            name = m[2]
            if not name:
                continue
            name = name.lower()
            if m[1]:
                if name in INLINE:
                    if name in ("a", "wbr", "br"):
                        open_links = max(0, open_links - 1) if name == "a" else open_links
                        if name == "br":
                            parts.append(" ")
                    continue
                for k in range(len(stack) - 1, 0, -1):
                    if tag[stack[k]] == name:
                        flush()
                        del stack[k:]
                        owner, open_links = stack[-1], 0
                        break
                continue
            if name in INLINE:
                if name == "a":
                    open_links = 1
                elif name == "br":
                    parts.append(" ")
                if m[3] and name not in VOID and not m[3].endswith("/") and junk_kind(name, m[3], True):
                    at = self._behind(source, at, name)
                    open_links = 0 if name == "a" else open_links
                continue
            if name in VOID:
                if name == "hr":
                    flush()
                continue
            flush()
            if name in CLOSES_P:
                for k in range(len(stack) - 1, 0, -1):
                    if tag[stack[k]] == "p":
                        del stack[k:]
                        break
                    if tag[stack[k]] not in PARAGRAPH:
                        break
            elif name in ("li", "dt", "dd", "tr", "td", "th", "option"):
                peers = {"dt", "dd"} if name in ("dt", "dd") else {"td", "th"} if name in ("td", "th") else {name}
                if tag[stack[-1]] in peers or tag[stack[-1]] == "p" and len(stack) > 2 and tag[stack[-2]] in peers:
                    while tag[stack[-1]] not in peers:
                        stack.pop()
                    stack.pop()
            up = stack[-1]
            node = len(tag)
            tag.append(name)
            parent.append(up)
            article.append(node if name in ("article", "main") and article[up] < 0 else article[up])
            junk.append(HARD if junk[up] == HARD else junk_kind(name, m[3], article[up] >= 0))
            open_links = 0
            if name in RAW:
                close = re.compile(rf"</{name}\s*>", re.I).search(source, at)
                at = close.end() if close else end
                owner = stack[-1]
                continue
            if m[3].endswith("/") and name in ("div", "p", "span"):
                pass  # a slash has no meaning on these
            stack.append(node)
            owner = node
        flush()


    @staticmethod
    def _behind(source: str, at: int, name: str) -> int:
        """Where an inline element that is open ends: behind its own end tag, or before the next tag of a block."""
        depth = 1
        for m in TOKEN.finditer(source, at):
            tag = (m[2] or "").lower()
            if tag == name:
                depth += -1 if m[1] else 1
                if not depth:
                    return m.end()
            elif tag and tag not in INLINE:
                return m.start()
        return len(source)


def points(text: str) -> float:
    """Points of a block: one for being there, one a comma, one a hundred characters up to three."""
    return 1 + text.count(",") + text.count("，") + min(len(text) // 100, 3)


def _without_furniture(page: Page) -> list[tuple[int, str, int]]:
    """Blocks outside of elements whose names say furniture, but for an element that holds most of the text in two
    paragraphs at least and is no list of links."""
    if not any(page.junk):
        return page.blocks
    n = len(page.tag)
    size, link, some = [0] * n, [0] * n, [0] * n
    for owner, text, links in page.blocks:
        node = owner
        while node >= 0:
            size[node] += len(text)
            link[node] += links
            some[node] += page.tag[owner] in PARAGRAPH
            node = page.parent[node]
    gone = [False] * n
    for i in range(1, n):
        most = 2 * size[i] > size[0] and some[i] > 1 and 3 * link[i] < size[i]
        gone[i] = gone[page.parent[i]] or page.junk[i] > 0 and not (page.junk[i] < HARD and most)
    return [b for b in page.blocks if not gone[b[0]]]


def main_text(source: str | None) -> str:
    """The main text of a page."""
    page = Page(source or "")
    n = len(page.tag)
    blocks = _without_furniture(page)
    if not blocks:
        return ""
    score, size, link = [0.0] * n, [0] * n, [0] * n
    for owner, text, links in blocks:
        gain = points(text) * (1 - links / len(text))
        node = page.parent[owner] if page.tag[owner] in PARAGRAPH and page.parent[owner] >= 0 else owner
        level = 0
        while node >= 0 and level < 5:
            score[node] += gain / (1 if level == 0 else 2 if level == 1 else 3 * level)
            node, level = page.parent[node], level + 1
        node = owner
        while node >= 0:
            size[node] += len(text)
            link[node] += links
            node = page.parent[node]
    final = [s * (1 - link[i] / size[i]) if size[i] else 0.0 for i, s in enumerate(score)]
    best = max(range(n), key=lambda i: (final[i], -i))
    whole = page.article[best]
    keep = {whole if whole >= 0 else best}
    top = next(iter(keep))
    floor = max(10.0, 0.2 * final[best])
    for i in range(n):
        if i != top and page.parent[i] == page.parent[top] and page.parent[i] >= 0 and size[i] and not page.junk[i]:
            density = link[i] / size[i]
            if whole >= 0:
                good = page.tag[i] == page.tag[top] and final[i] >= floor
            else:
                good = final[i] >= floor or page.tag[i] in PARAGRAPH and size[i] > 80 and density < 0.25
            if good:
                keep.add(i)
    inside = [False] * n
    for i in range(n):
        inside[i] = i in keep or page.parent[i] >= 0 and inside[page.parent[i]]
    return "\n".join(text for owner, text, _ in blocks if inside[owner])


def _extract(batches):
    import pyarrow as pa

    for b in batches:
        for at in range(0, b.num_rows, 256):
            part = b.slice(at, 256)
            texts = [main_text(h) for h in part.column("html").to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column("id"), part.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["id", "url", "text", "n_chars"])


def extract(df: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: id, url, text, n_chars."""
    small_batches(df.sparkSession)
    rows = df.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).cast("string").alias("html"))
    out = rows.mapInArrow(tidy(_extract), f"id {df.schema[id_col].dataType.simpleString()}, url string, text string, n_chars long")
    return out.withColumnRenamed("id", id_col).withColumnRenamed("url", url_col)


def op9_html_extract(spark, sf_dir: str) -> DataFrame:
    """Main text of all pages."""
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))
