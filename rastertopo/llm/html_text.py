"""Main text of web pages by composite text density.

A page becomes a tree. Parts that never hold the article (menus, headers, footers, asides, forms, adverts, notices,
reader comments, scripts, hidden parts) are pruned by tag, role, class and id. Of every remaining node the characters,
tags, link characters and link tags are counted; its density is its characters per tag, weighed by a logarithm that
falls with the share of links. The node whose children's densities sum highest is the kernel; the least density on
the path from it to the body is the threshold, and in every subtree that reaches the threshold the node of the highest
sum is taken. A taken node within a declared article or main element stands for the innermost such element, so that
headings and short paragraphs beside it aren't lost; several articles of a page all come, in page order.

Cases: null and empty pages give an empty text; a page without tags is all text; broken, unclosed and cut off markup
is read as browsers do; character references are decoded; a repeated page_id is a row of its own; other columns are
ignored. The tree is walked without recursion, so deep nesting and long pages are safe.
"""

from __future__ import annotations

import html
import math
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import slices

TAG = re.compile(
    r"""<!--(?:.*?-->|.*\Z)|<[!?][^>]*(?:>|\Z)|</([a-zA-Z][^\s/>]*)[^>]*(?:>|\Z)|<([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)>|<([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)""",
    re.S,
)
ATTRIBUTE = re.compile(r"""([^\s=/"']+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
WORD = re.compile(r"[A-Z]?[a-z]+|[A-Z]+|\d+")

# Element classes of HTML.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style xmp iframe noembed noframes textarea title".split())
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split()
)
CLOSES_P = frozenset(
    "address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split()
)
SIBLINGS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",), "tbody": ("tbody", "thead", "tr", "td", "th"), "optgroup": ("optgroup", "option")}
SCOPE = frozenset("html body table td th ul ol dl article section main div button object template caption select".split())
# What is never part of an article.
PRUNED_TAGS = frozenset(
    "nav footer aside form script style noscript template iframe button select option textarea input svg canvas head title dialog menu object applet audio video map datalist xmp noembed noframes".split()
)
PRUNED_ROLES = frozenset("navigation banner contentinfo complementary search form dialog alertdialog alert menu menubar toolbar tablist".split())
PRUNED_WORDS = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense adslot banner sponsor sponsors sponsored promo promos promotion promoted cookie cookies consent gdpr notice notices popup modal overlay newsletter subscribe subscription sidebar sidebars widget widgets related recommended recommendations share sharing social comment comments commentlist disqus respond reply replies nav navbar navigation menu menus breadcrumb breadcrumbs footer masthead login signup signin pagination pager toolbar skip outbrain taboola".split()
)
#: Words that say what a part is made of; a name of these and words above is boilerplate, "share-price" isn't.
FRAME_WORDS = frozenset(
    "a area bar block bottom box btn button buttons col column container content desktop feed footer form full global group grid header icon icons inner item items left link links list main media mobile outer page panel posts primary right row secondary section site slot small sticky text the title to top unit widget wrap wrapper".split()
)
COMMENT_WORDS = frozenset("comment comments commentlist reply replies".split())
KEPT_WORDS = frozenset("article main post body entry story".split())
DECLARED = frozenset(("article", "main"))


def _attributes(text: str) -> dict[str, str]:
    return {m[1].lower(): m[2] or m[3] or m[4] or "" for m in ATTRIBUTE.finditer(text)} if text.strip(" /") else {}


def _boilerplate(tag: str, attributes: dict[str, str], in_article: bool) -> bool:
    if tag in PRUNED_TAGS or tag == "header" and not in_article:
        return True
    if not attributes or tag in ("html", "body"):
        return False
    if "hidden" in attributes or attributes.get("aria-hidden") == "true" or re.search(r"display\s*:\s*none", attributes.get("style", "")):
        return True
    if attributes.get("role", "").lower() in PRUNED_ROLES:
        return True
    if tag in DECLARED and attributes.get("itemprop", "").lower() == "comment":
        return True
    for key in ("class", "id"):
        for name in attributes.get(key, "").split():
            words = [w.lower() for w in WORD.findall(name)]
            told = [w for w in words if w not in FRAME_WORDS and not w.isdigit()]
            if tag in DECLARED:
                # An article is one unless it says that it is a reader's comment.
                if words and words[0] in COMMENT_WORDS and not set(words) & KEPT_WORDS:
                    return True
                continue
            listed = [w for w in words if w in PRUNED_WORDS]
            if listed and all(w in PRUNED_WORDS for w in told):
                return True
            if not in_article and "header" in words and not set(words) & KEPT_WORDS:
                return True
    return False


class Page:
    """The tree of a page as parallel lists; a parent comes before its children. Node 0 is the body."""

    def __init__(self, source: str):
        self.tag, self.parent, self.drop, self.items = ["body"], [-1], [False], [[]]
        self.declared = [False]
        stack = [0]
        at, n = 0, len(source)
        while at < n:
            m = TAG.search(source, at)
            end = m.start() if m else n
            if end > at:
                self.items[stack[-1]].append(html.unescape(source[at:end]))
            if not m:
                break
            at = m.end()
            if m[1]:
                self._close(stack, m[1].lower())
            elif name := m[2] or m[4]:
                tag, attributes = name.lower(), m[3] or m[5] or ""
                at = self._open(stack, tag, attributes, source, at)

    def _close(self, stack: list[int], tag: str) -> None:
        if tag in ("body", "html"):
            return
        for depth in range(len(stack) - 1, 0, -1):
            if (open_tag := self.tag[stack[depth]]) == tag:
                del stack[depth:]
                return
            if tag in INLINE and open_tag not in INLINE and open_tag != "p":
                return

    def _open(self, stack: list[int], tag: str, text: str, source: str, at: int) -> int:
        if tag in ("html", "body"):
            return at
        closed = ("p",) if tag in CLOSES_P else SIBLINGS.get(tag, ())
        if closed:
            for depth in range(len(stack) - 1, 0, -1):
                if (open_tag := self.tag[stack[depth]]) in closed:
                    del stack[depth:]
                    if tag in CLOSES_P or tag in ("li", "option"):
                        break
                elif open_tag in SCOPE:
                    break
        top = stack[-1]
        attributes = _attributes(text)
        node = len(self.tag)
        self.tag.append(tag)
        self.parent.append(top)
        self.declared.append(self.declared[top] or tag in DECLARED or attributes.get("role") == "main")
        self.drop.append(self.drop[top] or _boilerplate(tag, attributes, self.declared[top]))
        self.items.append([])
        self.items[top].append(node)
        if tag in RAW:
            close = re.compile(f"</{tag}[^>]*(?:>|\\Z)", re.I).search(source, at)
            return close.end() if close else len(source)
        if tag not in VOID:
            stack.append(node)
        return at

    def densities(self) -> tuple[list[float], list[float]]:
        """For each node its density and the sum of its children's densities."""
        n = len(self.tag)
        chars, tags, link_chars, link_tags = [0] * n, [0] * n, [0] * n, [0] * n
        for i in range(n - 1, -1, -1):
            if self.drop[i]:
                continue
            chars[i] += sum(len(x) for s in self.items[i] if isinstance(s, str) for x in s.split())
            if self.tag[i] == "a":
                link_chars[i], link_tags[i] = chars[i], link_tags[i] + 1
            if (p := self.parent[i]) >= 0:
                chars[p] += chars[i]
                tags[p] += tags[i] + 1
                link_chars[p] += link_chars[i]
                link_tags[p] += link_tags[i]
        density, sums = [0.0] * n, [0.0] * n
        body_links = link_chars[0] / max(chars[0], 1)
        for i in range(n - 1, -1, -1):
            if self.drop[i] or not chars[i]:
                continue
            c, t, lc, lt = chars[i], max(tags[i], 1), max(link_chars[i], 1), max(link_tags[i], 1)
            # The base is at least ln(1 + e), as a link counts one character at least.
            base = math.log(c / max(c - link_chars[i], 1) * lc + body_links * c + math.e)
            density[i] = c / t * math.log(max(c / lc * t / lt, 1e-9)) / math.log(base) if c > link_chars[i] else 0.0
            if (p := self.parent[i]) >= 0:
                sums[p] += max(density[i], 0.0)
        return density, sums

    def roots(self) -> list[int]:
        """The subtrees that make up the article, in page order."""
        density, sums = self.densities()
        n = len(self.tag)
        kernel = max(range(n), key=lambda i: (sums[i], density[i], -i))
        path = [kernel]
        while self.parent[path[-1]] >= 0:
            path.append(self.parent[path[-1]])
        threshold = min(density[i] for i in path)
        best = list(range(n))
        for i in range(n - 1, 0, -1):
            p = self.parent[i]
            if sums[best[i]] > sums[best[p]] or sums[best[i]] == sums[best[p]] and best[p] != p and best[i] < best[p]:
                best[p] = best[i]
        taken = {best[i] for i in range(n) if not self.drop[i] and density[i] >= threshold and density[i] > 0} or {kernel}
        chosen = {self.article_of(i) for i in taken}
        inside = [False] * n
        roots = []
        for i in range(n):
            p = self.parent[i]
            inside[i] = p >= 0 and (inside[p] or p in chosen)
            if i in chosen and not inside[i]:
                roots.append(i)
        return roots

    def article_of(self, node: int) -> int:
        """The innermost declared element around a node, or the node."""
        at = node
        while at >= 0:
            if self.tag[at] in DECLARED:
                return at
            at = self.parent[at]
        return node

    def text(self, roots: list[int]) -> str:
        parts: list[str] = []
        work: list = list(reversed(roots))
        while work:
            x = work.pop()
            if isinstance(x, str):
                parts.append(x)
            elif not self.drop[x]:
                block = self.tag[x] not in INLINE
                if block:
                    parts.append(" ")
                    work.append(" ")
                work.extend(reversed(self.items[x]))
        return " ".join("".join(parts).split())


def main_text(source: str | None) -> str:
    """The article's text of one page."""
    if not source:
        return ""
    page = Page(source)
    return page.text(page.roots())


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row for each page: page_id, url, text, n_chars."""

    def task(batches):
        import pyarrow as pa

        for batch in slices(batches):
            texts = [main_text(x) for x in batch.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).alias("html"))
    return rows.mapInArrow(task, "page_id long, url string, text string, n_chars long")
