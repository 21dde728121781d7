"""Main text of web pages by composite text density.

Each page becomes a DOM of arrays.  For every node: characters, tags, characters and tags
in links, over all visible text, menus and adverts included; its density is characters per
tag, adjusted by the links' share as measured against the body; its sum is the total of its
children's densities.  The node with the largest sum is kept, and the least density on the
path from it to the body is the threshold: beside the path, a node goes on only if its density
reaches the threshold (and, right below the body, the largest sum in its branch does too), and of its
branch again the subtree with the largest sum is kept, and so on down.  So every group of
paragraphs stays, whatever their sizes to each other.  A paragraph, heading, list or table without
links stays with its siblings on the path below the body, however short; inside a kept subtree
only containers that are mostly links go.

Lists of elements, roles and class words name what the contract excludes whatever its
density (menus, footers, comments, ...).  They take such nodes out of the choice and out of the text,
but not out of the densities, and no element name pulls a node in.  A class or id counts only if it
consists of such words throughout.  ``marks=False`` leaves everything to the densities.

Defined results: null or empty html gives empty text; broken or cut-off markup is read as
far as it goes; nesting of any depth costs time in proportion to the page; repeated rows are
read each; pages of any length are read whole; an empty table gives an empty table; only the
id, url and html columns are read, so other columns may have any name.
"""

from __future__ import annotations

import html
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)"
    r"|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>"
    r"|<(/?)([a-zA-Z][^\s/>]*)([^>]*)>"
    r"|<[!?/][^>]*>"
    r"|<[a-zA-Z/!?][^>]*\Z",
    re.S,
)
_ATTRIBUTE = re.compile(r"(class|id|role|hidden|aria-hidden|style)\b\s*(?:=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+))?", re.I)
_SPLIT = re.compile(r"[^a-z0-9]+|(?<=[a-z])(?=[0-9])")

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe xmp noembed noframes".split())
#: Elements that never hold the article's text.
FURNITURE = frozenset("head nav footer aside form button select option datalist dialog menu template svg math canvas object audio video map".split()) | RAW
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
#: Words of a class or id, and roles, that mark furniture.
MARKS = frozenset("ad ads advert adverts advertisement advertising sponsor sponsored promo promotion banner sidebar menu nav navbar navigation breadcrumb breadcrumbs footer header masthead comment comments disqus replies cookie cookies consent gdpr notice notices newsletter subscribe signup share sharing social related recommended popup modal overlay pagination pager toolbar skip".split())
#: Words that say nothing beside such a word.
BESIDE = frozenset("a all area articles author bar block bottom box btn button buttons center col container content custom fixed floating footer global google group head holder inner item items js large left link links list local main mobile module more outer page posts primary region right row secondary section side site skyscraper slot small social sticky sub text thread title to top unit widget widgets wrap wrapper".split())
#: Blocks of text: without links they stay with the siblings of the kept node.
TEXTUAL = frozenset("p h1 h2 h3 h4 h5 h6 pre blockquote ul ol dl li dt dd table figure figcaption address hr".split())
#: Least share of links that is taken as usual.
LEAST_SHARE = 0.02
#: Containers of a kept subtree that go if they are mostly links.
LISTS = frozenset("div section ul ol dl table".split())
ROLES = frozenset("navigation banner contentinfo complementary search alert alertdialog dialog form menu menubar toolbar".split())
#: What a start tag closes, if it is open inside the given limits.
CLOSES = {t: (frozenset(["p"]), frozenset("body article section div main td th li blockquote button".split())) for t in "address article aside blockquote center details div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hr main menu nav ol p pre section table ul".split()}
CLOSES |= {"li": (frozenset(["li"]), frozenset(["ul", "ol", "menu"])), "option": (frozenset(["option"]), frozenset(["select"])), "tr": (frozenset(["tr"]), frozenset(["table"])), "td": (frozenset(["td", "th"]), frozenset(["tr", "table"])), "th": (frozenset(["td", "th"]), frozenset(["tr", "table"])), "dt": (frozenset(["dt", "dd"]), frozenset(["dl"])), "dd": (frozenset(["dt", "dd"]), frozenset(["dl"]))}
ROOTS = frozenset(["html", "body", "article", "main"])


def says_furniture(names: str) -> bool:
    """Whether one of the names of a class or id is made of marking words."""
    for name in names.split():
        words = [w for w in _SPLIT.split(name) if w and not w.isdigit()]
        if not MARKS.isdisjoint(words) and all(w in MARKS or w in BESIDE for w in words):
            return True
    return False


def is_hidden(attributes: str) -> bool:
    for m in _ATTRIBUTE.finditer(attributes):
        name, value = m[1].lower(), (m[2] or "").strip("\"'").lower()
        if name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "style" and "display:none" in value.replace(" ", "")):
            return True
    return False


def is_furniture(tag: str, attributes: str, inside_article: bool) -> bool:
    if tag in FURNITURE or (tag == "header" and not inside_article):
        return True
    if tag in ROOTS or not attributes:
        return False
    for m in _ATTRIBUTE.finditer(attributes):
        name, value = m[1].lower(), (m[2] or "").strip("\"'").lower()
        if name in ("class", "id") and says_furniture(value) or name == "role" and value in ROLES:
            return True
    return False


class Dom:
    """Nodes in document order: tag, parent, whether unseen or furniture, and pieces of text as (node, text)."""

    def __init__(self, page: str, marks: bool = True):
        self.tags, self.parents, self.unseen, self.marked = ["#"], [-1], [False], [False]
        self.pieces: list[tuple[int, str]] = []
        self.stack = [0]
        #: Places in the stack by tag, so that no tag is looked for by walking the stack.
        self.open: dict[str, list[int]] = {}
        at, end = 0, len(page)
        while at < end:
            m = _TOKEN.search(page, at)
            if not m:
                self.pieces.append((self.stack[-1], page[at:]))
                break
            if m.start() > at:
                self.pieces.append((self.stack[-1], page[at : m.start()]))
            at = m.end()
            tag = m[2] or m[5]
            if not tag:
                continue
            tag = tag.lower()
            if m[1] or m[4]:
                if tag not in ("body", "html"):
                    if self.open.get(tag):
                        self.close(self.open[tag][-1])
                    self.pieces.append((self.stack[-1], "" if tag in INLINE else "\0"))
                continue
            attributes = m[3] or m[6] or ""
            if tag in CLOSES:
                closed, limits = CLOSES[tag]
                place = self.last(closed)
                if place > self.last(limits):
                    self.close(place)
            if tag == "body" and self.open.get("head"):
                self.close(self.open["head"][0])
            node, parent = len(self.tags), self.stack[-1]
            self.tags.append(tag)
            self.parents.append(parent)
            self.unseen.append(self.unseen[parent] or tag in RAW or tag == "head" or bool(attributes) and is_hidden(attributes))
            self.marked.append(self.marked[parent] or marks and is_furniture(tag, attributes, bool(self.open.get("article"))))
            if tag not in INLINE:
                self.pieces.append((parent, "\0"))
            if tag in VOID or attributes.endswith("/"):
                continue
            if tag in RAW:
                close = re.compile(rf"</{tag}\b[^>]*>", re.I).search(page, at)
                at = close.end() if close else end
                continue
            self.open.setdefault(tag, []).append(len(self.stack))
            self.stack.append(node)

    def last(self, tags: frozenset) -> int:
        """The topmost place of any of these tags in the stack; 0 if none is open."""
        return max((self.open[t][-1] for t in tags if self.open.get(t)), default=0)

    def close(self, place: int) -> None:
        while len(self.stack) > place:
            self.open[self.tags[self.stack.pop()]].pop()


class Densities:
    """Characters, tags, densities and their sums of all nodes of a page."""

    def __init__(self, dom: Dom):
        self.dom, n = dom, len(dom.tags)
        self.chars, self.tags, self.link_chars, self.link_tags = [0] * n, [1] * n, [0] * n, [0] * n
        linked = [False] * n
        for i in range(1, n):
            linked[i] = dom.tags[i] == "a" or linked[dom.parents[i]]
        self.texts = []
        for node, piece in dom.pieces:
            if piece and piece != "\0" and not dom.unseen[node]:
                piece = html.unescape(piece) if "&" in piece else piece
                size = len(piece.strip())
                self.chars[node] += size
                self.link_chars[node] += size * linked[node]
            self.texts.append((node, " " if piece == "\0" else piece))
        for i in range(n - 1, 0, -1):
            if not dom.unseen[i]:
                p = dom.parents[i]
                self.chars[p] += self.chars[i]
                self.link_chars[p] += self.link_chars[i]
                self.tags[p] += self.tags[i]
                self.link_tags[p] += self.link_tags[i] + (dom.tags[i] == "a")
        self.body = next((i for i in range(n) if dom.tags[i] == "body"), 0)
        # The body's shares of link characters and of links: what is usual on this page.
        self.char_share = max(LEAST_SHARE, self.link_chars[self.body] / max(1, self.chars[self.body]))
        self.tag_share = max(LEAST_SHARE, self.link_tags[self.body] / self.tags[self.body])
        self.own = [0.0 if dom.unseen[i] else self.density(i) for i in range(n)]
        self.sums = [0.0] * n
        for i in range(1, n):
            if not (dom.unseen[i] or dom.marked[i] or dom.tags[i] in INLINE):
                self.sums[dom.parents[i]] += self.own[i]

    def density(self, i: int) -> float:
        """Characters per tag, times a logarithm that falls from that of link-free text to 0 as links take over."""
        c, t = self.chars[i], self.tags[i]
        if not c:
            return 0.0
        rest = c / (self.link_chars[i] + self.char_share * c) * t / (self.link_tags[i] + self.tag_share * t)
        return c / t * math.log(max(rest, 1.0))


#: What becomes of a node: gone, on the path to the largest sum of its branch, or kept whole.
GONE, PATH, WHOLE = 0, 1, 2


def kept_nodes(d: Densities) -> list[int]:
    """GONE, PATH or WHOLE for every node."""
    dom, n = d.dom, len(d.dom.tags)
    out = [dom.unseen[i] or dom.marked[i] for i in range(n)]
    state = [GONE] * n
    # The node with the largest sum in each subtree (then the most characters, then the first).
    best = [-1 if out[i] or dom.tags[i] in INLINE or not d.chars[i] else i for i in range(n)]
    rank = lambda i: (d.sums[i], d.chars[i], -i)
    for i in range(n - 1, 0, -1):
        p = dom.parents[i]
        if best[i] >= 0 and not out[p] and (best[p] < 0 or rank(best[i]) > rank(best[p])):
            best[p] = best[i]
    if best[0] < 0:
        return state

    def enter(root: int) -> None:
        node = best[root]
        state[node] = WHOLE
        while node != root:
            node = dom.parents[node]
            state[node] = PATH

    node = best[0]
    threshold = d.own[node]
    while node not in (d.body, 0):
        node = dom.parents[node]
        threshold = min(threshold, d.own[node])
    enter(0)
    for i in range(1, n):
        p = dom.parents[i]
        if state[i] or out[i] or not state[p]:
            continue
        inline = dom.tags[i] in INLINE
        if state[p] == WHOLE:
            menu = dom.tags[i] in LISTS and d.own[i] < threshold and d.link_tags[i] > 1 and 2 * d.link_chars[i] > d.chars[i]
            state[i] = GONE if menu else WHOLE
        elif inline:
            state[i] = WHOLE if p not in (d.body, 0) else GONE
        elif best[i] >= 0 and d.own[i] >= threshold and (d.sums[best[i]] >= threshold or p not in (d.body, 0)):
            enter(i)
        elif dom.tags[i] in TEXTUAL and not d.link_chars[i] and p not in (d.body, 0):
            state[i] = WHOLE
    return state


def main_text(page: str | None, marks: bool = True) -> str:
    if not page:
        return ""
    dom = Dom(page, marks)
    d = Densities(dom)
    state = kept_nodes(d)
    keep = [s == WHOLE or s == PATH and i not in (d.body, 0) for i, s in enumerate(state)]
    return " ".join("".join(t for node, t in d.texts if keep[node] or t == " ").split())


def extract(df: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """One row per page: page_id, url, text, n_chars."""
    rows = df.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url"), F.col(html_col).cast("string").alias("html"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(page.as_py()) for page in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], ["page_id", "url", "text", "n_chars"])

    return rows.mapInArrow(run, f"page_id {rows.schema['page_id'].dataType.simpleString()}, url {rows.schema['url'].dataType.simpleString()}, text string, n_chars long")
