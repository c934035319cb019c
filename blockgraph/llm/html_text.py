"""Main text of HTML pages by tree scoring.

A tolerant tokenizer finds elements and text (a block start ends an open
paragraph, items end items, an end tag closes what is open inside it, markup cut
off at the end of the page is dropped). The text between two block boundaries is
a paragraph. Each gives points: one for itself, one for each comma, one for each
hundred characters up to three, and a half for the end of a sentence. Its parent
gets them in full, the grandparent half, and so on upwards; an element's total
is discounted by the share of its text that is in links, and by what its tag and
names say. No name deletes anything by itself.

The element with the highest total is the main container. Everything else stands
or falls by its value, the mean points of its paragraphs after the same
discounts: elements in the container by 1, those beside it or beside an element
around it by that and ``SHARE`` of the container's own value. What holds the
container always stays, so several articles, or an article in parts that lie in
different elements, stay together. Names that speak of furniture weigh little
inside the container unless they can hardly mean anything else, such as reader
comments or adverts.

All steps are linear in the page, and nothing recurses.

Edge cases: a null or empty page, or one without text outside furniture, gives
an empty text; of containers with equal totals the first in page order wins;
very long and very deep pages are read whole; repeated pages are extracted each;
extra columns pass by unless kept.
"""

from __future__ import annotations

import html as entities
import re

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import portions

VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Elements whose content is not markup.
RAW = frozenset("script style textarea iframe title xmp noframes noembed".split())
#: Elements that show no text of the page, or belong to forms.
GONE = RAW | frozenset("noscript template svg math select datalist object canvas audio video map head button label fieldset".split())
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul caption legend".split()
)
#: What the paragraphs of a tag are worth to the elements around it, and those
#: of an element whose name speaks of furniture or may do so.
TAG_WORTH = {"nav": 0.0, "footer": 0.0, "aside": 0.0, "menu": 0.0, "dialog": 0.0, "header": 0.0, "form": 0.05}
NAMED, NAMED_MAYBE = 0.05, 0.4
HEADS = frozenset(("h1", "h2", "h3", "h4", "h5", "h6"))
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar toolbar form".split())
#: Words in class or id. The first hardly ever name content; the second may.
PLAIN = frozenset(
    "ad ads adv advert adverts advertisement advertising advertorial breadcrumb breadcrumbs comment comments commentlist consent cookie cookies disqus footer gdpr login masthead modal nav navbar navigation newsletter pager pagination paywall popup promo promotion promoted related reply replies respond share sharing sidebar signup skip sponsor sponsored subscribe toolbar topbar".split()
)
MAYBE = frozenset("alert aside author banner byline copyright disclaimer discussion feedback header hidden menu meta notice notices notification notifications overlay recommended rss search social subscription tags widget widgets".split())
#: Words that leave the meaning of the word before them as it is, those that
#: make the word after them one of the site's, and those that speak of content.
FRAME = frozenset("area bar block body bottom box button buttons column container content form group inner item items left link links list message outer panel post posts right row section slot text title top unit wrap wrapper".split())
SITE = frozenset("account cookie global legal main mobile nav page primary privacy secondary site top user".split())
GOOD = frozenset("article body content entry post story text hentry".split())
#: "with-sidebar" and the like describe a layout, not the element.
LAYOUT = frozenset("with has no without".split())
SHARE, MENU_LINKS = 0.2, 3
CLOSES = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "tbody": ({"tbody", "thead", "tfoot", "tr", "td", "th"}, {"table"}),
    "thead": ({"tbody", "thead", "tfoot", "tr", "td", "th"}, {"table"}), "tfoot": ({"tbody", "thead", "tfoot", "tr", "td", "th"}, {"table"}),
}
_STRUCTURE = {tag: i for i, group in enumerate((("li", "ul", "ol", "menu", "dir"), ("dt", "dd", "dl"), ("tr", "td", "th", "tbody", "thead", "tfoot", "table"))) for tag in group}
TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[(?P<cdata>.*?)(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)|<(?P<end>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<attrs>(?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?P<close>>|\Z)", re.S)
LOOSE_TAG = re.compile(r"</?[a-zA-Z][^>]*(?:>|\Z)", re.S)
ATTR = re.compile(r"([^\s=/\"'<>]+)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))|([^\s=/\"'<>]+)")
WORDS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
UNSEEN = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden")
SPACES = re.compile(r"\s+")
SENTENCE = re.compile(r"[.!?…。！？][\"'”’»)\]]*$")
ROOT = 0


class Page:
    """Elements in page order (tag, attributes, number of the parent), and what
    was met in page order: the number of an element at its start, its
    complement at its end, and strings."""

    def __init__(self, page: str):
        self.tag, self.attrs, self.parent, self.events = ["#root"], [""], [-1], [ROOT]
        self._open = [ROOT]  # elements
        self._scopes: list[tuple[int, dict[str, int]]] = [(0, {})]  # depth of open blocks, inline elements open in each
        self._blocks: dict[str, int] = {}
        self._structure: tuple[list[int], ...] = ([], [], [])  # depths of open list and table elements
        self._read(page)
        self._close_to(0)

    def _close_to(self, depth: int) -> None:
        """End the open elements from this depth on."""
        while len(self._open) > depth:
            node = self._open.pop()
            tag = self.tag[node]
            self.events.append(~node)
            if tag in BLOCK:
                self._scopes.pop()
                self._blocks[tag] -= 1
                if tag in _STRUCTURE:
                    self._structure[_STRUCTURE[tag]].pop()
            elif node != ROOT:
                self._scopes[-1][1][tag] -= 1

    def _start(self, tag: str, attrs: str, stays: bool) -> None:
        if tag in CLOSES:
            ends, bounds = CLOSES[tag]
            last = None
            for depth in reversed(self._structure[_STRUCTURE[tag]]):
                have = self.tag[self._open[depth]]
                if have in bounds:
                    break
                if have in ends:
                    last = depth
            if last is not None:
                self._close_to(last)
        if tag in BLOCK:
            depth = self._scopes[-1][0]
            around = self.tag[self._open[depth]]
            if around == "p" or around in HEADS and tag in HEADS:
                self._close_to(depth)
        node = len(self.tag)
        self.tag.append(tag)
        self.attrs.append(attrs)
        self.parent.append(self._open[-1])
        self.events.append(node)
        if not stays:
            self.events.append(~node)
            return
        self._open.append(node)
        if tag in BLOCK:
            self._scopes.append((len(self._open) - 1, {}))
            self._blocks[tag] = self._blocks.get(tag, 0) + 1
            if tag in _STRUCTURE:
                self._structure[_STRUCTURE[tag]].append(len(self._open) - 1)
        else:
            inline = self._scopes[-1][1]
            inline[tag] = inline.get(tag, 0) + 1

    def _end(self, tag: str) -> None:
        if not (self._blocks if tag in BLOCK else self._scopes[-1][1]).get(tag):
            return
        depth = len(self._open) - 1
        while self.tag[self._open[depth]] != tag:
            depth -= 1
        self._close_to(depth)

    def _read(self, page: str) -> None:
        at, n = 0, len(page)
        while at < n:
            start = page.find("<", at)
            start = n if start < 0 else start
            if start > at:
                self.events.append(entities.unescape(page[at:start]))
            if start == n:
                break
            m = TOKEN.match(page, start)
            if m is None:
                loose = LOOSE_TAG.match(page, start)  # a tag with unbalanced quotes, or no tag
                if not loose:
                    self.events.append("<")
                at = loose.end() if loose else start + 1
                continue
            at = m.end()
            if m["cdata"] is not None:
                self.events.append(m["cdata"])
            if m["tag"] is None or m["close"] != ">":
                continue  # a comment or declaration, or a tag cut off
            tag = m["tag"].lower()
            if m["end"]:
                self._end(tag)
            elif tag in RAW:
                end = re.compile(rf"</{tag}[\s/>]", re.I).search(page, at)
                close = page.find(">", end.start()) if end else -1
                at = n if close < 0 else close + 1
            else:
                self._start(tag, m["attrs"], not (tag in VOID or m["attrs"].endswith("/") and tag not in BLOCK))


def _attributes(attrs: str) -> dict[str, str]:
    found: dict[str, str] = {}
    for m in ATTR.finditer(attrs):
        found.setdefault((m[1] or m[5]).lower(), m[2] or m[3] or m[4] or "")
    return found


def speaks_of_furniture(name: str) -> int:
    """Of one class or id: 2 if it names furniture, 1 if it may, else 0."""
    words = [w.lower() for w in WORDS.findall(name)]
    if LAYOUT.intersection(words):
        return 0
    while len(words) > 1 and words[-1] in FRAME:
        words.pop()
    if not words:
        return 0
    head, rest = words[-1], words[:-1]
    if head in PLAIN or any(w in PLAIN for w in rest) and head in MAYBE:
        return 2
    if head in MAYBE:
        if GOOD.intersection(rest):
            return 0
        return 2 if all(w in SITE for w in rest) and head not in ("author", "byline", "meta", "tags") else 1
    return 0


class Tree:
    """Points, values and the choice of elements of a page."""

    def __init__(self, page: Page):
        self.page, n = page, len(page.tag)
        self.block = [t in BLOCK for t in page.tag]
        self.block[ROOT] = True
        self.named = [0] * n
        self.worth = [1.0] * n
        in_article = [False] * n
        self.gone = [False] * n
        for x in range(1, n):
            tag, up = page.tag[x], page.parent[x]
            in_article[x] = in_article[up] or tag in ("article", "main")
            self.gone[x] = self.gone[up] or tag in GONE
            if self.gone[x]:
                continue
            if tag in TAG_WORTH and not (tag == "header" and in_article[x]):
                self.worth[x] = TAG_WORTH[tag]
            if page.attrs[x]:
                found = _attributes(page.attrs[x])
                if "hidden" in found or found.get("aria-hidden") == "true" or UNSEEN.search(found.get("style", "")):
                    self.gone[x] = True
                if found.get("role", "").lower() in ROLES:
                    self.worth[x] = 0.0
                if self.block[x] and tag not in ("main", "body", "html"):
                    names = entities.unescape(f"{found.get('class', '')} {found.get('id', '')}").split()
                    self.named[x] = max(map(speaks_of_furniture, names), default=0)
        self._lines()
        self._totals()

    def _lines(self) -> None:
        """Text between block boundaries: (text, element, characters in links)."""
        page, part, linked = self.page, [], 0
        self.lines: list[tuple[str, int, int]] = []
        self.links = [0] * len(page.tag)
        owner, in_link = ROOT, 0

        def flush():
            nonlocal linked
            text = SPACES.sub(" ", "".join(part)).strip()
            part.clear()
            if text:
                self.lines.append((text, owner, min(linked, len(text))))
            linked = 0

        for e in page.events:
            if isinstance(e, str):
                if not self.gone[top]:
                    part.append(e)
                    linked += len(e) if in_link else 0
                continue
            x = e if e >= 0 else ~e
            top = x if e >= 0 else page.parent[x]
            if self.gone[x]:
                continue
            if self.block[x] or page.tag[x] == "br":
                flush()
                if self.block[x]:
                    owner = x if e >= 0 else page.parent[x]
                    while owner > ROOT and not self.block[owner]:
                        owner = page.parent[owner]
            elif page.tag[x] == "a":
                in_link += 1 if e >= 0 else -1
                self.links[x] += e >= 0

    def _totals(self) -> None:
        page, n = self.page, len(self.page.tag)
        self.chars, self.linked, self.raw, self.count = [0] * n, [0] * n, [0.0] * n, [0] * n
        has_block = [False] * n
        for x in range(n - 1, 0, -1):
            if (self.block[x] or has_block[x]) and not self.gone[x]:
                has_block[page.parent[x]] = True
        self.leaf = [b and not h for b, h in zip(self.block, has_block)]
        self.total = [0.0] * n
        given = [0.0] * n  # by a leaf's paragraphs to its parent
        for text, x, linked in self.lines:
            points = paragraph_points(text)
            self.chars[x] += len(text)
            self.linked[x] += linked
            self.raw[x] += points
            self.count[x] += 1
            points *= 0.5 if page.tag[x] in HEADS else 1
            if self.leaf[x]:
                given[x] += points
            else:
                self.total[x] += points
        for x in range(n - 1, 0, -1):
            up = page.parent[x]
            w = self.worth[x] = self.worth[x] * (1.0, NAMED_MAYBE, NAMED)[self.named[x]]
            self.chars[up] += self.chars[x]
            self.linked[up] += self.linked[x]
            self.links[up] += self.links[x]
            self.raw[up] += w * self.raw[x]
            self.count[up] += self.count[x]
            # an inline element around blocks hands on what it got
            self.total[up] += w * (given[x] if self.leaf[x] else self.total[x] / (2 if self.block[x] else 1))
        self.around = [1.0] * n  # worth of what an element lies in
        for x in range(1, n):
            up = page.parent[x]
            self.around[x] = self.around[up] * self.worth[up]

    def weight(self, x: int) -> float:
        """Total points after the discounts for links, tag and names."""
        if not self.chars[x]:
            return 0.0
        return self.total[x] * (1 - self.linked[x] / self.chars[x]) * self.worth[x] * self.around[x]

    def value(self, x: int, inside: bool) -> float:
        """Mean points of a paragraph in x after the discounts."""
        worth = self.worth[x]
        if self.named[x] == 1:  # a doubtful name counts in full outside, and not at all in the article without links
            worth *= NAMED if not inside else 1.0 if self.links[x] or self.loose else 1 / NAMED_MAYBE
        menu = self.links[x] >= MENU_LINKS and not (self.leaf[x] and self.page.tag[x] in ("p", "td", "th", "li"))
        links = 1 - self.linked[x] / self.chars[x] if menu or not inside else 1.0
        return self.raw[x] / self.count[x] * links * worth

    def best(self) -> int:
        """The main container: the highest weight, the first of equals."""
        top, most = ROOT, 0.0
        for x in range(len(self.page.tag)):
            if self.block[x] and self.chars[x] and not self.leaf[x]:
                w = self.weight(x)
                if w > most:
                    top, most = x, w
        return top

    def kept_lines(self) -> list[str]:
        page, n, main = self.page, len(self.page.tag), self.best()
        path, x = {ROOT}, main
        while x > ROOT:
            path.add(x)
            x = page.parent[x]
        self.loose = page.tag[main] in ("#root", "html", "body")  # nothing marks the article off
        limit = max(1.0, SHARE * self.value(main, True)) if self.count[main] else 1.0
        inside, drop = [False] * n, [False] * n
        inside[main] = True
        for x in range(1, n):
            up = page.parent[x]
            inside[x] |= inside[up]
            drop[x] = drop[up]
            if drop[x] or x in path or not self.block[x] or not self.count[x]:
                continue
            if page.tag[x] in HEADS and up in path and not self.named[x]:
                continue  # a title over the container or one of its parts
            drop[x] = self.value(x, inside[x]) < (1.0 if inside[x] else limit)
        return [text for text, x, _ in self.lines if not drop[x]]


def paragraph_points(text: str) -> float:
    return 1 + text.count(",") + text.count("，") + text.count("、") + min(len(text) / 100, 3) + (0.5 if SENTENCE.search(text, max(0, len(text) - 8)) else 0)


def main_text(page: str | None) -> str:
    return "\n".join(Tree(Page(page)).kept_lines()) if page else ""


def extract(df: DataFrame, keep: tuple[str, ...] = ("page_id", "url"), html: str = "html") -> DataFrame:
    """The kept columns, text and n_chars (code points) of every page."""
    n = len(keep)

    def run(batches):
        for b in portions(batches):
            texts = [main_text(p) for p in b.column(n).to_pylist()]
            yield pa.RecordBatch.from_arrays([*b.columns[:n], pa.array(texts, pa.string()), pa.array(list(map(len, texts)), pa.int64())], names=[*keep, "text", "n_chars"])

    src = df.select(*keep, html)
    schema = ", ".join([*(f"`{c}` {t}" for c, t in src.dtypes[:n]), "text string, n_chars long"])
    return src.mapInArrow(run, schema)
