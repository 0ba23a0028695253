"""Main text of web pages by tree scoring.

A page is cut into blocks of text under a tree of its block elements (unclosed paragraphs, list items and cells are closed
as browsers do). Elements that are never main text by their tag, role, class or id are left out of the tree's text. A class or id
counts by its main word, and not if content is named beside it, or if the elements of that word hold most of the page's
unlinked prose; a form counts like a name, as some pages are one form, and its labels and buttons never count. A page that
names leave without text is read again without them. Every block passes points to the elements around it: one, one for each comma and one for each hundred characters up to three,
whole to its container, half to the next, less further up. A container's points are discounted by the share of its
characters that are links; articles and elements named as content start with a bonus. The best container is kept, or the whole
article (else the main element, else the containers named as content) that it lies in, with those of its siblings that have a
good part of its points or are paragraphs of prose, outside articles also containers of such paragraphs; lists of links inside
it are not.

Null pages are empty; a page without text gives an empty string. Pages of any length are read whole, each in its row. Repeated rows give repeated results, an empty table none.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from html import unescape

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from cellfleet.llm.common import table

TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*(?:>|\Z)"
    r"|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)(?:>|\Z)"
    r"|<(/?)([a-zA-Z][^\s/>]*+)([^>]*+)(?:>|\Z)",
    re.S,
)
ATTRIBUTE = re.compile(r"(class|id|role|itemprop|hidden|aria-hidden|style)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?(?=\s|/|$)", re.I)
PARTS = re.compile(r"[A-Z]?[a-z]+|[A-Z]+(?![a-z])|\d+")

# HTML's element groups.
RAW = frozenset("script style title textarea noscript iframe template svg math object select noembed noframes xmp".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCK = frozenset(
    "address article aside blockquote body button caption center dd details dialog dir div dl dt fieldset figcaption figure footer form"
    " h1 h2 h3 h4 h5 h6 head header hgroup hr html label legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split()
)
HEADINGS = frozenset("h1 h2 h3 h4 h5 h6".split())
PARAGRAPHS = HEADINGS | frozenset("p pre td th li dd dt blockquote figcaption caption summary".split())
#: A start tag of the first closes an open one of the second, up to one of the third.
CLOSES = {
    "li": ({"li"}, {"ul", "ol", "menu", "dir"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr"}, {"table"}),
    "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, set()),
    "tbody": ({"thead", "tbody", "tfoot"}, {"table"}), "tfoot": ({"thead", "tbody", "tfoot"}, {"table"}),
}
LEFT_OUT = frozenset("nav aside footer button dialog menu fieldset label optgroup option head search".split())
ROLES = frozenset("navigation banner contentinfo complementary search form dialog alert alertdialog menu menubar toolbar".split())
COMMENTS = frozenset("comment comments commentlist disqus reply replies respond".split())
OTHER = COMMENTS | frozenset(
    "ad ads adv advert adverts advertisement advertising adsense sponsor sponsored promo promotion banner sidebar menu nav navbar navigation breadcrumb breadcrumbs"
    " share sharing social cookie cookies consent gdpr notice notices notification alert popup modal overlay newsletter subscribe signup login footer masthead topbar toolbar"
    " related recommended recommendations widget pagination pager skip".split()
)
CONTENT = frozenset("content article post entry story main text articlebody".split())
#: Words before which a name says where or how, and after which it tells of a state.
PLACES = frozenset(
    "left right top bottom inner outer wrapper wrap container holder box area block section list item items link links button buttons bar slot unit group row col column"
    " panel body zone space primary secondary posts post articles article stories story content main text title heading icon icons image img form fixed info law this us".split()
)
STATES = frozenset("has no with without is not non hide show open closed enabled disabled on off".split())
#: Shares of the unlinked prose above which a name doesn't leave an element out: without and with prose in content elements.
MOST, NEARLY_ALL, PROSE = 0.5, 0.8, 80
BONUS, NAMED = 25.0, 10.0
HEADER = "header"


def _word(name: str) -> str:
    """What a class or id names: its last word that isn't a place; none for a state."""
    parts = [x for x in (y.lower() for y in PARTS.findall(name)) if len(x) > 1 and not x.isdigit()]
    if not parts or len(parts) > 1 and (parts[0] in STATES or parts[-1] in STATES):
        return ""
    return next((x for x in reversed(parts) if x not in PLACES), parts[-1])


def _kind(tag: str, attributes: str, by_name: bool = True) -> tuple[bool, bool, bool, float, str]:
    """(left out, for good: no article inside counts, a header, bonus, the words by which alone it is left out or a header); without
    names, if not ``by_name``."""
    out = tag in LEFT_OUT
    good, header, bonus, named = out, tag == HEADER, BONUS if tag in ("article", "main") else 0.0, ""
    if tag == "form" and by_name:
        out, named = True, "form"
    if attributes and not attributes.isspace():
        names: set[str] = set()
        words: set[str] = set()
        for name, a, b, c in ATTRIBUTE.findall(attributes):
            name, value = name.lower(), a or b or c
            if name in ("class", "id"):
                names |= {x.lower() for x in PARTS.findall(value)} | set(value.lower().split())
                words |= {_word(x) for x in value.split()} | set(value.lower().split())
            elif name == "role":
                roles = set(value.lower().split())
                out, named, bonus = out or bool(roles & ROLES), "" if roles & ROLES else named, BONUS if roles & {"main", "article"} else bonus
            elif name == "itemprop":
                bonus = BONUS if value.lower() == "articlebody" else bonus
            elif name == "style":
                hides = bool(re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I))
                out, named = out or hides, "" if hides else named
            elif name == "hidden" or value.lower() == "true":
                out, named = True, ""
        if names & CONTENT:
            bonus = max(bonus, NAMED)
        if by_name and tag not in ("html", "body"):
            if words & COMMENTS:
                out, good, named = True, True, ""
            elif not words & CONTENT and tag not in ("article", "main"):
                if (found := words & OTHER) and (named or not out):
                    out, named = True, " ".join(sorted(found | set(named.split())))
                if HEADER in words and tag not in HEADINGS:
                    named, header = named or (HEADER if not header and not out else ""), True
    return out, good, header, bonus, named


class Page:
    """The blocks of a page and the tree of elements above them."""

    def __init__(self, html: str, by_name: bool = True, spared: frozenset[int] = frozenset()):
        self.by_name, self.spared, self.at = by_name, spared, 0  # where tags stand whose names don't count; where the open tag ends
        # outermost element that names leave out, its words, where tags end, and prose by those words
        self.named, self.words, self.start, self.prose = [-1], {}, [0], {}
        self.tag, self.parent, self.bonus = [""], [-1], [0.0]
        self.out, self.good, self.header = [False], [False], [False]
        self.blocks: list[tuple[int, str, int]] = []  # element, text, characters in links
        self.stack, self.links, self.text, self.linked = [0], 0, [], 0
        self.held: dict[int, tuple[list[str], int]] = {}  # text before an inline element that is left out
        self._read(html)

    def _emit(self, at: int, text: list[str], linked: int) -> None:
        whole = " ".join("".join(text).split())
        if self.named[at] >= 0 and len(whole) - linked > PROSE and linked < 0.25 * len(whole):
            words = self.words[self.named[at]]
            self.prose[words] = self.prose.get(words, 0) + len(whole) - linked
        if whole and not self.out[at] and not (self.header[at] and self.tag[at] not in HEADINGS):
            self.blocks.append((at, whole, min(linked, len(whole))))

    def _flush(self) -> None:
        if self.text:
            self._emit(self.stack[-1], self.text, self.linked)
            self.text, self.linked = [], 0

    def _pop(self, depth: int) -> None:
        for i in reversed(self.stack[depth:]):
            if i in self.held:  # never closed: what stood before it is a block
                self._emit(self.parent[i], *self.held.pop(i))
        del self.stack[depth:]

    def _open(self, tag: str, attributes: str, kind: tuple) -> None:
        at = self.stack[-1]
        out, good, header, bonus, named = kind
        if self.out[at] and not (tag in ("article", "main") and not out and not self.good[at]):
            out, good, named = True, self.good[at] or good, named if named or out else "above" if self.named[at] >= 0 else ""
        elif header and not (self._inside_article() and not out):
            out, header = out or not self._inside_article(), header
        hidden = out or header and tag not in HEADINGS
        # below an element that names leave out, what is left out for other reasons counts no prose
        outermost = self.named[at] if named and self.named[at] >= 0 else len(self.tag) if named and named != "above" and hidden else -1
        if outermost == len(self.tag):
            self.words[outermost] = named
        self.named.append(outermost)
        self.start.append(self.at)
        self.tag.append(tag)
        self.parent.append(at)
        self.out.append(out)
        self.good.append(good)
        self.header.append(header or (self.header[at] and tag not in ("article", "main")))
        self.bonus.append(0.0 if out else bonus)
        self.stack.append(len(self.tag) - 1)

    def _kind(self, tag: str, attributes: str) -> tuple:
        return _kind(tag, attributes, self.by_name and self.at not in self.spared)

    def overruled(self) -> frozenset[int]:
        """Where the tags end of the elements that some words leave out though most of the page's unlinked prose is in them."""
        if not self.prose:
            return frozenset()
        kept = [(at, len(text) - inside) for at, text, inside in self.blocks if len(text) - inside > PROSE and inside < 0.25 * len(text)]
        content = False
        for i, _ in kept:
            while i > 0 and not content:
                content, i = self.bonus[i] > 0, self.parent[i]
        words = max(sorted(self.prose), key=self.prose.__getitem__)
        large = self.prose[words] > (NEARLY_ALL if content else MOST) * (sum(self.prose.values()) + sum(x for _, x in kept))
        return frozenset(self.start[i] for i, w in self.words.items() if w == words) if large else frozenset()

    def _inside_article(self) -> bool:
        return any(self.tag[i] in ("article", "main") for i in self.stack)

    def _close(self, tags: set[str], up_to: set[str]) -> None:
        for depth in range(len(self.stack) - 1, 0, -1):
            t = self.tag[self.stack[depth]]
            if t in tags:
                self._pop(depth)
                return
            if t in up_to:
                return

    def _read(self, html: str) -> None:
        at, n, search = 0, len(html), TOKEN.search
        lower = None
        while at < n:
            m = search(html, at)
            end = m.start() if m else n
            if end > at:
                part = html[at:end]
                if "&" in part:
                    part = unescape(part)
                self.text.append(part)
                if self.links:
                    self.linked += len(part.strip())
            if not m:
                break
            at = self.at = m.end()
            tag = m[2] or m[5]
            if not tag:
                continue
            tag, closing, attributes = tag.lower(), m[1] or m[4], (m[3] if m[2] else m[6]) or ""
            if closing:
                if tag == "a":
                    self.links = max(0, self.links - 1)
                elif self.stack[-1] in self.held and self.tag[self.stack[-1]] == tag:
                    self.text, self.linked = self.held.pop(self.stack.pop())
                elif tag in BLOCK:
                    self._flush()
                    self._close({tag}, {"td", "th"} if tag not in ("table", "tr", "tbody", "thead", "tfoot", "td", "th", "body", "html") else set())
            elif tag in RAW:
                if tag not in ("svg", "math", "title", "object") or not attributes.rstrip().endswith("/"):
                    lower = lower if lower is not None else html.lower() if len(html.lower()) == n else html
                    shut = lower.find(f"</{tag}", at)
                    at = n if shut < 0 else shut
                self.text.append(" ")
            elif tag == "br":
                self.text.append(" ")
            elif tag in VOID:
                if tag == "hr":
                    self._flush()
            elif tag == "a":
                self.links += 1
            elif tag in BLOCK:
                self._flush()
                self.links = 0
                self._close({"p"}, BLOCK - {"p"})
                if tag in HEADINGS:
                    self._close(HEADINGS, BLOCK - HEADINGS)
                if tag in CLOSES:
                    self._close(*CLOSES[tag])
                self._open(tag, attributes, self._kind(tag, attributes))
            elif attributes and (kind := self._kind(tag, attributes))[0]:
                before = (self.text, self.linked)
                self._open(tag, attributes, kind)
                self.held[self.stack[-1]] = before
                self.text, self.linked = [], 0
        self._flush()
        self._pop(1)

    def _whole(self, best: int) -> int:
        """The outermost article around ``best``, else its main element, else the last of the content containers right above it."""
        above = [best]
        while above[-1] > 0:
            above.append(self.parent[above[-1]])
        for tag in ("article", "main"):
            if found := [i for i in above if self.tag[i] == tag]:
                return found[-1]
        for i in above[1:]:
            if not self.bonus[i] or self.tag[i] in ("html", "body"):
                break
            best = i
        return best

    def scores(self) -> tuple[list[float], list[int], list[int], list[int]]:
        """(score, characters, characters in links, blocks with links) of each element, all that is below it included."""
        n = len(self.tag)
        points, chars, linked, anchors = self.bonus[:], [0] * n, [0] * n, [0] * n
        for at, text, inside in self.blocks:
            size = len(text)
            i = at
            while i >= 0:
                chars[i] += size
                linked[i] += inside
                anchors[i] += inside > 0
                i = self.parent[i]
            if self.tag[at] in HEADINGS:
                continue
            worth = (1 + text.count(",") + text.count("，") + text.count("、") + min(size / 100, 3.0)) * (1 - inside / size)
            i, level = (self.parent[at] if self.tag[at] in PARAGRAPHS else at), 0
            while i > 0:
                points[i] += worth / (1 if level == 0 else 2 if level == 1 else 3 * level)
                i, level = self.parent[i], level + 1
        return [p * (1 - linked[i] / chars[i]) if chars[i] else 0.0 for i, p in enumerate(points)], chars, linked, anchors

    def main(self) -> str:
        if not self.blocks:
            return ""
        n = len(self.tag)
        score, chars, linked, anchors = self.scores()
        bare = [True] * n  # holds headings only
        for at, _, inside in self.blocks:
            if self.tag[at] not in HEADINGS or inside:
                i = at
                while i >= 0 and bare[i]:
                    bare[i], i = False, self.parent[i]
        best = max(range(n), key=lambda i: (score[i] if self.tag[i] not in PARAGRAPHS else 0.0, i == 0))
        most = score[best]
        best = self._whole(best)
        framed = self.tag[best] in ("article", "main")
        prose_in = [False] * n  # holds a paragraph of unlinked prose
        for at, text, inside in self.blocks:
            if len(text) > 80 and inside < 0.25 * len(text) and self.tag[at] not in HEADINGS:
                i = at
                while i >= 0 and not prose_in[i]:
                    prose_in[i], i = True, self.parent[i]
        kept = {best}
        if best > 0 and (above := self.parent[best]) >= 0:
            for i in range(1, n):
                if self.parent[i] == above and chars[i] and i != best:
                    density = linked[i] / chars[i]
                    prose = self.tag[i] in PARAGRAPHS and density < 0.25 and (chars[i] > 80 or self.tag[i] in HEADINGS)
                    part = score[i] >= max(10.0, 0.2 * max(most, score[best])) or not framed and prose_in[i] and density < 0.25
                    if prose or bare[i] or self.tag[i] not in PARAGRAPHS and part:
                        kept.add(i)
        lists = {i for i in range(1, n) if self.tag[i] in ("ul", "ol", "dl", "div", "section", "table") and i not in kept and anchors[i] > 1 and linked[i] > 0.7 * chars[i]}
        inside = [False] * n
        for i in range(n):  # parents come first
            up = self.parent[i]
            inside[i] = i in kept or (up >= 0 and inside[up] and i not in lists)
        return "\n".join(text for at, text, _ in self.blocks if inside[at])


def main_text(html: str | None) -> str:
    if not html:
        return ""
    page = Page(html)
    spared: frozenset[int] = frozenset()
    while more := page.overruled() - spared:
        spared |= more
        page = Page(html, True, spared)
    return page.main() or Page(html, False).main()


def extract(pages: DataFrame, html: str = "html", keep: tuple[str, ...] = ("page_id", "url")) -> DataFrame:
    """The ``keep`` columns of each page, its main text and that text's length in code points."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = [main_text(x.as_py()) for x in b.column(len(keep))]
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(found, pa.string()), pa.array([len(x) for x in found], pa.int64())], names=[*keep, "text", "n_chars"])

    kinds = ", ".join(f"`{c}` {pages.schema[c].dataType.simpleString()}" for c in keep)
    return pages.select(*keep, html).mapInArrow(run, f"{kinds}, text string, n_chars bigint")


def op4_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract(table(spark, sf_dir, "pages"))
