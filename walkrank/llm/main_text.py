"""Main text of web pages by scoring the element tree.

Each paragraph earns points for its length and its commas and passes them to its LEVELS nearest ancestors: all to the
parent, half to the next, less to those above. An element's points, with a bonus for its kind and names, are discounted by the share
of link text in it. The best element is kept, with those siblings that score well too or are paragraphs of prose.

Scripts, forms, menus, headers, footers, sidebars, notices, adverts and comments are left out before, by element, role
and names in class and id. If nothing is left the names don't count. End tags may be missing as HTML allows.

Tags are found by a scanner of linear time, also where quotes, brackets or elements are never closed.

The text has one line for each block, in page order. Character references are decoded and white space becomes one
space. A null or empty page, or one without text, has the empty text. Rows are independent: repeated pages give
repeated results, other columns are left out, an empty table gives an empty table.
"""

from __future__ import annotations

import html
import re
from bisect import bisect_left, bisect_right

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

# Kinds of elements.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title noscript iframe template xmp noframes".split())
NEVER = frozenset("head nav aside footer header form script style noscript template svg math iframe button select textarea input object canvas dialog menu audio video map datalist label fieldset".split())
BLOCK = frozenset("address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
PARAGRAPH = frozenset("p pre blockquote li dd dt td th h1 h2 h3 h4 h5 h6 figcaption caption".split())
#: A start tag that ends open elements, up to the nearest of those that hold them.
ENDS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"}), "tbody": ({"tr", "td", "th", "tbody", "thead"}, {"table"}), "tfoot": ({"tr", "td", "th", "tbody", "thead"}, {"table"})}
BONUS = {"article": 25, "main": 20, "section": 3, "div": 5, "pre": 3, "td": 3, "blockquote": 3, "ul": -3, "ol": -3, "dl": -3, "th": -5, "h1": -5, "h2": -5, "h3": -5, "body": 0}
BAD = frozenset("ad ads adv advert advertisement advertising adsense banner breadcrumb breadcrumbs comment comments cookie cookies consent disqus footer gdpr header hidden menu masthead modal nav navbar navigation newsletter notice notification notices overlay pagination pager popup popular promo promotion promoted recommended related remark respond reply replies rss share sharing shoutbox sidebar sidebars signup skip social sponsor sponsored subscribe subscription tags toolbar topbar widget widgets".split())
GOOD = frozenset("article articlebody body content entry main page post story text blog hentry".split())
BAD_ROLE = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form".split())
KEPT_ALWAYS = frozenset("html body article main".split())

#: From the first letter of a tag's name: the name, and from behind it the attributes up to the closing bracket, which is
#: the first outside quotes.
TAG_NAME = re.compile(r"[a-zA-Z][^\s/>]*+")
TAG_REST = re.compile(r"""[^>"']*+(?:"[^"]*+"[^>"']*+|'[^']*+'[^>"']*+)*+>""")
STOPS = re.compile(r"""[>"']""")
ATTRIBUTE = re.compile(r"""(?<![a-zA-Z-])([a-zA-Z-]++)\s*+=\s*+(?:"([^"]*)"|'([^']*)'|([^\s>"']+))""")
NAME = re.compile(r"[A-Z]?[a-z]+|[A-Z]+")
#: Ancestors that a paragraph passes points to.
LEVELS = 12


class Tags:
    """The tags of a page, one after another, in time linear in its length whatever it holds.

    A quote that is never closed makes the search for a tag's end run to the end of the page. After the first time all
    quotes and brackets are gone through once, backwards, which tells for each where a tag open there ends."""

    def __init__(self, source: str):
        self.source, self.open_from = source, 0
        self.stops: list[int] | None = None
        self.ends: list[int] = []

    def closing(self, at: int) -> int:
        """Behind the bracket that ends a tag of which `at` is a place outside quotes; -1 if none does."""
        if self.stops is None:
            m = TAG_REST.match(self.source, at)
            if m:
                return m.end()
            found = [(m.start(), m[0]) for m in STOPS.finditer(self.source, at)]
            self.stops = [k for k, _ in found]
            self.ends = [-1] * (len(found) + 1)
            again = {'"': -1, "'": -1}
            for i in range(len(found) - 1, -1, -1):
                k, c = found[i]
                if c == ">":
                    self.ends[i] = k + 1
                else:
                    self.ends[i] = self.ends[again[c] + 1] if again[c] >= 0 else -1
                    again[c] = i
        return self.ends[bisect_left(self.stops, at)]

    def __iter__(self):
        """Where each tag starts, its end, '/' for an end tag, its name (empty for comments and the like), its attributes."""
        source, at, last = self.source, 0, self.source.rfind(">")
        while (at := source.find("<", at)) >= 0:
            after = source[at + 1 : at + 2]
            if after == "!" and source.startswith("<!--", at):
                end = source.find("-->", at + 4)
                end = end + 3 if end >= 0 else len(source)
                yield at, end, "", "", ""
                at = end
                continue
            if at > last:  # no tag can end any more; only a comment needs no bracket
                if (at := source.find("<!--", at)) < 0:
                    return
                continue
            slash = after == "/"
            m = TAG_NAME.match(source, at + 1 + slash)
            end = self.closing(m.end()) if m else -1
            if end >= 0:
                yield at, end, "/" if slash else "", m[0].lower(), source[m.end() : end - 1]
            elif after and after in "!?/" and (end := source.find(">", at) + 1):
                yield at, end, "", "", ""
            else:
                at += 1
                continue
            at = end if self.open_from <= end else self.open_from
            self.open_from = 0


class Page:
    """Elements in page order: parent, tag, end of the subtree; texts with their element, block and whether in a link."""

    def __init__(self, source: str, by_name: bool = True):
        self.parent, self.tag, self.end, self.weight = [-1], ["#"], [0], [0]
        self.tops: dict[int, int] = {}
        self.texts: list[tuple[int, int, str, bool]] = []
        out, links, block = [False], [False], 0
        stack, at = [0], 0
        #: depths in the stack by tag, and of all blocks
        depths: dict[str, list[int]] = {}
        blocks: list[int] = []

        def close(depth: int) -> None:
            nonlocal block
            while len(stack) > depth:
                k = stack.pop()
                self.end[k] = len(self.tag)
                depths[self.tag[k]].pop()
                if self.tag[k] in BLOCK:
                    block += 1
                    blocks.pop()

        def text(stop: int) -> None:
            if stop > at and not out[stack[-1]]:
                self.texts.append((stack[-1], block, source[at:stop], links[stack[-1]]))

        tags = Tags(source)
        for start, end, slash, name, attributes in tags:
            text(start)
            at = end
            if not name:
                continue
            if slash:
                if depths.get(name):
                    close(depths[name][-1])
                elif name == "p":
                    block += 1
                continue
            if name in BLOCK and blocks and self.tag[stack[blocks[-1]]] == "p":
                close(blocks[-1])
            if name in ENDS:
                ends, within = ENDS[name]
                lowest = max((depths[x][-1] for x in within if depths.get(x)), default=0)
                found = [depths[x][k] for x in ends if depths.get(x) for k in [bisect_right(depths[x], lowest)] if k < len(depths[x])]
                if found:
                    close(min(found))
            block += name in BLOCK
            if name == "br":
                if not out[stack[-1]]:
                    self.texts.append((stack[-1], block, " ", False))
                continue
            if name in VOID:
                continue
            up, k = stack[-1], len(self.tag)
            weight, bad = self.named(name, attributes) if attributes else (0, False)
            self.parent.append(up)
            self.tag.append(name)
            self.end.append(k + 1)
            self.weight.append(weight)
            out.append(out[up] or name in NEVER or (bad and by_name and name not in KEPT_ALWAYS))
            links.append(links[up] or name == "a")
            if attributes.endswith("/") and name not in BLOCK:
                continue
            if name in RAW:
                closing = re.compile(rf"</{name}\b", re.I).search(source, at)
                at = tags.open_from = closing.start() if closing else len(source)
            depths.setdefault(name, []).append(len(stack))
            if name in BLOCK:
                blocks.append(len(stack))
            stack.append(k)
        text(len(source))
        close(1)
        self.end[0] = len(self.tag)

    @staticmethod
    def named(tag: str, attributes: str) -> tuple[int, bool]:
        """Weight by the names of an element, and whether it is to be left out."""
        weight, bad = 0, bool(re.search(r"(?:^|\s)hidden(?:\s|=|/|$)", re.sub(r"\"[^\"]*\"|'[^']*'", '""', attributes)))
        for name, *values in ATTRIBUTE.findall(attributes):
            value = next((v for v in values if v), "")
            name = name.lower()
            if name in ("class", "id"):
                words = {w.lower() for w in NAME.findall(value)}
                if words & GOOD:
                    weight += 25
                if words & BAD:
                    weight -= 25
                    bad |= not words & {"has", "with", "without", "no"}
            elif name == "role":
                bad |= value.lower() in BAD_ROLE
            elif name == "aria-hidden":
                bad |= value.lower() == "true"
            elif name == "style":
                bad |= bool(re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value, re.I))
        return weight, bad

    def blocks(self, spans: list[tuple[int, int]]) -> list[str]:
        """The blocks of text inside some ranges of elements, which are in order and apart."""
        out, now, parts, starts = [], None, [], [a for a, _ in spans]
        for node, block, text, _ in self.texts:
            k = bisect_right(starts, node) - 1
            if k < 0 or node >= spans[k][1]:
                continue
            if block != now:
                out.append("".join(parts))
                now, parts = block, []
            parts.append(text)
        out.append("".join(parts))
        return [x for x in (" ".join(html.unescape(x).split()) for x in out) if x]

    def main(self) -> str:
        points, chars, linked = {}, [0] * len(self.tag), [0] * len(self.tag)
        paragraphs: dict[int, list] = {}
        for node, block, text, link in self.texts:
            n = len(text.strip())
            if n:
                found = paragraphs.setdefault(block, [node, 0, 0, 0])
                found[1] += n
                found[2] += text.count(",") + text.count("，") + text.count("、")
                found[3] += n if link else 0
        for node, n, commas, in_links in paragraphs.values():
            if node:
                chars[node] += n
                linked[node] += in_links
            owner = node
            while owner and self.tag[owner] not in BLOCK:
                owner = self.inline(owner)
            if self.tag[owner] in PARAGRAPH:
                owner = self.parent[owner]
            value = (1 + commas + min(n / 100, 3.0)) * (1 - in_links / n)
            for level in range(LEVELS):
                if owner < 0 or (level and not owner):
                    break
                points[owner] = points.get(owner, 0) + value / (1 if not level else 2 if level == 1 else 3 * level)
                owner = self.parent[owner]
        for k in range(len(self.tag) - 1, 0, -1):  # children come behind their parents
            if self.parent[k]:
                chars[self.parent[k]] += chars[k]
                linked[self.parent[k]] += linked[k]
        if not points:
            return ""
        score = {k: (v + BONUS.get(self.tag[k], 0) + self.weight[k] * (v > 0)) * (1 - linked[k] / max(chars[k], 1)) for k, v in points.items()}
        best = max(score, key=lambda k: (score[k], -k))
        spans = [(best, self.end[best])]
        if best:
            least = max(10.0, 0.2 * score[best])
            for k in range(1, len(self.tag)):
                if k == best or self.parent[k] != self.parent[best] or not chars[k]:
                    continue
                density = linked[k] / chars[k]
                prose = self.tag[k] in PARAGRAPH and (density < 0.25 if chars[k] > 80 else not density)
                if score.get(k, 0) >= least or prose:
                    spans.append((k, self.end[k]))
        return "\n".join(self.blocks(sorted(spans)))

    def inline(self, node: int) -> int:
        """The parent of an inline element; long chains of them are gone up once."""
        up = self.parent[node]
        if up and self.tag[up] not in BLOCK:
            top = self.tops.get(up)
            if top is None:
                path, top = [], up
                while top and self.tag[top] not in BLOCK and top not in self.tops:
                    path.append(top)
                    top = self.parent[top]
                top = self.tops.get(top, top)
                for k in path:
                    self.tops[k] = top
            return top
        return up


def main_text(source: str | None) -> str:
    if not source:
        return ""
    return Page(source).main() or Page(source, by_name=False).main()


def extracted(pages: DataFrame) -> DataFrame:
    """page_id, url, text and n_chars of each row of pages (page_id, url, html)."""

    def setup():
        def one(key, url, source):
            text = main_text(source)
            return key, url, text, len(text)

        return one

    return common.map_rows(pages.select("page_id", "url", "html"), setup, "page_id long, url string, text string, n_chars long")


def op3_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The main text of every page."""
    return extracted(common.documents(spark, sf_dir, "pages"))


QUERIES = {"op3_main_text": op3_main_text}
ORACLES: dict[str, str] = {}
