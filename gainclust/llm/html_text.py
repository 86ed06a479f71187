"""Main text of web pages by composite text density.

The tag soup becomes a tree; elements that never hold article text (scripts, menus and so on) are cut off by tag.
Words of class, id or role, forms and page headers only make an element suspect: it is cut unless it holds the page's
principal article or most of its text; if little would be left, nothing suspect is cut. Each node's density is its characters per tag, corrected by how much of them are links;
a node's density sum adds the densities of its children. The node of the greatest sum is the main content; the least
density on its path to the body is the threshold that other top-level parts must reach to count as content too.

Cases: null or empty html, or no text left - empty text; broken markup - tags close implicitly, stray ends are
skipped, an open comment or script runs to the end; repeated rows - each answered; null ids are kept; empty table -
no rows; other columns are not read; nothing is cut for length.
"""

from __future__ import annotations

import html
import math
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gainclust.llm.common import trimmed

#: Elements by HTML role (fixed values).
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style textarea title xmp noembed noframes iframe".split())
NEVER = frozenset("script style textarea title head noscript template iframe object svg canvas nav footer aside button select dialog menu audio video map xmp noembed noframes".split())
BLOCK = frozenset(
    "address article aside blockquote body br caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 "
    "header hr html legend li main menu nav ol option p pre section summary table tbody td tfoot th thead tr ul".split()
)
CLOSES_P = BLOCK - {"br", "body", "html", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "option"}
#: A start tag closes an open one of these, up to the fence.
SIBLINGS = {"li": ({"li"}, {"ul", "ol", "menu"}), "dt": ({"dt", "dd"}, {"dl"}), "dd": ({"dt", "dd"}, {"dl"}), "tr": ({"tr", "td", "th"}, {"table"}), "td": ({"td", "th"}, {"tr", "table"}), "th": ({"td", "th"}, {"tr", "table"}), "option": ({"option"}, {"select"})}
#: An open p is not closed from inside these.
P_FENCE = ("td", "th", "table", "button", "object")
#: Words of class, id and role that mark what is not article text.
NOISE = frozenset(
    "ad ads advert adverts advertisement advertising sponsor sponsored promo banner cookie cookies consent gdpr notice notices popup modal overlay newsletter "
    "subscribe subscription sidebar aside related recommended share sharing social comment comments disqus reply replies nav navbar navigation menu "
    "breadcrumb breadcrumbs footer masthead pagination pager widget login signup toolbar skip contentinfo complementary search".split()
)
#: A name that begins so tells how a page is laid out, not what an element holds (with-sidebar, has-comments).
STATES = frozenset({"no", "not", "non", "with", "without", "has", "have"})
#: A suspect element with more of the page's text than this is the page itself; with less left than LEFT, nothing is cut.
MOST, LEFT = 0.75, 0.25
#: Beside the content, these go with it by density alone; others only with this share of its density sum.
TEXT, SHARE = frozenset("h1 h2 h3 h4 h5 h6 p blockquote pre".split()), 0.1
HEADERS = frozenset({"header", "masthead", "banner"})
SAFE = frozenset({"html", "body", "article", "main"})

_NAME = re.compile(r"/?([a-zA-Z][^\s/>]*)")
_PLAIN = re.compile(r"[^>\"']*")
_MARK = re.compile(r"""(?:^|\s)(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]+))?""", re.I | re.S)
_WORD = re.compile(r"[a-z]+")


def _noise(tag: str, attrs: str, in_article: bool) -> str:
    """"never" for what is cut while parsing, "suspect" for what is judged with the whole page, else empty."""
    if tag in NEVER:
        return "never"
    found = "suspect" if tag == "form" or (tag == "header" and not in_article) else ""
    if not attrs or tag in SAFE:
        return found
    for name, value in _MARK.findall(attrs):
        name, value = name.lower(), value.strip("\"'").lower()
        if name == "hidden" or (name == "aria-hidden" and value == "true"):
            return "never"
        if name == "style":
            if "display:none" in value.replace(" ", ""):
                return "never"
            continue
        for token in value.split():
            words = _WORD.findall(token)
            if words and words[0] not in STATES and (NOISE.intersection(words) or (HEADERS.intersection(words) and not in_article)):
                found = "suspect"
    return found


def tags(source: str) -> Iterator[tuple[int, int, bool, str, str]]:
    """(begin, end, is end tag, name, attributes) of every tag, comments and declarations with an empty name, in one pass.

    The caller may send a place from which to go on. An unclosed comment runs to the end; a tag without its closing
    bracket is text; a quotation mark that is never closed is a plain character.
    """
    at, n = 0, len(source)
    last = {c: source.rfind(c) for c in ">\"'"}
    while True:
        begin = source.find("<", at)
        if begin < 0 or begin > last[">"] and not source.startswith("<!--", begin):
            return
        at = begin + 1
        if source.startswith("!--", at):
            end = source.find("-->", at + 3)
            end = n if end < 0 else end + 3
            found = (begin, end, False, "", "")
        elif source[at] in "!?":
            end = source.find(">", at) + 1
            found = (begin, end, False, "", "")
        elif m := _NAME.match(source, at):
            end = m.end()
            while True:
                end = _PLAIN.match(source, end).end()
                if end >= n or source[end] == ">":
                    break
                # of a quotation mark on, the matching one if there is any
                end = source.find(source[end], end + 1) + 1 if last[source[end]] > end else end + 1
            if end >= n:
                return  # the rest is text
            end += 1
            found = (begin, end, source[at] == "/", m[1], source[m.end() : end - 1])
        else:
            continue
        resume = yield found
        at = end
        if resume is not None:
            at = resume
            yield found  # what send() returns


class Open:
    """The open elements, with the places of each tag, so that finding one does not look through all."""

    def __init__(self) -> None:
        self.items: list[tuple[int, str]] = [(0, "body")]  # noise is on the stack as node -1
        self.places: dict[str, list[int]] = {}

    def push(self, node: int, tag: str) -> None:
        self.places.setdefault(tag, []).append(len(self.items))
        self.items.append((node, tag))

    def pop(self) -> tuple[int, str]:
        node, tag = self.items.pop()
        self.places[tag].pop()
        return node, tag

    def last(self, names) -> int:
        """Place of the innermost open element of these tags; 0 if there is none."""
        return max((self.places[t][-1] for t in names if self.places.get(t)), default=0)


class Page:
    """Nodes in page order; a node's parent precedes it. What never holds text is left out while parsing, suspects after it."""

    def __init__(self, source: str):
        self.tag, self.parent, self.link, self.text = ["body"], [-1], [False], [[]]  # text: (place, string) of a node's own text
        self.suspect = [False]
        self.place = 0
        stack = Open()
        muted, at = 0, 0
        article = 0

        def close(until: int) -> None:
            nonlocal muted, article
            while len(stack.items) > until:
                node, tag = stack.pop()
                muted -= node < 0
                article -= tag == "article"
                if tag in BLOCK:
                    self._say(stack, muted, None)

        found = tags(source)
        for begin, end, closing, tag, attrs in found:
            self._say(stack, muted, source[at:begin])
            at = end
            tag = tag.lower()
            if tag in ("", "html", "body"):
                continue
            if closing:
                if place := stack.last((tag,)):
                    close(place)
                continue
            if tag in CLOSES_P and (place := stack.last(("p",))) > stack.last(P_FENCE):
                close(place)
            if tag in SIBLINGS:
                shut, fence = SIBLINGS[tag]
                if (place := stack.last(shut)) > stack.last(fence):
                    close(place)
            if tag in BLOCK:
                self._say(stack, muted, None)
            if tag in RAW:
                stop = re.compile(rf"</{re.escape(tag)}\b[^>]*>", re.I).search(source, at)
                at = stop.end() if stop else len(source)
                found.send(at)
                continue
            if tag in VOID:
                if not muted:
                    self._add(stack, tag)
                continue
            if attrs.rstrip().endswith("/") and tag in ("svg", "path"):
                continue
            node = -1
            if not muted and (noise := _noise(tag, attrs, article > 0)) != "never":
                node = self._add(stack, tag)
                self.suspect[node] = noise == "suspect"
            stack.push(node, tag)
            muted += node < 0
            article += tag == "article"
        self._say(stack, muted, source[at:])
        if any(self.suspect):
            self._cut()

    def _cut(self) -> None:
        """Take out the suspect nodes that are not the page's content."""
        n = len(self.tag)
        own = [0 if self.link[i] else sum(len("".join(t.split())) for _, t in self.text[i] if t) for i in range(n)]
        plain, under, clean = own[:], [False] * n, 0
        for i in range(n - 1, 0, -1):
            plain[self.parent[i]] += plain[i]
        for i in range(n):
            under[i] = self.suspect[i] or (i > 0 and under[self.parent[i]])
            clean += 0 if under[i] else own[i]
        holds: set[int] = set()  # nodes around the article (else main element) with the most text
        for name in ("article", "main"):
            if named := [i for i in range(n) if self.tag[i] == name and plain[i]]:
                at = max(named, key=lambda i: (plain[i], -i))
                while at >= 0 and (holds or plain[at] >= clean or not under[at]):
                    holds.add(at)
                    at = self.parent[at]
                break
        gone = [False] * n
        for i in range(1, n):
            gone[i] = gone[self.parent[i]] or (self.suspect[i] and i not in holds and plain[i] <= MOST * plain[0])
        if sum(own[i] for i in range(n) if not gone[i]) < LEFT * plain[0]:
            return
        number, kept = {-1: -1}, [i for i in range(n) if not gone[i]]
        number |= {old: new for new, old in enumerate(kept)}
        self.parent = [number[self.parent[i]] for i in kept]
        self.tag, self.link, self.text, self.suspect = ([c[i] for i in kept] for c in (self.tag, self.link, self.text, self.suspect))

    def _add(self, stack: Open, tag: str) -> int:
        parent = stack.items[-1][0]
        self.tag.append(tag)
        self.parent.append(parent)
        self.link.append(tag == "a" or self.link[parent])
        self.text.append([])
        self.suspect.append(False)
        return len(self.tag) - 1

    def _say(self, stack: Open, muted: int, text: str | None) -> None:
        """Own text of the open node; None is a block's edge."""
        if not muted and (text is None or text):
            self.place += 1
            self.text[stack.items[-1][0]].append((self.place, text))

    def densities(self) -> tuple[list[float], list[float]]:
        n = len(self.tag)
        chars, linked, tags, links = [0] * n, [0] * n, [0] * n, [0] * n
        for i in range(n - 1, -1, -1):
            own = sum(len("".join(t.split())) for _, t in self.text[i] if t)
            chars[i] += own
            linked[i] += own if self.link[i] else 0
            if (p := self.parent[i]) >= 0:
                chars[p] += chars[i]
                linked[p] += linked[i]
                tags[p] += tags[i] + 1
                links[p] += links[i] + (self.tag[i] == "a")
        body = linked[0] / max(chars[0], 1)
        density, total = [0.0] * n, [0.0] * n
        for i in range(n):
            if chars[i]:
                c, lc, t, lt = chars[i], linked[i], max(tags[i], 1), max(links[i], 1)
                base = math.log(c / max(c - lc, 1) * lc + body * c + math.e)
                density[i] = c / t * math.log(c / max(lc, 1) * t / lt + 1e-9) / math.log(base + 1e-9) if base > 1.0001 else c / t * math.log(c / max(lc, 1) * t / lt + 1.0)
                if self.parent[i] >= 0:
                    total[self.parent[i]] += density[i]
        return density, total

    def main(self) -> str:
        density, total = self.densities()
        best = max((i for i in range(len(total)) if self.tag[i] in BLOCK and self.tag[i] not in TEXT), key=lambda i: (total[i], -i))
        if total[best] <= 0:
            best = max(range(len(density)), key=lambda i: (density[i], -i))
        path = [best]
        while self.parent[path[-1]] >= 0:
            path.append(self.parent[path[-1]])
        # what stands beside the content and is as dense as its path to the body is content as well
        threshold, up = min(density[i] for i in path), self.parent[best]
        chosen = {best}
        for i in range(len(self.tag)):
            if up >= 0 and self.parent[i] == up and density[i] >= threshold and (self.tag[i] in TEXT or total[i] >= SHARE * total[best]):
                chosen.add(i)
        pieces = []
        inside = [False] * len(self.tag)
        for i in range(len(self.tag)):
            inside[i] = i in chosen or (self.parent[i] >= 0 and inside[self.parent[i]])
            if inside[i]:
                pieces += self.text[i]
        pieces.sort(key=lambda x: x[0])
        return " ".join(html.unescape("".join(" " if t is None else t for _, t in pieces)).split())


def main_text(source: str | None) -> str:
    return Page(source).main() if source else ""


def extract(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """Rows (id, url, text, n_chars), one per page."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 256):
                part = batch.slice(a, 256)
                texts = [main_text(x) for x in part.column(2).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["id", "url", "text", "n_chars"])

    return pages.select(F.col(id_col).cast("long").alias("id"), F.col(url_col).cast("string").alias("url"), F.col(html_col).alias("html")).mapInArrow(trimmed(run), "id long, url string, text string, n_chars long")
