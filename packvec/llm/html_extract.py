"""Operator 6: the main text of web pages by minimum-cut labelling of their blocks.

A page becomes blocks of text between block-level tags. A linear classifier over structure, names, links and length
gives each block a probability of being content; its logarithms are the capacities to the two terminals. Neighbours in
page order and blocks under one parent are tied by smoothness capacities. The minimum cut is the cheapest labelling.
Blocks whose terminal costs outweigh all their ties are settled first, which leaves the flow few nodes.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter, deque
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

TAG = re.compile(r"""<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:"[^"]*"|'[^']*'|[^'"<>])*)>|<[!?][^<>]*>""", re.S)
ATTRIBUTE = re.compile(r"""([^\s"'>/=]+)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""")
NO_DISPLAY = re.compile(r"(?:^|;)\s*display\s*:\s*none", re.I)

#: HTML element names by their part in a page.
RAW = {"script", "style", "template", "textarea", "svg", "iframe", "title"}
RAW_ENDS = {name: re.compile(rf"</{name}[^>]*>", re.I) for name in RAW}
DROPPED = {"head", "datalist"}
VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "param", "source", "track", "wbr"}
BLOCK = {"address", "article", "aside", "blockquote", "body", "caption", "center", "dd", "details", "dialog", "dir", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4", "h5", "h6", "header", "hgroup", "hr", "html", "legend", "li", "main", "menu", "nav", "ol", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "tr", "ul"}
ENDS_P = BLOCK - {"html", "body", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "legend", "summary"}
ENDS_OWN = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
SCOPES = {"ul", "ol", "menu", "dl", "table", "td", "th", "div", "section", "article", "main", "body", "aside", "nav", "form", "blockquote", "header", "footer"}

#: Names in class, id and role: whole parts, and beginnings of parts.
BAD_PARTS = {"ad", "ads", "nav", "menu", "aside", "toc", "tags", "meta", "byline", "modal", "popup", "alert", "banner", "toolbar", "copyright", "complementary", "contentinfo", "search", "login", "signup", "skip", "share", "sharing", "social", "legal"}
BAD_STARTS = ("advert", "sponsor", "promo", "sidebar", "comment", "cookie", "consent", "gdpr", "notice", "footer", "header", "masthead", "navbar", "navigation", "breadcrumb", "related", "recommend", "newsletter", "subscri", "disqus", "respond", "reply", "replies", "discussion", "paywall", "pagination", "pager", "widget", "popup", "modal", "outbrain", "taboola", "topbar")
GOOD_PARTS = {"article", "content", "main", "post", "entry", "story", "body", "text"}

#: Weights of the classifier: a parameter. Named boilerplate outweighs all ties of a block; the rest is of their order.
WEIGHTS = {"bias": -0.4, "outside": -8.0, "bad": -8.0, "article": 0.6, "good": 0.4, "heading": 0.5, "paragraph": 0.8, "item": -0.6, "links": -3.5, "length": 0.7, "sentence": 0.5, "symbol": -1.5}
#: Ties between neighbours under one parent, neighbours elsewhere, and the next block of one parent further on.
TIES = (2.0, 0.4, 0.8)


@dataclass
class Block:
    text: str
    parent: int
    facts: dict[str, float]


class Page:
    """Blocks of one page, from a single pass over its tags with a stack of open elements."""

    def __init__(self, source: str):
        self.blocks: list[Block] = []
        self.stack: list[tuple[str, int, str]] = []  # element, number, part: "", "bad", "good", "article", "outside", "dropped"
        self.words: list[str] = []
        self.inside: Counter[str] = Counter()  # open elements by part, and by name
        self.linked, self.number, end = 0, 0, 0
        while m := TAG.search(source, end):
            self.take(source[end : m.start()])
            end, name = m.end(), (m[2] or "").lower()
            if not name:
                continue
            if m[1]:
                self.close(name)
            elif name not in RAW:
                self.open(name, m[3])
            elif not m[3].rstrip().endswith("/"):  # what is inside is not markup
                found = RAW_ENDS[name].search(source, end)
                end = found.end() if found else len(source)
        self.take(re.sub(r"<[a-zA-Z/!][^>]*\Z", "", source[end:]))
        self.flush()

    def take(self, text: str) -> None:
        if text and not self.inside["part dropped"]:
            self.words.append(text)
            if self.inside["a"]:
                self.linked += len(text.strip())

    def flush(self) -> None:
        if not self.words:
            return
        text = " ".join(html.unescape("".join(self.words)).split())
        linked, self.words, self.linked = self.linked, [], 0
        if not text:
            return
        blocks = (x for x in reversed(self.stack) if x[0] in BLOCK)
        kind, parent = next(blocks, ("", 0, ""))[0], next(blocks, ("", 0, ""))[1]
        within = lambda part: float(self.inside[f"part {part}"] > 0)
        letters = sum(c.isalnum() for c in text)
        self.blocks.append(Block(text, parent, {
            "bias": 1.0, "outside": within("outside"), "bad": within("bad"), "article": within("article"), "good": within("good"),
            "heading": float(kind in ("h1", "h2", "h3", "h4", "h5", "h6")), "paragraph": float(kind in ("p", "pre", "blockquote")), "item": float(kind in ("li", "dt", "dd", "td", "th")),
            "links": min(1.0, linked / max(1, len(text))), "length": min(3.0, math.log1p(len(text)) / 2 - 1), "sentence": float(bool(re.search(r"[.!?…:](?:\s|$)", text))), "symbol": float(letters * 3 < len(text)),
        }))

    def part(self, name: str, attributes: str) -> str:
        given = {k.lower(): a or b or c for k, a, b, c in reversed(ATTRIBUTE.findall(attributes))} if attributes and not attributes.isspace() else {}
        if name in DROPPED or (given and ("hidden" in given or given.get("aria-hidden", "").lower() == "true" or NO_DISPLAY.search(given.get("style", "")))):
            return "dropped"
        within = self.inside["part article"] > 0
        if name in ("nav", "aside", "form", "dialog", "menu") or name == "footer" or (name == "header" and not within):
            return "outside"
        named = " ".join(given[k] for k in ("class", "id", "role") if k in given).lower()
        tokens = re.split(r"[^a-z0-9]+", re.sub(r"[\s_-]+", " ", named)) if named else []
        own = within and any(t in ("article", "post", "entry", "content", "story") for t in re.split(r"[^a-z0-9]+", named))
        if name not in ("html", "body", "article", "main") and not own and any(t in BAD_PARTS or t.startswith(BAD_STARTS) for t in tokens):
            return "bad"
        if name in ("article", "main"):
            return "article"
        return "good" if any(t in GOOD_PARTS for t in tokens) else ""

    def open(self, name: str, attributes: str) -> None:
        if name in BLOCK:
            self.flush()
            if name in ENDS_P:
                self.drop_to({"p"}, SCOPES - {"p"})
            if name in ENDS_OWN:
                self.drop_to(ENDS_OWN[name], {"ul", "ol", "dl", "table", "menu"})
        elif name in ("br", "img", "input", "wbr"):
            self.words.append("" if name == "wbr" else " ")
        if name not in VOID and not attributes.endswith("/"):
            self.number += 1
            part = self.part(name, attributes)
            self.stack.append((name, self.number, part))
            self.inside.update((name, f"part {part}"))

    def close(self, name: str) -> None:
        if name in BLOCK:
            self.flush()
        if not self.inside[name]:
            return
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] == name:
                self.cut(i)
                return
            if name not in BLOCK and self.stack[i][0] in BLOCK:
                return

    def drop_to(self, names: set[str], bounds: set[str]) -> None:
        """Ends the innermost open element of names, if none of bounds is open inside it."""
        if not any(self.inside[x] for x in names):
            return
        for i in range(len(self.stack) - 1, -1, -1):
            if self.stack[i][0] in names:
                self.cut(i)
                return
            if self.stack[i][0] in bounds:
                return

    def cut(self, i: int) -> None:
        """Ends the open elements from the i-th on."""
        for name, _, part in self.stack[i:]:
            self.inside.subtract((name, f"part {part}"))
        del self.stack[i:]


def minimum_cut(gain: list[float], ties: dict[tuple[int, int], float]) -> list[bool]:
    """Labels x that minimise the sum of (gain > 0: gain if not x; gain < 0: -gain if x) and the ties cut. True is content."""
    n = len(gain)
    near: list[dict[int, float]] = [{} for _ in range(n)]
    for (a, b), w in ties.items():
        near[a][b] = near[a].get(b, 0.0) + w
        near[b][a] = near[b].get(a, 0.0) + w
    label: list[bool | None] = [None] * n
    own = list(gain)
    todo = deque(range(n))
    while todo:  # a node whose own gain outweighs its free ties is settled; its ties become gains of its neighbours
        a = todo.popleft()
        if label[a] is None and abs(own[a]) >= sum(w for b, w in near[a].items() if label[b] is None):
            label[a] = own[a] > 0
            for b, w in near[a].items():
                if label[b] is None:
                    own[b] += w if label[a] else -w
                    todo.append(b)
    free = [a for a in range(n) if label[a] is None]
    if free:
        side = max_flow_side({a: own[a] for a in free}, {a: {b: w for b, w in near[a].items() if label[b] is None} for a in free})
        for a in free:
            label[a] = a in side
    return [bool(x) for x in label]


def max_flow_side(gain: dict[int, float], near: dict[int, dict[int, float]]) -> set[int]:
    """Nodes on the source's side of a minimum cut: shortest augmenting paths from all nodes with excess."""
    left = {a: max(0.0, g) for a, g in gain.items()}
    room = {a: max(0.0, -g) for a, g in gain.items()}
    rest = {a: dict(x) for a, x in near.items()}
    while True:
        came: dict[int, int | None] = {a: None for a in rest if left[a] > 1e-12}
        queue, goal = deque(came), None
        while queue:
            a = queue.popleft()
            if room[a] > 1e-12:
                goal = a
                break
            for b, w in rest[a].items():
                if w > 1e-12 and b not in came:
                    came[b] = a
                    queue.append(b)
        if goal is None:
            return set(came)
        path, a = [goal], goal
        while came[a] is not None:
            a = came[a]
            path.append(a)
        flow = min([room[goal], left[a], *(rest[y][x] for x, y in zip(path, path[1:]))])
        room[goal] -= flow
        left[a] -= flow
        for x, y in zip(path, path[1:]):
            rest[y][x] -= flow
            rest[x][y] = rest[x].get(y, 0.0) + flow


def gains(blocks: list[Block], weights: dict[str, float]) -> list[float]:
    """-log(1 - p) + log(p): what labelling a block as content saves, p from the classifier."""
    return [max(-12.0, min(12.0, sum(weights[k] * v for k, v in b.facts.items()))) for b in blocks]


def ties_of(blocks: list[Block]) -> dict[tuple[int, int], float]:
    ties: dict[tuple[int, int], float] = {}
    last: dict[int, int] = {}
    for i, b in enumerate(blocks):
        parent = b.parent
        if i:
            same = parent == blocks[i - 1].parent
            ties[i - 1, i] = TIES[0] if same else TIES[1]
        if parent in last and last[parent] < i - 1:
            ties[last[parent], i] = TIES[2]
        last[parent] = i
    return ties


def main_text(source: str | None, weights: dict[str, float] = WEIGHTS) -> str:
    """Text blocks labelled content, one a line; empty for null or empty pages."""
    if not source:
        return ""
    blocks = Page(source).blocks
    keep = minimum_cut(gains(blocks, weights), ties_of(blocks))
    return "\n".join(b.text for b, k in zip(blocks, keep) if k)


def extract(df: DataFrame, id: str = "page_id", url: str = "url", source: str = "html") -> DataFrame:
    """id, url, text, n_chars of every page.

    Edge cases: null, empty and tag-only pages give an empty text; pages cut off in a tag, comment or script give what
    precedes it; repeated rows give repeated results; other columns are not read; an empty table gives an empty result.
    """
    types = {c: df.schema[c].dataType.simpleString() for c in (id, url)}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x.as_py()) for x in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array(map(len, texts), pa.int64())], names=["id", "url", "text", "n_chars"])

    out = df.select(id, url, source).mapInArrow(run, f"id {types[id]}, url {types[url]}, text string, n_chars long")
    return out.withColumnsRenamed({"id": id, "url": url})
