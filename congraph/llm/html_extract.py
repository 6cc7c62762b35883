"""Main text of web pages by minimum cut.

A page becomes its text blocks. A linear classifier gives each block log odds for content, from the elements above it,
the kind of its own element, its words, its marks of sentences, its share of linked text, its place on the page and, as one
feature among these, the names of containers. The odds become the block's capacity from the source (content) or to
the sink (boilerplate). Neighbours in page order and blocks near in the document tree are joined by smoothness edges, as strong as
the odds of a doubtful block, so that it goes with those around it. The cut of least cost separates content from boilerplate.

Cases: null or empty html, and pages without content: the empty text; unclosed or stray tags, comments and
quotes are read as browsers do; a `<` that opens no tag is text; repeated page_ids are rows of their own; an
empty table gives no rows; further columns are left alone. Nothing is cut off or capped.
"""

from __future__ import annotations

import html
import re
from collections import deque
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from congraph.sources.shipping import ship_code

_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)"
    r"|<(script|style|noscript|template|svg|math|iframe|object|title|textarea|select)\b(?:[^>\"']|\"[^\"]*\"|'[^']*')*+>.*?(?:</\1\s*>|\Z)"
    r"|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+)>"
    r"|<[!?/][^>]*>"
    r"|<[a-zA-Z][^>]*(?:>|\Z)",
    re.S | re.I,
)
_NAME = re.compile(r"\b(class|id|role|hidden|aria-hidden|style|itemprop)\b(?:\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s\"'>]+))?", re.I)

#: Elements that stay inside a block; every other one starts or ends a block.
INLINE = frozenset(
    "a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr br input picture source".split()
)
_VOID = frozenset("area base col embed hr img input link meta param source track wbr br".split())
_CLOSES_ITSELF = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
_SCOPES = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table", "tr"}, "th": {"table", "tr"}}
#: Log odds of the classifier, by element above a block; fixed values.
ABOVE = {
    "article": 3.0, "main": 2.5, "nav": -7.0, "footer": -7.0, "aside": -6.0, "form": -5.0, "menu": -6.0, "dialog": -7.0,
    "button": -7.0, "fieldset": -4.0, "header": -4.0, "head": -9.0,
}
#: By a block's own element.
OWN = {"p": 1.0, "pre": 1.5, "blockquote": 1.0, "figcaption": 1.0, "h1": 2.5, "h2": 1.0, "h3": 0.8, "h4": 0.5, "h5": 0.5, "h6": 0.5, "li": -0.3, "td": -0.3, "th": -0.3, "dt": -0.3, "dd": -0.3}
HIDDEN, NAMED_FOR, NAMED_AGAINST, NAMED_BESIDE, NAMED_DOUBTFUL = -10.0, 2.0, -10.0, -7.5, -1.2
#: Outside any container of content; a word, up to MOST_WORDS; the end of a sentence; linked text outside content and inside it; the ends of a page.
BARE, WORD, MOST_WORDS, SENTENCE, LINKED, LINKED_INSIDE, EDGE = -1.5, 0.08, 40, 0.7, -6.0, -2.5, -0.4
#: Smoothness: of neighbours, and of blocks in one container, over one and the tree's distance.
ADJACENT, PROXIMITY = 0.4, 2.2
#: Words in names of containers: against content; such as articles' own parts have as well; of teasers; for content.
_AGAINST = re.compile(
    r"(?:^|[\s_-])(?:ad|ads|advert\w*|adsense|sponsor\w*|promo\w*|banner|nav\w*|menu\w*|breadcrumbs?|foot|footer|masthead|sidebar|aside|widgets?|comments?|commentlist|replies|respond|disqus|cookies?|consent|gdpr|popup|modal|overlay|newsletter|subscribe|signup|login|share|sharing|social\w*|pagination|pager|toolbar|hidden|notices?|alert|searchform|searchbox)(?=$|[\s_-])",
    re.I,
)
_DOUBTFUL = re.compile(r"(?:^|[\s_-])(?:header|side|reply|tags?|meta|legal|copyright|disclaimer|skip|form|search)(?=$|[\s_-])", re.I)
_BESIDE = re.compile(r"(?:^|[\s_-])(?:related|recommend\w*)(?=$|[\s_-])", re.I)
_FOR = re.compile(r"(?:^|[\s_-])(?:article\w*|content|main|post|entry|story|body|text|articlebody|prose)(?=$|[\s_-])", re.I)
_ENDS = re.compile(r"[.!?\u2026:;\u3002\uff01\uff1f][\"'\u00bb\u201d\u2019)\]]*$")


class Block:
    __slots__ = ("path", "tag", "text", "linked")

    def __init__(self, path: tuple, tag: str, text: str, linked: int):
        self.path, self.tag, self.text, self.linked = path, tag, text, linked


class _Node:
    """An element with what it and those above it say: `inside` for content, `lean` for everything else."""

    __slots__ = ("tag", "up", "depth", "inside", "lean")

    def __init__(self, tag: str, up: _Node | None, attributes: str):
        self.tag, self.up, self.depth = tag, up, (up.depth + 1 if up else 0)
        names, hidden = "", False
        if attributes:
            for key, value in _NAME.findall(attributes):
                key, value = key.lower(), value.strip("\"'")
                if key == "hidden" or key == "aria-hidden" and value == "true" or key == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value):
                    hidden = True
                elif key in ("class", "id", "role", "itemprop"):
                    names += " " + value
        inside, lean = (up.inside, up.lean) if up else (0.0, 0.0)
        own = ABOVE.get(tag, 0.0)
        if own > 0:
            inside = max(inside, own)
        elif not (tag == "header" and inside >= 2.0):  # an article's header holds its headline
            lean += own
        if names and tag not in ("body", "html"):
            if _AGAINST.search(names):
                lean += NAMED_AGAINST
            elif _BESIDE.search(names):
                lean += NAMED_BESIDE
            elif _DOUBTFUL.search(names):
                lean += NAMED_DOUBTFUL
            if _FOR.search(names):
                inside = max(inside, NAMED_FOR)
        self.inside, self.lean = inside, lean + HIDDEN * hidden


def blocks_of(page: str) -> list[Block]:
    root = _Node("html", None, "")
    top, out = root, []
    parts: list[str] = []
    links, linked, tag = 0, 0, ""
    leaf: _Node | None = None  # a paragraph's or heading's own names

    def flush():
        nonlocal linked, parts
        text = " ".join(html.unescape("".join(parts)).split())
        if text:
            out.append(Block(leaf or top, tag or top.tag, text, min(linked, len(text))))
        parts, linked = [], 0

    def add(text):
        nonlocal linked
        parts.append(text)
        if links:
            linked += len(text.strip())

    def close(name):
        """Leaves the innermost element of that name; False if there is none."""
        nonlocal top
        node = top
        while node is not root and node.tag != name:
            node = node.up
        if node is root:
            return False
        top = node.up
        return True

    at = 0
    for m in _TOKEN.finditer(page):
        if m.start() > at:
            add(page[at : m.start()])
        at = m.end()
        name = m.group(3)
        if not name:
            continue
        name, shut = name.lower(), bool(m.group(2))
        if name in INLINE:
            if name == "a":
                links = max(0, links - 1) if shut else 1
            elif name == "br":
                parts.append(" ")
            continue
        flush()
        links, leaf = 0, None
        if name in ("html", "body"):
            continue
        if shut:
            close(name)
            tag = ""
            continue
        tag = name
        if name in _CLOSES_ITSELF:
            node = top
            while node is not root and node.tag not in _CLOSES_ITSELF[name] and node.tag not in _SCOPES.get(name, ()):
                node = node.up
            if node is not root and node.tag in _CLOSES_ITSELF[name]:
                top = node.up
        if name == "p" or re.fullmatch(r"h[1-6]|pre|blockquote", name):
            # A paragraph ends the one before it; headings and paragraphs are leaves here.
            if name != "blockquote":
                if m.group(4).strip():
                    leaf = _Node(name, top, m.group(4))
                continue
        if name not in _VOID and not m.group(4).endswith("/"):
            top = _Node(name, top, m.group(4))
    if at < len(page):
        add(page[at:])
    flush()
    return out


def evidence(block: Block, place: float = 0.5) -> float:
    """Log odds that a block is content; place: 0 to 1 along the page."""
    node, words = block.path, len(block.text.split())
    share = block.linked / max(1, len(block.text))
    score = (node.inside or BARE) + node.lean + OWN.get(block.tag, 0.0) + WORD * min(words, MOST_WORDS)
    score += share * (LINKED_INSIDE if node.inside else LINKED)
    if _ENDS.search(block.text):
        score += SENTENCE
    return score + (EDGE if place < 0.05 or place > 0.95 else 0.0)


def _tree_distance(a: _Node, b: _Node) -> int:
    steps = 0
    while a is not b:
        if a.depth >= b.depth and a.up is not None:
            a = a.up
        else:
            b = b.up
        steps += 1
    return steps


def edges_of(blocks: list[Block], adjacency: float = ADJACENT, proximity: float = PROXIMITY) -> list[tuple[int, int, float]]:
    """Smoothness: each block with the next, and with the one after its next in the same container."""
    out = []
    last: dict[int, int] = {}
    for k, b in enumerate(blocks):
        if k:
            out.append((k - 1, k, adjacency + proximity / (1 + _tree_distance(blocks[k - 1].path, b.path))))
        before = last.get(id(b.path))
        if before is not None and before < k - 1:
            out.append((before, k, proximity / 2))
        last[id(b.path)] = k
    return out


def minimum_cut(odds: list[float], edges: list[tuple[int, int, float]]) -> list[bool]:
    """True for nodes on the source's side of the least cut; odds > 0: capacity from the source, else to the sink."""
    n = len(odds)
    source, sink = n, n + 1
    to: list[int] = []
    room: list[float] = []
    out: list[list[int]] = [[] for _ in range(n + 2)]

    def arc(a, b, there, back):
        out[a].append(len(to)), to.append(b), room.append(there)
        out[b].append(len(to)), to.append(a), room.append(back)

    for k, x in enumerate(odds):
        if x > 0:
            arc(source, k, x, 0.0)
        elif x < 0:
            arc(k, sink, -x, 0.0)
    for a, b, w in edges:
        arc(a, b, w, w)
    tiny = 1e-9
    while True:
        level = [-1] * (n + 2)
        level[source] = 0
        queue = deque([source])
        while queue:
            a = queue.popleft()
            for e in out[a]:
                if room[e] > tiny and level[to[e]] < 0:
                    level[to[e]] = level[a] + 1
                    queue.append(to[e])
        if level[sink] < 0:
            return [level[k] >= 0 for k in range(n)]
        used = [0] * (n + 2)
        while True:  # blocking flow, one path at a time, without recursion
            path, a = [], source
            while a != sink:
                while used[a] < len(out[a]):
                    e = out[a][used[a]]
                    if room[e] > tiny and level[to[e]] == level[a] + 1:
                        break
                    used[a] += 1
                if used[a] < len(out[a]):
                    path.append(out[a][used[a]])
                    a = to[path[-1]]
                elif path:
                    a = to[path.pop() ^ 1]
                    used[a] += 1
                else:
                    break
            if a != sink:
                break
            least = min(room[e] for e in path)
            for e in path:
                room[e] -= least
                room[e ^ 1] += least


def labelled(page: str) -> list[tuple[Block, float, bool]]:
    """Each block with the classifier's log odds, and whether the cut puts it on the side of content."""
    blocks = blocks_of(page)
    odds = [evidence(b, k / max(1, len(blocks) - 1)) for k, b in enumerate(blocks)]
    if all(x > 0 for x in odds) or all(x <= 0 for x in odds):
        kept = [x > 0 for x in odds]  # nothing to cut
    else:
        kept = minimum_cut(odds, edges_of(blocks))
    return list(zip(blocks, odds, kept))


def main_text(page: str) -> str:
    return "\n\n".join(b.text for b, _, keep in labelled(page) if keep)


def _extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        texts = [main_text(x or "") for x in batch.column("html").to_pylist()]
        yield pa.record_batch([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])


def extract_pages(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars: one row for each row of pages."""
    ship_code(pages.sparkSession)
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return rows.mapInArrow(_extract, "page_id long, url string, text string, n_chars long")
