"""Main text of web pages by minimum-cut labelling.

A page is cut into blocks of text at block-level elements. A classifier on each block's ancestors, links and length
gives log-odds of being content; they become capacities from the source or to the sink. Blocks that follow each
other, and blocks under one parent, are tied by smoothness edges whose capacity falls with their distance in the
tree. The minimum cut separates content from boilerplate.

What elements say of themselves by name, class, id and role is evidence, not a verdict. A class is read token by token;
tokens that only tell a state of the page (has-sidebar) do not count, and where tokens disagree the first one that says
anything holds. An element that says boilerplate but holds the page's main element, its first heading or nearly all its
prose is a wrapper, and what it says is void.

The parser is a single pass over tags: it knows comments, raw-text elements, void elements and the end tags that HTML
lets pages leave out. Character references are decoded, white space inside a block becomes one space, and blocks are
joined by an empty line.

Edge cases: null and empty pages, and pages without content, give an empty text. Unclosed elements end with their
parent, an unclosed comment or script with the page. Text without any tag is one block. Repeated rows are extracted
alike; null ids are kept. Extra columns are ignored.
"""

from __future__ import annotations

import html as _html
import math
import re
from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

# --- parsing -------------------------------------------------------------------------------------------------------

_TOKEN = re.compile(r"<!--.*?(?:-->|\Z)|<[!?][^>]*+>?|<(/?)([a-zA-Z][^\s/>]*+)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>?", re.S)
_ATTRIBUTE = re.compile(r"([^\s=/\"'>]+)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_SPLIT = re.compile(r"[^a-z0-9]+|(?<=[a-z])(?=[A-Z])")

# Element names of HTML by how they are parsed.
RAW = frozenset("script style noscript template iframe textarea title noembed noframes svg select".split())
TO_THE_END = frozenset("script style textarea title".split())  # of a page, where they are not closed
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q s samp small span strike strong sub sup time tt u var wbr nobr blink math mrow mi mo mn ms mtext msup msub msubsup mfrac msqrt mroot mover munder mstyle semantics object".split())
CLOSES_P = frozenset("address article aside blockquote center details dialog dir div dl fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr main menu nav ol p pre section summary table ul".split())
SIBLINGS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "thead": {"tr", "td", "th"}, "tbody": {"thead", "tbody", "tr", "td", "th"}, "tfoot": {"tbody", "tr", "td", "th"}}
SCOPE = {"li": {"ul", "ol", "menu"}, "dt": {"dl"}, "dd": {"dl"}, "tr": {"table"}, "td": {"table"}, "th": {"table"}, "option": {"select"}, "thead": {"table"}, "tbody": {"table"}, "tfoot": {"table"}}
WALLS = frozenset("html body table td th caption button object".split())

STOPS = ".!?:;\"')…»”。！？"  # that end a sentence

# Words in class, id and role that tell boilerplate or content.
BOILERPLATE = frozenset("nav navbar navigation menu menubar submenu footer foot sidebar side aside rail ad ads advert advertisement adverts advertising adsense banner sponsor sponsored promo promotion promoted cookie cookies consent gdpr notice notices alert disclaimer comment comments disqus reply replies respond discussion share sharing social follow related recommend recommended recommendations more trending popular newsletter subscribe subscription signup login signin register popup modal overlay dialog breadcrumb breadcrumbs pagination pager toolbar topbar masthead skip search form copyright legal widget widgets tags toc contentinfo complementary paywall".split())
STATES = frozenset("has with no not without is open opened closed enabled disabled layout active page".split())  # such a token tells a state
HEADERS = frozenset("header head top site".split())
CONTENT = frozenset("article content main post entry story body text prose page hentry articlebody".split())
BAD_TAGS = frozenset("nav footer aside form dialog menu button fieldset".split())
GOOD_TAGS = frozenset("article main".split())


@dataclass(slots=True)
class Node:
    """An element, with what it says of itself: good for content, bad for boilerplate, and how strongly."""

    tag: str
    parent: Node | None
    depth: int
    good: bool
    bad: float
    prose: int = 0  # characters of unlinked prose inside
    wraps: bool = False  # holds the page's main element or its first heading

    def told(self, all_prose: int) -> tuple[bool, float]:
        """(whether anything around says content, how strongly anything around says boilerplate)."""
        good, bad, at = False, 0.0, self
        while at is not None:
            good = good or at.good
            if at.bad and not (at.wraps or all_prose and at.prose > 0.9 * all_prose):
                bad = max(bad, at.bad if at.bad >= 2 or not good else 0.0)
            at = at.parent
        return good, bad


@dataclass(slots=True)
class Block:
    node: Node
    text: str
    linked: int
    in_head: bool = False


@dataclass(frozen=True)
class Weights:
    """Log-odds of the classifier and capacities of the smoothness edges."""

    start: float = -0.6
    good: float = 3.0
    strong: float = -9.0
    header: float = -4.0
    link: float = -3.5
    length: float = 0.55
    sentence: float = 0.8
    paragraph: float = 0.7
    heading: float = 0.3
    item: float = -0.4
    near: float = 0.8
    sibling: float = 0.6
    fade: float = field(default=0.5)


def _said(value: str) -> str:
    """What a class, id or role says: "content", "boilerplate", "header" or nothing."""
    said = ""
    for token in value.split():
        words = {w for w in _SPLIT.split(re.sub(r"(?<=[a-z0-9])(?=[A-Z])", "-", token).lower()) if w}
        if words & STATES and len(words) > 1:
            continue
        now = "boilerplate" if words & BOILERPLATE else "content" if words & CONTENT else "header" if words & HEADERS else ""
        if now and (not said or said == "header"):
            said = now
    return said


def _signals(tag: str, attributes: str) -> tuple[bool, float]:
    """What an element says of itself."""
    good, bad = tag in GOOD_TAGS, 2.0 if tag in BAD_TAGS else 1.0 if tag == "header" else 0.0
    if "=" in attributes or "hidden" in attributes:
        for name, *values in _ATTRIBUTE.findall(attributes):
            name, value = name.lower(), "".join(values)
            if name in ("class", "id", "role") and tag not in ("html", "body"):
                said = _said(value)
                if said == "boilerplate" and not (good and bad < 2 and name != "class"):
                    good, bad = False, 2.0
                elif said == "content" and bad < 2:
                    good = True
                elif said == "header" and not good:
                    bad = max(bad, 1.0)
            elif name == "hidden" or name == "aria-hidden" and value.lower() == "true" or name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value.lower()):
                bad = 3.0
    return good, bad


def parse(page: str) -> list[Block]:
    """The page's blocks of text in order."""
    root = Node("#", None, 0, False, 0.0)
    node, blocks = root, []
    pieces: list[str] = []
    linked, links, place, head, headed = 0, 0, root, 0, False

    def flush() -> None:
        nonlocal pieces, linked, place
        if pieces:
            text = " ".join("".join(pieces).split())
            if text:
                blocks.append(Block(place, text, min(linked, len(text)), head > 0))
                own = len(text) - blocks[-1].linked
                if not head and (text[-1] in STOPS or text.count(" ") >= 9):
                    up = place
                    while up is not None:
                        up.prose += own
                        up = up.parent
        pieces, linked = [], 0

    def add(raw: str) -> None:
        nonlocal linked, place
        if raw:
            text = _html.unescape(raw) if "&" in raw else raw
            if not pieces or not any(not p.isspace() for p in pieces):
                place = node
            pieces.append(text)
            if links:
                linked += len(text.strip())

    def leave(to: Node) -> None:
        """Close elements until ``to`` is closed."""
        nonlocal node, links, head
        while True:
            if node.tag == "a":
                links = max(0, links - 1)
            elif node.tag == "head":
                head = 0
            last, node = node, node.parent
            if last is to:
                return

    def close(names: set[str] | frozenset[str], stops: set[str] | frozenset[str]) -> bool:
        at = node
        while at is not root and at.tag not in stops:
            if at.tag in names:
                leave(at)
                return True
            at = at.parent
        return False

    at, n = 0, len(page)
    while at < n:
        m = _TOKEN.search(page, at)
        if m is None:
            add(page[at:])
            break
        add(page[at : m.start()])
        at = m.end()
        name = m[2]
        if name is None:
            continue
        tag = name.lower()
        if m[1]:
            if tag == "br":
                add(" ")
                continue
            if tag in INLINE:
                close({tag}, WALLS)
            else:
                flush()
                close({tag}, {"#"})
            continue
        if tag == "br":
            add(" ")
            continue
        if tag not in INLINE:
            flush()
        if tag in RAW:
            end = re.compile(rf"</{re.escape(tag)}(?=[\s/>]|\Z)[^>]*>?", re.I).search(page, at)
            if not m[3].rstrip().endswith("/"):
                at = end.end() if end else n if tag in TO_THE_END else at  # others are left open by mistake, and what follows is the page
            continue
        if tag in VOID:
            continue
        if tag in CLOSES_P:
            close({"p"}, WALLS)
        if tag in SIBLINGS:
            while close(SIBLINGS[tag], SCOPE[tag]):
                pass
        if tag == "body" and head:
            close({"head"}, {"#"})
        if tag == "a":
            if close({"a"}, WALLS):
                pass
            links += 1
        node = Node(tag, node, node.depth + 1, *_signals(tag, m[3]))
        if tag == "main" or tag == "h1" and not headed:
            headed = headed or tag == "h1"
            up = node.parent
            while up is not None and not up.wraps:
                up.wraps = up.tag not in ("header", "nav")  # the name of a site stands there
                up = up.parent
        if tag == "head":
            head = 1
    flush()
    return [b for b in blocks if not b.in_head]


# --- labelling -----------------------------------------------------------------------------------------------------


def odds(block: Block, w: Weights, all_prose: int = 0) -> float:
    """Log-odds that the block is content."""
    node, text = block.node, block.text
    good, bad = node.told(all_prose)
    if bad >= 2:
        return w.strong
    words = text.count(" ") + 1
    score = w.start + w.length * math.log1p(min(words, 200)) + w.link * block.linked / len(text)
    if text[-1] in STOPS:
        score += w.sentence
    at = node
    while at.parent is not None and at.tag in INLINE:
        at = at.parent
    if at.tag == "p" or at.tag in ("blockquote", "pre"):
        score += w.paragraph
    elif len(at.tag) == 2 and at.tag[0] == "h" and at.tag[1].isdigit():
        score += w.heading
    elif at.tag == "li":
        score += w.item
    if good:
        score += w.good
    if bad >= 1:
        score += w.header
    return score


def _apart(a: Node, b: Node) -> tuple[int, bool]:
    """(steps between two nodes in the tree, whether they have the same parent)."""
    same, steps = a.parent is b.parent, 0
    while a is not b:
        if a.depth >= b.depth:
            a = a.parent
        else:
            b = b.parent
        steps += 1
    return steps, same


def label(blocks: list[Block], w: Weights = Weights()) -> tuple[list[bool], int]:
    """(True for content blocks, by minimum cut; how many of them the edges turned against their own odds)."""
    root = blocks[0].node if blocks else None
    while root is not None and root.parent is not None:
        root = root.parent
    terminal = [odds(b, w, root.prose) for b in blocks]
    edges: list[tuple[int, int, float]] = []
    last: dict[int, int] = {}
    for i, b in enumerate(blocks):
        if i:
            steps, _ = _apart(blocks[i - 1].node, b.node)
            edges.append((i - 1, i, w.near * w.fade ** max(0, steps - 2)))
        parent = id(b.node.parent)
        if (j := last.get(parent)) is not None:
            edges.append((j, i, w.sibling))
        last[parent] = i
    kept = cut(terminal, edges)
    return kept, sum(k != (t > 0) for k, t in zip(kept, terminal, strict=True))


def cut(terminal: list[float], edges: list[tuple[int, int, float]]) -> list[bool]:
    """Minimum cut: True on the source side. terminal > 0 ties a node to the source, < 0 to the sink.

    A node whose terminal capacity is at least that of all its edges lies on that terminal's side of some
    minimum cut; it is settled first and its edges become terminal capacity of its neighbours. What remains, mostly
    nothing, is solved by augmenting along shortest paths.
    """
    n = len(terminal)
    terminal = list(terminal)
    links: list[dict[int, float]] = [{} for _ in range(n)]
    for a, b, c in edges:
        if a != b and c > 0:
            links[a][b] = links[a].get(b, 0.0) + c
            links[b][a] = links[b].get(a, 0.0) + c
    side: list[bool | None] = [None] * n
    queue = deque(range(n))
    queued = [True] * n
    while queue:
        i = queue.popleft()
        queued[i] = False
        if side[i] is not None:
            continue
        if abs(terminal[i]) >= sum(links[i].values()):
            side[i] = terminal[i] > 0
            for j, c in links[i].items():
                del links[j][i]
                terminal[j] += c if side[i] else -c
                if not queued[j]:
                    queued[j] = True
                    queue.append(j)
            links[i] = {}
    core = [i for i in range(n) if side[i] is None]
    if core:
        for i, s in zip(core, _flow(core, terminal, links), strict=True):
            side[i] = s
    return [bool(s) for s in side]


def _flow(core: list[int], terminal: list[float], links: list[dict[int, float]]) -> list[bool]:
    """Source sides of the core's nodes, by maximum flow along shortest augmenting paths."""
    source, sink = -1, -2
    room: dict[int, dict[int, float]] = {i: dict(links[i]) for i in core}
    room[source], room[sink] = {}, {}
    for i in core:
        t = terminal[i]
        room[source][i], room[i][source] = max(t, 0.0), 0.0
        room[i][sink], room[sink][i] = max(-t, 0.0), 0.0
    while True:
        came: dict[int, int] = {source: source}
        queue = deque([source])
        while queue and sink not in came:
            i = queue.popleft()
            for j, c in room[i].items():
                if c > 1e-12 and j not in came:
                    came[j] = i
                    queue.append(j)
        if sink not in came:
            return [i in came for i in core]
        path, at = [], sink
        while at != source:
            path.append((came[at], at))
            at = came[at]
        least = min(room[a][b] for a, b in path)
        for a, b in path:
            room[a][b] -= least
            room[b][a] = room[b].get(a, 0.0) + least


def main_text(page: str | None, w: Weights = Weights()) -> str:
    if not page:
        return ""
    return labelled(page, w)[0]


def labelled(page: str | None, w: Weights = Weights()) -> tuple[str, int, int]:
    """(main text, number of blocks, number of blocks whose label the smoothness edges turned)."""
    blocks = parse(page) if page else []
    kept, turned = label(blocks, w)
    return "\n\n".join(b.text for b, keep in zip(blocks, kept, strict=True) if keep), len(blocks), turned


def extract(pages: DataFrame, w: Weights = Weights()) -> DataFrame:
    """Per row of ``pages`` (page_id, url, html): page_id, url, text, n_chars, n_blocks, n_turned."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, blocks, turned = zip(*(labelled(x.as_py(), w) for x in batch["html"]), strict=True) if batch.num_rows else ((), (), ())
            lengths = pa.array([len(t) for t in texts], pa.int64())
            yield pa.RecordBatch.from_arrays([batch["page_id"], batch["url"], pa.array(texts, pa.string()), lengths, pa.array(blocks, pa.int64()), pa.array(turned, pa.int64())], names=["page_id", "url", "text", "n_chars", "n_blocks", "n_turned"])

    rows = pages.select(pages["page_id"].cast("long").alias("page_id"), pages["url"].cast("string").alias("url"), "html")
    return rows.mapInArrow(run, "page_id long, url string, text string, n_chars long, n_blocks long, n_turned long")


def op5_html_text(spark, sf_dir: str) -> DataFrame:
    return extract(spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", "html"))
