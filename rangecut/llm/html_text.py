"""Main text of web pages by minimum cuts.

A page is read by a tolerant tokenizer into blocks: runs of text between
block-level tags, each with the elements that it stands in. Every block is a
vertex. A logistic classifier of a block's features gives the log odds of
content against boilerplate; they are the capacities of its edges to the two
terminals. Neighbours in the page, and next siblings of one parent, are joined
by smoothness edges, each of a kind: how far apart the two stand in the document
tree, and whether a landmark or a telling class name begins between them. The
minimum cut is the cheapest labelling; blocks on the content side are the text.

The cut is exact. Vertices whose terminal edge outweighs all their other edges
keep their label in every minimum cut, so they are decided first and their edges
move to the neighbours' terminals; only what stays undecided goes through
maximum flow (shortest augmenting paths).

All capacities are learned, in one currency: log odds. Examples are a few pages
labelled by hand (``html_seeds``), and on a bounded sample of the corpus the
blocks in landmark elements (article, main against nav, footer, aside, form).
Every third page has its landmarks and class names blotted out, so that density,
links, tags and position have to carry its blocks. First the classifier is
fitted, by maximum likelihood with a ridge. Then, with the log odds as offsets,
each kind of edge gets the weight that makes blocks' labels given their
neighbours' likeliest (pseudo-likelihood), none below zero: what is usual among
neighbours on the sampled pages counts as much as a feature of the same odds.

Cases: a null page is an empty one and has an empty text; a null id or URL
stays null; repeated rows give a row each; a block at equal cost on both sides
is boilerplate; an empty table gives no rows; other columns are left out, so
none can clash. Pages are read whole; nesting and length have no limit.
"""

from __future__ import annotations

import html
import re
from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rangecut.llm import html_seeds

#: Pages that train the classifier, those whose id hashes lowest.
TRAINING_PAGES = 400
#: Share of the hand-labelled pages in what is learned.
SEED_SHARE = 0.3

# Kinds of HTML elements.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template textarea iframe svg math object title select option button canvas audio video".split())
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark nobr q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split())
CONTENT_TAGS = frozenset(("article", "main"))
BOILERPLATE_TAGS = frozenset("nav footer aside form menu dialog fieldset".split())
BOILERPLATE_ROLES = frozenset("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar toolbar form status".split())
BOILERPLATE_NAMES = frozenset(
    "ad ads advert adverts advertisement advertising banner breadcrumb breadcrumbs byline comment commentlist comments consent cookie cookies copyright disclaimer discussion disqus footer gdpr header hidden legal login masthead menu menus modal nav navbar navigation navi newsletter notice notices notification overlay pagination pager popup popular promo promoted promotion recommended related replies reply respond response responses rail search share sharing sidebar sidebars signup skip social sponsor sponsored subscribe subscription tags teaser toc toolbar topbar trending widget widgets".split()
)
CONTENT_NAMES = frozenset("article articlebody body content contents entry main maincontent post postbody prose story storybody text".split())

_MARKUP = re.compile(
    r"<!--.*?(?:-->|\Z)|<![^>]*>?|<\?[^>]*>?|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*)(?:>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)([^>]*)>",
    re.DOTALL,
)
_ATTRIBUTE = re.compile(r"([a-zA-Z_:][-\w:.]*)(?:\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+)))?")
_NAME = re.compile(r"[a-z0-9]+")
#: Start tags that end an open paragraph, item or cell of their kind.
_ENDS = {"li": ("li",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "tr": ("tr", "td", "th"), "td": ("td", "th"), "th": ("td", "th"), "option": ("option",)}


@dataclass
class Element:
    tag: str
    parent: Element | None
    depth: int
    #: 1 in content landmarks, -1 in boilerplate ones, 0 elsewhere; the nearest that says anything counts.
    landmark: int = 0
    names: int = 0
    header: bool = False
    index: int = 0


@dataclass
class Block:
    element: Element
    tag: str
    parts: list[str] = field(default_factory=list)
    linked: int = 0
    text: str = ""

    def finish(self) -> bool:
        self.text = " ".join(html.unescape("".join(self.parts)).split())
        return bool(self.text)


def _said_by(tag: str, attributes: str, parent: Element | None) -> tuple[int, int, bool]:
    """What an element says of its content: landmark, names, header."""
    landmark, names, header = (parent.landmark, parent.names, parent.header) if parent else (0, 0, False)
    if tag in CONTENT_TAGS:
        landmark = 1 if landmark >= 0 else landmark
    elif tag in BOILERPLATE_TAGS:
        landmark = -1
    elif tag == "header":
        # A header inside an article holds its heading; others are the site's.
        if landmark > 0:
            header = True
        else:
            landmark = -1
    if attributes and not attributes.isspace():
        for name, *values in _ATTRIBUTE.findall(attributes):
            name, value = name.lower(), "".join(values).lower()
            if name == "hidden" or (name == "aria-hidden" and value == "true") or (name == "style" and re.search(r"display\s*:\s*none|visibility\s*:\s*hidden", value)):
                landmark, names = -1, -1
            elif name == "role":
                if value in BOILERPLATE_ROLES:
                    landmark = -1
                elif value in CONTENT_TAGS and landmark >= 0:
                    landmark = 1
            elif name in ("class", "id"):
                words = set(_NAME.findall(value))
                if landmark > 0:
                    words.discard("header")
                if words & BOILERPLATE_NAMES and tag not in ("body", "html", "article", "main"):
                    names, landmark = -1, min(landmark, 0)
                elif words & CONTENT_NAMES and names == 0:
                    names = 1
    return landmark, names, header


def blocks_of(page: str) -> list[Block]:
    """The page's blocks in order, empty ones left out."""
    root = Element("", None, 0)
    here, found = root, []
    current: Block | None = None
    links, count, at, end = 0, 0, 0, len(page)
    lower: str | None = None

    def add(text: str) -> None:
        nonlocal current
        if not text:
            return
        if current is None:
            current = Block(here, here.tag)
        current.parts.append(text)
        if links:
            current.linked += len(text)

    def close() -> None:
        nonlocal current
        if current is not None and current.finish():
            found.append(current)
        current = None

    while at < end:
        match = _MARKUP.search(page, at)
        if match is None:
            add(page[at:])
            break
        add(page[at : match.start()])
        at = match.end()
        tag = match[2] or match[5]
        if not tag:
            continue
        tag = tag.lower()
        closing = bool(match[1] or match[4])
        if tag in RAW and not closing:
            lower = lower if lower is not None else page.lower()
            if len(lower) != end:  # lower case may be longer; then positions are looked up without it
                stop = re.compile(f"</{tag}", re.I).search(page, at)
                begin = stop.start() if stop else -1
            else:
                begin = lower.find(f"</{tag}", at)
            if begin < 0:
                at = end if tag in ("script", "style", "title", "textarea") else at
            else:
                close_at = page.find(">", begin)
                at = end if close_at < 0 else close_at + 1
            continue
        if tag in RAW or tag in ("html", "body", "head") and closing:
            continue
        if tag in INLINE:
            if tag == "a":
                links = 0 if closing else 1
            elif tag == "br":
                add("\n")
            continue
        close()
        links = 0
        if closing:
            node = here
            while node.parent is not None and node.tag != tag:
                node = node.parent
            if node.parent is not None:
                here = node.parent
            continue
        if tag in VOID:
            continue
        if here.tag == "p":  # an open paragraph ends where any block begins
            here = here.parent or root
        if tag in _ENDS and here.tag in _ENDS[tag]:
            here = here.parent or root
        count += 1
        here = Element(tag, here, here.depth + 1, *_said_by(tag, match[3] or match[6] or "", here), count)
    close()
    return found


N_FEATURES = 16
_NOTICE = re.compile(r"©|\(c\)\s*\d|all rights reserved|cookie|privacy policy|terms of (?:use|service)|subscribe|newsletter|sign up|log ?in|advertisement|sponsored", re.I)


def features_of(blocks: list[Block], blotted: bool = False) -> np.ndarray:
    """Landmarks and names come first; ``blotted`` hides them."""
    out = np.zeros((len(blocks), N_FEATURES))
    total = sum(len(b.text) for b in blocks) or 1
    for i, (row, b) in enumerate(zip(out, blocks, strict=True)):
        words = b.text.split(" ")
        n = len(words)
        link = min(1.0, b.linked / max(1, len(b.text)))
        if not blotted:
            row[1], row[2] = b.element.landmark > 0, b.element.landmark < 0
            row[3], row[4] = b.element.names > 0, b.element.names < 0
        row[0] = 1
        row[5] = link
        row[6] = min(1.0, np.log1p(n) / 5) * (1 - link)
        row[7] = b.tag == "p"
        row[8] = b.tag in ("h1", "h2", "h3", "h4", "h5", "h6", "blockquote", "pre")
        row[9] = b.text[-1] in ".!?…:\"”»"
        row[10] = b.tag in ("li", "td", "th", "dt", "dd", "label", "caption")
        row[11] = min(1.0, 3 * len(b.text) / total)
        row[12] = bool(_NOTICE.search(b.text)) and n < 40
        row[13] = n < 4
        row[14] = i / len(blocks)
        row[15] = b.element.header
    return out


@dataclass
class Cutter:
    """Weights of features, and of the kinds of edges."""

    weights: np.ndarray
    edges: np.ndarray

    def gains(self, blocks: list[Block], blotted: bool = False) -> np.ndarray:
        return np.clip(features_of(blocks, blotted) @ self.weights, -30, 30)

    def content(self, blocks: list[Block], blotted: bool = False) -> np.ndarray:
        edges = [(i, j, self.edges[k]) for i, j, k in edges_of(blocks, blotted) if self.edges[k] > 0]
        return minimum_cut(self.gains(blocks, blotted), edges)


@dataclass
class Example:
    """A page to learn from: 1 content, 0 boilerplate, -1 unknown."""

    blocks: list[Block]
    labels: np.ndarray
    blotted: bool
    weight: float


def examples_of(pages: list[str]) -> list[Example]:
    """The hand-labelled pages, each seen with its landmarks and without, and the landmark blocks of ``pages``."""
    found = []
    for page in html_seeds.PAGES:
        blocks = blocks_of(page)
        labels = np.array([b.text.startswith(html_seeds.MARK) for b in blocks], np.int64)
        for b in blocks:
            b.text = b.text.removeprefix(html_seeds.MARK)
        found += [Example(blocks, labels, blotted, share * SEED_SHARE / len(html_seeds.PAGES)) for blotted, share in ((False, 0.6), (True, 0.4))]
    for k, page in enumerate(pages):
        blocks = blocks_of(page)
        said = np.array([b.element.landmark if b.element.names >= 0 else -1 for b in blocks])
        if len(blocks) and said.any():
            found.append(Example(blocks, np.where(said == 0, -1, said > 0), k % 3 == 1, (1 - SEED_SHARE) / len(pages)))
    return found


def train(pages: list[str], ridge: float = 2e-4) -> Cutter:
    examples = examples_of(pages)
    known = [e.labels >= 0 for e in examples]
    x = np.concatenate([features_of(e.blocks, e.blotted)[k] for e, k in zip(examples, known, strict=True)])
    y = np.concatenate([e.labels[k] for e, k in zip(examples, known, strict=True)]).astype(np.float64)
    w = np.concatenate([np.full(k.sum(), e.weight / k.sum()) for e, k in zip(examples, known, strict=True)])
    for c in (0, 1):  # both kinds of blocks weigh the same
        w[y == c] *= 0.5 / w[y == c].sum()
    weights = np.zeros(N_FEATURES)
    for _ in range(30):  # Newton's method
        p = 1 / (1 + np.exp(-np.clip(x @ weights, -30, 30)))
        curve = (x * (w * p * (1 - p))[:, None]).T @ x + ridge * np.eye(N_FEATURES)
        step = np.linalg.solve(curve, x.T @ (w * (y - p)) - ridge * weights)
        weights = weights + step / max(1.0, np.abs(step).max() / 2)
    return Cutter(weights, _edge_weights(examples, weights))


def _edge_weights(examples: list[Example], weights: np.ndarray, rounds: int = 400, ridge: float = 5e-3) -> np.ndarray:
    sides, offsets, labels, each = [], [], [], []
    for e in examples:
        sign = np.where(e.labels < 0, 0, 2 * e.labels - 1)
        side = np.zeros((len(e.blocks), EDGE_KINDS))
        for i, j, k in edges_of(e.blocks, e.blotted):
            side[i, k] += sign[j]
            side[j, k] += sign[i]
        known = sign != 0
        sides.append(side[known])
        offsets.append(np.clip(features_of(e.blocks, e.blotted) @ weights, -30, 30)[known])
        labels.append(e.labels[known])
        each.append(np.full(known.sum(), e.weight / max(1, known.sum())))
    side, offset, y, w = np.concatenate(sides), np.concatenate(offsets), np.concatenate(labels), np.concatenate(each)
    w = w / w.sum()
    found = np.zeros(EDGE_KINDS)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(offset + side @ found, -30, 30)))
        found = np.maximum(0.0, found + 0.5 * (side.T @ (w * (y - p)) - ridge * found))
    return found


#: Kinds of edges: neighbours in the page by steps in the tree (0 for siblings, 3 for 3 and more), next siblings' children, across a landmark or name.
EDGE_KINDS = 6
_UNDER_SIBLINGS, _ACROSS = 4, 5


def edges_of(blocks: list[Block], blotted: bool = False) -> list[tuple[int, int, int]]:
    """Neighbours in the page, and next ones under one grandparent, with their kinds."""
    edges = []
    last: dict[int, int] = {}
    for i, block in enumerate(blocks):
        here = block.element
        if i:
            before = blocks[i - 1].element
            across = not blotted and (before.landmark, before.names) != (here.landmark, here.names)
            edges.append((i - 1, i, _ACROSS if across else min(3, tree_distance(before, here))))
        parent = id(here.parent)
        j = last.get(parent)
        if j is not None and j != i - 1:
            before = blocks[j].element
            across = not blotted and (before.landmark, before.names) != (here.landmark, here.names)
            edges.append((j, i, _ACROSS if across else _UNDER_SIBLINGS))
        last[parent] = i
    return edges


def tree_distance(a: Element, b: Element) -> int:
    """Steps from the nearer of two elements up to their common ancestor, beyond the first."""
    up_a = up_b = 0
    while a is not b:
        if a.depth >= b.depth and a.parent is not None:
            a, up_a = a.parent, up_a + 1
        elif b.parent is not None:
            b, up_b = b.parent, up_b + 1
        else:
            break
    return max(0, max(up_a, up_b) - 1)


def minimum_cut(gain: np.ndarray, edges: list[tuple[int, int, float]]) -> np.ndarray:
    """Labels that maximise the sum of ``gain`` over content less the weights of edges between unlike ends."""
    n = len(gain)
    gain = gain.astype(np.float64).copy()
    around: list[dict[int, float]] = [{} for _ in range(n)]
    for i, j, w in edges:
        around[i][j] = around[i].get(j, 0.0) + w
        around[j][i] = around[j].get(i, 0.0) + w
    label = np.full(n, -1, np.int8)
    waiting = deque(range(n))
    while waiting:
        i = waiting.popleft()
        if label[i] < 0 and abs(gain[i]) >= sum(around[i].values()):
            label[i] = gain[i] > 0
            for j, w in around[i].items():
                del around[j][i]
                gain[j] += w if label[i] else -w
                waiting.append(j)
            around[i] = {}
    open_ = np.flatnonzero(label < 0)
    if len(open_):
        label[open_] = _max_flow(open_, gain, around)
    return label == 1


def _max_flow(open_: np.ndarray, gain: np.ndarray, around: list[dict[int, float]]) -> np.ndarray:
    """Edmonds and Karp on the undecided vertices; what the source still reaches is content."""
    number = {int(v): k for k, v in enumerate(open_)}
    n = len(open_)
    source, sink = n, n + 1
    room: list[dict[int, float]] = [{} for _ in range(n + 2)]
    for v, k in number.items():
        for j, w in around[v].items():
            room[k][number[j]] = w
        if gain[v] > 0:
            room[source][k], room[k][source] = gain[v], 0.0
        else:
            room[k][sink], room[sink][k] = -gain[v], 0.0
    while True:
        before = {source: source}
        queue = deque([source])
        while queue and sink not in before:
            u = queue.popleft()
            for v, r in room[u].items():
                if r > 1e-12 and v not in before:
                    before[v] = u
                    queue.append(v)
        if sink not in before:
            return np.array([k in before for k in range(n)])
        path, v = [], sink
        while v != source:
            path.append((before[v], v))
            v = before[v]
        flow = min(room[u][v] for u, v in path)
        for u, v in path:
            room[u][v] -= flow
            room[v][u] = room[v].get(u, 0.0) + flow


def main_text(page: str, cutter: Cutter) -> str:
    blocks = blocks_of(page)
    if not blocks:
        return ""
    return "\n".join(b.text for b, keep in zip(blocks, cutter.content(blocks), strict=True) if keep)


def fit(pages: DataFrame) -> Cutter:
    """The capacities, from at most ``TRAINING_PAGES`` pages."""
    ids = pages.select("page_id").where(F.col("page_id").isNotNull()).distinct().orderBy(F.xxhash64("page_id"), "page_id").limit(TRAINING_PAGES)
    rows = pages.join(F.broadcast(ids), "page_id").groupBy("page_id").agg(F.min(F.coalesce("html", F.lit(""))).alias("html")).collect()
    return train([r.html for r in sorted(rows, key=lambda r: r.page_id)])


def extract(pages: DataFrame, cutter: Cutter) -> DataFrame:
    """page_id, url, text, n_chars."""

    @F.pandas_udf("string")
    def extracted(parts: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for part in parts:
            yield pd.Series([main_text(page or "", cutter) for page in part], dtype=object)

    found = pages.select("page_id", "url", extracted("html").alias("text"))
    return found.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"))
