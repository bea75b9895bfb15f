"""Main text of HTML pages by minimum cut.

A page becomes text blocks (runs of text between block-level tags).  A logistic classifier
gives each block a cost for either label from its own text (length, sentences, link share); these costs, at most ``MOST_OWN``, are the capacities to the two terminals.  DOM edges tie a block to the
elements it stands in: one that its tag, class or role settles (article, nav, advert) counts as
merged with its terminal, so its ties are terminal capacities too.  Smoothness edges join
neighbouring blocks, the stronger the more ancestors they share, and blocks under one parent.  The minimum cut separates content
from boilerplate; content blocks are joined in page order.

The classifier's weights are learned from blocks of at most ``SAMPLE_PAGES`` pages (those of least hash) that have an article or
main element: blocks inside it are content, the others are not.  They are drawn towards ``PRIOR``, which also holds where no page
has such an element.

Every page gives one row.  Null or empty html, and pages without content, give the empty
text.  Unclosed, stray or cut-off markup is read the way browsers recover from it; extra
columns are not carried; repeated page ids are kept as they are.  Time grows in proportion to a page, also for deep or unclosed markup.
"""

from __future__ import annotations

import html
import math
import re
from collections import Counter, deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from tolerant_gd.llm.store import modest_batches

# Element names of HTML by what they do to text.
BLOCK_TAGS = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 header hgroup hr html legend li main menu nav ol optgroup option p pre search section summary table tbody td tfoot th thead tr ul".split())
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW_TAGS = frozenset("script style textarea title noscript iframe xmp noembed noframes template svg math object select button datalist".split())
P_ENDERS = BLOCK_TAGS - {"body", "html", "option", "optgroup", "td", "th", "tr", "tbody", "thead", "tfoot", "caption"}
NEVER = frozenset("nav aside footer form head menu dialog search fieldset".split())
# Words in class, id and role attributes that tell what an element is.
NEVER_WORDS = frozenset("ad ads advert advertisement adverts advertising banner sponsor sponsored promo menu nav navbar navigation breadcrumb breadcrumbs sidebar footer cookie cookies consent notice alert popup modal newsletter subscribe signup login share sharing social related recommended recommendations comments comment comment-list disqus replies reply copyright contentinfo complementary toolbar pagination pager search masthead site-header page-header hidden visually-hidden sr-only skip-link".split())
DOUBT_WORDS = frozenset("ad ads advert sponsor promo menu nav sidebar side widget foot footer header top cookie consent notice alert popup modal newsletter subscribe share social related comment comments reply copyright legal tags meta byline toolbar pager hidden skip".split())
# Words that condemn an element even as a part of a name (user-comments, ad_top), unless an article begins inside it.
PART_WORDS = frozenset("ad ads advert adverts advertisement banner sponsor sponsored promo menu nav navbar navigation breadcrumb breadcrumbs sidebar footer cookie cookies consent notice newsletter subscribe signup share sharing social related recommended comment comments replies reply disqus toolbar pagination pager widget popup modal".split())
TALK_WORDS = frozenset("comment comments reply replies disqus".split())
GOOD_WORDS = frozenset("article content post entry story main text body page".split())
LAYOUT_WORDS = frozenset("has with no without layout wrapper container page body col row grid".split())
GOOD_TAGS = frozenset(["article", "main"])

_MARKUP = re.compile(r"""<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:[^>"']++|"[^"]*+"|'[^']*+')*+|[^>]*+)>|<[!?/][^>]*+>?|<[a-zA-Z][^>]*+\Z""", re.S)
_ATTRIBUTE = re.compile(r"""(?:^|[\s"'/])(class|id|role|hidden|aria-hidden|style)(?:\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+)))?""", re.I)
_SENTENCE = re.compile(r"[.!?…。](?:\s|$)|,\s")
_HIDING = re.compile(r"display\s*:\s*none|visibility\s*:\s*hidden", re.I)

#: Weights of smoothness edges, of ties to elements that are settled, and the most that a block's own text may say.
SMOOTH_NEXT, SMOOTH_PARENT = 1.5, 0.75
TIE_NEVER, TIE_MAIN, TIE_PART, MOST_OWN = -60.0, 8.0, -14.0, 4.0
TIE_TAG = {"p": 1.0, "h1": 1.0, "h2": 0.6, "h3": 0.4, "blockquote": 0.8, "pre": 0.8, "li": -0.3, "td": -0.3, "th": -0.3}
#: Odds beyond which a block is a seed: no sum of what else speaks of it comes near.
SEED = 30.0
#: Before anything is learned: bias, length, sentences, link share.
PRIOR = (-1.0, 1.0, 1.0, -4.0)
#: Pages that the classifier learns from at most, and how firmly it is drawn to PRIOR (as so many blocks).
SAMPLE_PAGES, PRIOR_BLOCKS = 400, 50.0
#: Components of the graph of more blocks than this are thinned, block by block, before the flow.
THIN_FROM = 200


class Element:
    __slots__ = ("depth", "good", "id", "never", "odds", "parent", "part", "tag", "talk")

    def __init__(self, tag: str, attributes: str, parent: Element | None, number: int):
        self.tag, self.parent, self.id = tag, parent, number
        self.depth = parent.depth + 1 if parent else 0
        self.never = parent.never if parent else False
        self.odds = parent.odds if parent else 0.0
        self.good = parent.good if parent else False
        self.part = parent.part if parent else False  # below an element condemned by a part of its name
        self.talk = parent.talk if parent else False  # and that part speaks of readers
        if tag in NEVER:
            self.never = True
        elif tag == "header":
            self.never = self.never or not self.good
        elif tag in GOOD_TAGS:
            self.good = True
            self.part = self.talk
        if attributes and tag not in ("html", "body"):
            self._cues(attributes)

    def _cues(self, attributes: str) -> None:
        for name, a, b, c in _ATTRIBUTE.findall(attributes):
            name, value = name.lower(), (a or b or c).lower()
            if name == "hidden" or name == "aria-hidden" and value == "true" or name == "style" and _HIDING.search(value):
                self.never = True
            elif name in ("class", "id", "role"):
                whole = value.split()
                if any(w in NEVER_WORDS for w in whole):
                    self.never = True
                parts = {p for w in whole for p in re.split(r"[-_]+", w)}
                if len(parts) > len(whole) or len(whole) > 1:
                    self.part = self.part or bool(parts & PART_WORDS and not parts & LAYOUT_WORDS)
                    self.talk = self.talk or bool(parts & TALK_WORDS)
                if parts & GOOD_WORDS:
                    self.odds = 2.0
                elif parts & DOUBT_WORDS:
                    self.odds = -3.0


class Block:
    __slots__ = ("element", "link", "text")

    def __init__(self, text: str, link: int, element: Element):
        self.text, self.link, self.element = text, link, element


def blocks(page: str) -> list[Block]:
    """Text blocks in page order, with white space collapsed and character references decoded."""
    top = Element("#", "", None, 0)
    stack, number, out = [top], 1, []
    opened: Counter[str] = Counter()  # of the stack's tags
    pieces: list[str] = []
    linked = links = 0
    holder = top

    def cut(i: int) -> None:
        for e in stack[i:]:
            opened[e.tag] -= 1
        del stack[i:]

    def flush() -> None:
        nonlocal linked, pieces
        if pieces:
            text = " ".join(html.unescape("".join(pieces)).split())
            if text:
                out.append(Block(text, linked, holder))
            pieces = []
        linked = 0

    at, n = 0, len(page)
    while at < n:
        m = _MARKUP.search(page, at)
        end = m.start() if m else n
        if end > at:
            if not pieces:
                holder = stack[-1]
            pieces.append(page[at:end])
            if links:
                linked += end - at
        if not m:
            break
        at = m.end()
        name = m.group(2)
        if name is None:
            continue
        name, closing = name.lower(), m.group(1)
        if name in RAW_TAGS and not closing:
            if not m.group(3).endswith("/") or name not in ("svg", "math", "object"):
                tail = re.compile(f"</{re.escape(name)}[^>]*>?", re.I).search(page, at)
                at = tail.end() if tail else n
            pieces.append(" ")
        elif name == "br" or name in VOID_TAGS and name != "hr":
            if pieces:
                pieces.append(" " if name == "br" else "")
        elif closing:
            if name in BLOCK_TAGS:
                flush()
            if name == "a":
                links = max(0, links - 1)
            for i in range(len(stack) - 1, 0, -1) if opened[name] else ():
                if stack[i].tag == name:
                    cut(i)
                    break
                if name not in BLOCK_TAGS and stack[i].tag in BLOCK_TAGS:
                    break  # a stray inline end tag closes nothing beyond its block
            if name in BLOCK_TAGS:
                links = opened["a"]
        else:
            if name in BLOCK_TAGS:
                flush()
                if name in P_ENDERS and opened["p"]:
                    cut(next(i for i in range(len(stack) - 1, 0, -1) if stack[i].tag == "p"))
                if name in KIN and any(opened[k] for k in KIN[name]):
                    cut(_implied_end(stack, name))
                if name == "hr":
                    continue
            if name == "a":
                links = 1
            stack.append(Element(name, m.group(3), stack[-1], number))
            opened[name] += 1
            number += 1
    flush()
    return out


KIN = {"li": ("li",), "option": ("option",), "dt": ("dt", "dd"), "dd": ("dt", "dd"), "td": ("td", "th"), "th": ("td", "th"), "tr": ("tr",)}


def _implied_end(stack: list[Element], name: str) -> int:
    """Where the stack ends when an item ends an open one of its kind that belongs to the same list or table."""
    walls = ("ul", "ol", "dl", "table", "menu", "select", "#") + (("tr",) if name in ("td", "th") else ())
    for i in range(len(stack) - 1, 0, -1):
        if stack[i].tag in KIN[name]:
            return i
        if stack[i].tag in walls:
            break
    return len(stack)


def _block_tag(e: Element | None) -> str:
    for _ in range(64):
        if not e or e.tag in BLOCK_TAGS:
            break
        e = e.parent
    return e.tag if e else ""


def clues(b: Block) -> tuple[float, ...]:
    """What the classifier sees of a block: its own text, nothing of the elements it stands in."""
    size = len(b.text)
    return (1.0, min(size, 400) / 150, min(len(_SENTENCE.findall(b.text)), 6) * 0.25, min(1.0, b.link / max(1, size)))


def own_odds(found: list[Block], weights: tuple[float, ...]) -> list[float]:
    """Log-odds that a block is content by its own text."""
    return [max(-MOST_OWN, min(MOST_OWN, sum(w * x for w, x in zip(weights, clues(b), strict=True)))) for b in found]


def ties(found: list[Block]) -> list[float]:
    """Capacity of the edges to the elements a block stands in: positive to content, negative to boilerplate."""
    has_main = any(b.element.good and not b.element.never for b in found)
    out = []
    for b in found:
        e = b.element
        main = TIE_MAIN if e.good else -TIE_MAIN if has_main else 0.0
        out.append(TIE_NEVER if e.never else main + e.odds + TIE_TAG.get(_block_tag(e), 0.0) + (TIE_PART if e.part else 0.0))
    return out


def learn(pages: list[str]) -> tuple[float, ...]:
    """Classifier weights from the blocks of pages whose markup names the content; logistic, drawn towards PRIOR."""
    rows, marks = [], []
    for page in pages:
        found = blocks(page)
        if any(b.element.good and not b.element.never for b in found):
            rows += [clues(b) for b in found]
            marks += [b.element.good and not b.element.never and not b.element.part for b in found]
    prior = np.array(PRIOR)
    if not rows or all(marks) or not any(marks):
        return PRIOR
    x, y, w = np.array(rows), np.array(marks, float), prior.copy()
    pull = PRIOR_BLOCKS * np.eye(len(w)) / 4
    for _ in range(30):  # Newton steps
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve(x.T @ (x * (p * (1 - p))[:, None]) + pull, x.T @ (y - p) - pull @ (w - prior))
        w = w + step
        if np.abs(step).max() < 1e-9:
            break
    return tuple(float(v) for v in w)


class Cut:
    """Minimum cut by shortest augmenting paths (level graph and blocking flow)."""

    def __init__(self, n: int):
        self.n, self.to, self.room, self.out = n, [], [], [[] for _ in range(n)]

    def edge(self, a: int, b: int, there: float, back: float) -> None:
        self.out[a].append(len(self.to))
        self.to.append(b)
        self.room.append(there)
        self.out[b].append(len(self.to))
        self.to.append(a)
        self.room.append(back)

    def source_side(self, s: int, t: int) -> list[bool]:
        while True:
            level, queue = [-1] * self.n, deque([s])
            level[s] = 0
            while queue:
                a = queue.popleft()
                for e in self.out[a]:
                    if self.room[e] > 1e-9 and level[self.to[e]] < 0:
                        level[self.to[e]] = level[a] + 1
                        queue.append(self.to[e])
            if level[t] < 0:
                return [x >= 0 for x in level]
            nexts, path, a = [0] * self.n, [], s
            while True:
                if a == t:
                    least = min(self.room[e] for e in path)
                    for e in path:
                        self.room[e] -= least
                        self.room[e ^ 1] += least
                    path, a = [], s
                    continue
                while nexts[a] < len(self.out[a]):
                    e = self.out[a][nexts[a]]
                    if self.room[e] > 1e-9 and level[self.to[e]] == level[a] + 1:
                        break
                    nexts[a] += 1
                else:
                    if a == s:
                        break
                    level[a] = -1
                    a = self.to[path.pop() ^ 1]
                    continue
                path.append(e)
                a = self.to[e]


def smoothness(found: list[Block]) -> list[tuple[int, int, float]]:
    """Edges between neighbours, and between successive blocks under one parent."""
    edges, last = [], {}
    for i, b in enumerate(found):
        if i:
            x, y = found[i - 1].element, b.element
            deep = max(x.depth, y.depth, 1)
            while x is not y:
                if x.depth >= y.depth:
                    x = x.parent
                else:
                    y = y.parent
            edges.append((i - 1, i, SMOOTH_NEXT * (x.depth + 1) / (deep + 1)))
        parent = b.element.parent.id if b.element.parent else 0
        if (j := last.get(parent)) is not None:
            edges.append((j, i, SMOOTH_PARENT))
        last[parent] = i
    return edges


def label(odds: list[float], edges: list[tuple[int, int, float]]) -> list[bool]:
    """The labelling of least cost: True is content.

    Seeds, whose odds outweigh all their edges by far, keep their own label in every minimum cut; the others enter the graph.
    """
    weight = [0.0] * len(odds)
    for a, b, w in edges:
        weight[a] += w
        weight[b] += w
    fixed = [abs(o) > max(w, SEED) for o, w in zip(odds, weight, strict=True)]
    open_ = [i for i, f in enumerate(fixed) if not f]
    answer = [o > 0 for o in odds]
    if not open_:
        return answer
    near: dict[int, list[tuple[int, float]]] = {i: [] for i in open_}
    pull = dict(zip(open_, [odds[i] for i in open_], strict=True))
    for a, b, w in edges:
        for i, k in ((a, b), (b, a)):
            if i in near:
                if k in near:
                    near[i].append((k, w))
                else:
                    pull[i] += w if answer[k] else -w
    for group in _groups(near):
        if len(group) > THIN_FROM:
            group = _thinned(group, near, pull, answer)
        if group:
            _flow(group, near, pull, answer)
    return answer


def _groups(near: dict[int, list[tuple[int, float]]]) -> Iterator[list[int]]:
    """Connected components of the open blocks."""
    seen: set[int] = set()
    for first in near:
        if first not in seen:
            seen.add(first)
            group = [first]
            for i in group:
                for k, _ in near[i]:
                    if k not in seen:
                        seen.add(k)
                        group.append(k)
            yield group


def _thinned(group: list[int], near: dict[int, list[tuple[int, float]]], pull: dict[int, float], answer: list[bool]) -> list[int]:
    """Settle blocks whose pull outweighs their edges to blocks not yet settled, until none is left that does."""
    weight = {i: sum(w for _, w in near[i]) for i in group}
    todo, done = deque(group), set()
    while todo:
        i = todo.popleft()
        if i in done or abs(pull[i]) <= weight[i]:
            continue
        done.add(i)
        answer[i] = pull[i] > 0
        for k, w in near[i]:
            if k not in done:
                pull[k] += w if answer[i] else -w
                weight[k] -= w
                todo.append(k)
    left = [i for i in group if i not in done]
    for i in left:
        near[i] = [(k, w) for k, w in near[i] if k not in done]
    return left


def _flow(group: list[int], near: dict[int, list[tuple[int, float]]], pull: dict[int, float], answer: list[bool]) -> None:
    spot, n = {i: k for k, i in enumerate(group)}, len(group)
    cut = Cut(n + 2)
    for i, k in spot.items():
        for other, w in near[i]:
            if i < other:
                cut.edge(k, spot[other], w, w)
        if pull[i] > 0:
            cut.edge(n, k, pull[i], 0.0)
        elif pull[i] < 0:
            cut.edge(k, n + 1, -pull[i], 0.0)
    side = cut.source_side(n, n + 1)
    for i, k in spot.items():
        answer[i] = side[k]


def main_text(page: str | None, weights: tuple[float, ...] = PRIOR) -> str:
    found = blocks(page or "")
    if not found:
        return ""
    odds = [a + b for a, b in zip(own_odds(found, weights), ties(found), strict=True)]
    if not all(math.isfinite(o) for o in odds):
        raise ValueError("odds must be finite")
    return "\n".join([b.text for b, keep in zip(found, label(odds, smoothness(found)), strict=True) if keep])


def share_of_cut(pages: list[str], weights: tuple[float, ...] = PRIOR) -> tuple[int, int, int]:
    """(blocks, blocks that enter the graph, labels that differ from what the block's own text says)."""
    total = inside = changed = 0
    for page in pages:
        found = blocks(page or "")
        own, edges = own_odds(found, weights), smoothness(found)
        odds = [a + b for a, b in zip(own, ties(found), strict=True)]
        weight = [0.0] * len(found)
        for a, b, w in edges:
            weight[a] += w
            weight[b] += w
        total += len(found)
        inside += sum(abs(o) <= max(w, SEED) for o, w in zip(odds, weight, strict=True))
        changed += sum((o > 0) != keep for o, keep in zip(own, label(odds, edges), strict=True))
    return total, inside, changed


def fit(pages: DataFrame, sample_pages: int = SAMPLE_PAGES) -> tuple[float, ...]:
    """Weights learned from at most ``sample_pages`` pages with an article or main element, those of least hash."""
    rows = pages.select(F.col("html").cast("string").alias("html"))
    named = rows.where(F.col("html").rlike("(?i)<(?:article|main)[\\s>]"))
    least = named.select(F.xxhash64("html").alias("h")).distinct().orderBy("h").limit(sample_pages)  # keys only
    some = named.select("html", F.xxhash64("html").alias("h")).join(F.broadcast(least), "h", "left_semi")
    return learn(sorted(r["html"] for r in some.groupBy("h").agg(F.first("html").alias("html")).collect()))


def extract(pages: DataFrame, weights: tuple[float, ...] | None = None) -> DataFrame:
    """Per page: page_id, url, text, n_chars; ``weights`` are learned from the pages where none are given."""
    modest_batches(pages.sparkSession)
    held = fit(pages) if weights is None else weights

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = [main_text(x.as_py(), held) for x in batch.column(2)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string")).mapInArrow(run, "page_id long, url string, text string, n_chars long")
