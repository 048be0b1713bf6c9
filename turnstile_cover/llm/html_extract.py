"""Main-text extraction: a linear-chain conditional random field over a page's leaf blocks.

A page becomes a list of leaf blocks (runs of text between block-level tags) with the tags and
class words of their ancestors. Features of ancestors and of the text score each block, and
Viterbi picks the best sequence of labels (main text or not). The field is trained on labelled
pages; where no labels are given, pages that mark their article by an element label themselves,
and half of the training pages hide that mark, so pages without one are decoded by the rest.
"""

from __future__ import annotations

import html as htmllib
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(?:![^>]*|\?[^>]*)>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^>\"']|\"[^\"]*\"|'[^']*')*+)>|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)([^>]*)>", re.S)
UNCLOSED = re.compile(r"<!--.*", re.S)
ATTRIBUTE = re.compile(r"(?:class|id|role|itemprop|aria-label)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>\"']+))", re.I)
WORDS = re.compile(r"[A-Za-z]+")
#: HTML's block-level elements, elements without content, and raw-text elements.
BLOCK = frozenset("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead title tr ul button label textarea".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = frozenset("script style noscript template svg math iframe object canvas".split())
#: Elements and class words that usually hold anything but the article.
ASIDE_TAGS = frozenset("nav footer aside form head title button label select option textarea menu dialog fieldset".split())
ASIDE_WORDS = frozenset("ad ads advert advertisement adverts banner breadcrumb breadcrumbs comment comments consent cookie cookies disqus discussion footer form gdpr login masthead menu modal nav navbar navigation newsletter notice notices pager pagination popup promo promoted promotion recommended related replies reply respond share sharing sidebar signup social sponsor sponsored subscribe toolbar topbar widget".split())
MAIN_TAGS = frozenset(("article", "main"))
MAIN_WORDS = frozenset("article articlebody entry main post story".split())
FEATURES = 1 << 12


class Node:
    """An open element of a page: its tag, class words and the element around it. Blocks share nodes, so depth costs no copies."""

    __slots__ = ("up", "tag", "words", "state")

    def __init__(self, up: Node | None, tag: str, words: frozenset[str] = frozenset()):
        self.up, self.tag, self.words = up, tag, words
        self.state: tuple[int, int, bool, int] | None = None


def chain(node: Node | None, most: int | None = None) -> list[Node]:
    """Ancestors from the root, the node included; the first ones only with most."""
    out = []
    while node is not None:
        out.append(node)
        node = node.up
    return out[::-1][:most]


@dataclass
class Block:
    text: str
    path: Node | None
    linked: int


def blocks_of(page: str) -> list[Block]:
    """Leaf blocks in page order; broken markup closes at the next block-level tag."""
    out: list[Block] = []
    stack: list[Node] = []
    open_: Counter[str] = Counter()
    parts: list[str] = []
    path: Node | None = None
    seen = False
    linked = at = 0
    none: frozenset[str] = frozenset()

    def text(piece: str) -> None:
        nonlocal path, linked, seen
        if not piece:
            return
        if not seen and not piece.isspace():
            path, seen = stack[-1] if stack else None, True
        parts.append(piece)
        if open_["a"]:
            linked += len(piece.strip())

    def close() -> None:
        nonlocal path, linked, seen
        if seen:
            joined = "".join(parts)
            words = " ".join((htmllib.unescape(joined) if "&" in joined else joined).split())
            if words:
                out.append(Block(words, path, linked))
        parts.clear()
        path, linked, seen = None, 0, False

    def shut(k: int) -> None:
        for x in stack[k:]:
            open_[x.tag] -= 1
        del stack[k:]

    n, last = len(page), page.rfind(">")
    while at < n:
        # no tag ends after the last ">", but a comment that never closes hides the rest
        m = TAG.search(page, at) if at <= last else UNCLOSED.search(page, at)
        if not m:
            text(page[at:])
            break
        text(page[at : m.start()])
        at = m.end()
        name = (m[2] or m[5]) if m.re is TAG else None
        if not name:
            continue
        name, ending, rest = name.lower(), m[1] or m[4], m[3] or m[6] or ""
        if ending:
            if name in BLOCK:
                close()
            if open_[name] > 0:
                shut(next(k for k in range(len(stack) - 1, -1, -1) if stack[k].tag == name))
            continue
        if name in RAW:
            if not rest.endswith("/"):
                end = re.compile(rf"</{name}\s*>", re.I).search(page, at)
                at = end.end() if end else n
            continue
        if name == "br":
            text(" ")
        if name in BLOCK:
            close()
            repeats = name in ("li", "td", "th", "tr", "dt", "dd", "option") and open_[name] > 0
            if name != "title" and (open_["p"] > 0 or repeats):
                for k in range(len(stack) - 1, -1, -1):
                    if stack[k].tag == "p" or repeats and stack[k].tag == name:
                        shut(k)
                        break
                    if stack[k].tag in BLOCK:
                        break
            if name == "body" and open_["head"] > 0:
                shut(next(k for k, x in enumerate(stack) if x.tag == "head"))
        if name in VOID or rest.endswith("/"):
            continue
        words = frozenset(w.lower() for a in ATTRIBUTE.findall(rest) for w in WORDS.findall("".join(a))) if "=" in rest else none
        stack.append(Node(stack[-1] if stack else None, name, words))
        open_[name] += 1
    close()
    return out


@lru_cache(50_000)
def bucket(name: str) -> int:
    return zlib.crc32(name.encode()) % FEATURES


@lru_cache(50_000)
def element(tag: str, words: frozenset[str]) -> tuple[bool, bool, int]:
    """Does the element mark the article, does it set its content apart, and its features as bits of an integer."""
    main = tag in MAIN_TAGS or bool(words & MAIN_WORDS) and not words & ASIDE_WORDS
    names = [f"up:{tag}", *(f"word:{w}" for w in words), *(["in:main"] if main else [])]
    return main, tag in ASIDE_TAGS or bool(words & ASIDE_WORDS), sum({1 << bucket(x) for x in names})


def state_of(node: Node | None) -> tuple[int, int, bool, int]:
    """Of a node and all around it: features, features with the article's mark hidden, inside an article, and the page's own
    label: 0 outside, 1 inside, 2 inside something set apart. Worked out once a node, from the root down."""
    todo = []
    while node is not None and node.state is None:
        todo.append(node)
        node = node.up
    shown, hidden, inside, label = node.state if node is not None else (0, 0, False, 0)
    for x in reversed(todo):
        main, aside, bits = element(x.tag, x.words)
        inside = inside or main
        if aside or x.tag == "header" and not inside:
            bits |= 1 << bucket("in:aside")
        shown |= bits
        hidden |= 0 if main else bits
        label = 2 if label == 2 or aside and not main else 1 if main else label
        x.state = (shown, hidden, inside, label)
    return shown, hidden, inside, label


@dataclass
class Features:
    sets: dict[int, list[int]] = field(default_factory=dict)

    def listed(self, bits: int) -> list[int]:
        """Places of an integer's bits."""
        have = self.sets.get(bits)
        if have is None:
            if len(self.sets) > 2_000:
                self.sets.clear()
            have = self.sets[bits] = [i for i, c in enumerate(reversed(bin(bits)[2:])) if c == "1"]
        return have

    def ancestors(self, path: Node | None, hide: bool) -> list[int]:
        return [*self.listed(state_of(path)[hide]), bucket(f"leaf:{path.tag if path else ''}")]

    def vector(self, b: Block, hide: bool = False) -> list[int]:
        t = b.text
        n = len(t)
        ends = t[-1] in ".!?:;\"'»)"
        link = b.linked * 4 // max(1, n)
        return [*self.ancestors(b.path, hide), bucket("bias"), bucket(f"len:{n.bit_length()}"), bucket(f"link:{min(4, link)}"), bucket(f"end:{ends}"), bucket(f"stop:{min(3, t.count('. '))}"), bucket(f"copy:{'©' in t}")]


@dataclass
class Field:
    """Weights: emit[feature, label] and move[label before, label]."""

    emit: np.ndarray
    move: np.ndarray

    def scores(self, vectors: list[list[int]]) -> np.ndarray:
        return np.array([self.emit[v].sum(0) for v in vectors])

    def decode(self, scores: np.ndarray) -> list[int]:
        """Viterbi."""
        move = self.move.tolist()
        best, back = scores[0].tolist(), []
        for e in scores[1:].tolist():
            via = [0 if best[0] + move[0][y] >= best[1] + move[1][y] else 1 for y in (0, 1)]
            best = [best[via[y]] + move[via[y]][y] + e[y] for y in (0, 1)]
            back.append(via)
        y = 0 if best[0] >= best[1] else 1
        out = [y]
        for via in reversed(back):
            y = via[y]
            out.append(y)
        return out[::-1]


def gradient(field_: Field, vectors: list[list[int]], labels: list[int]) -> tuple[np.ndarray, np.ndarray]:
    """Expected minus observed label counts: for each block and for each move (forward-backward in log space)."""
    e, n = field_.scores(vectors), len(vectors)
    ahead, behind = np.zeros((n, 2)), np.zeros((n, 2))
    ahead[0] = e[0]
    for t in range(1, n):
        ahead[t] = e[t] + np.logaddexp(ahead[t - 1, 0] + field_.move[0], ahead[t - 1, 1] + field_.move[1])
    for t in range(n - 2, -1, -1):
        x = field_.move + (e[t + 1] + behind[t + 1])
        behind[t] = np.logaddexp(x[:, 0], x[:, 1])
    total = np.logaddexp(*ahead[-1])
    single = np.exp(ahead + behind - total)
    single[np.arange(n), labels] -= 1
    pair = np.zeros((2, 2))
    for t in range(1, n):
        pair += np.exp(ahead[t - 1][:, None] + field_.move + (e[t] + behind[t]) - total)
        pair[labels[t - 1], labels[t]] -= 1
    return single, pair


def marked(b: Block) -> int:
    """A page's own label of a block: inside the element that marks the article and nothing that sets it apart."""
    return int(state_of(b.path)[3] == 1)


def with_moved(blocks: list[Block], labels: list[int]) -> tuple[list[Block], list[int]]:
    """The page with its first article block copied into a page header and its last ones into reader comments."""
    top = None
    for x in chain(blocks[0].path, 2):
        top = Node(top, x.tag, x.words)
    header, comments = Node(top, "header"), Node(top, "div", frozenset(["comments"]))
    below = lambda up, b: Block(b.text, Node(up, b.path.tag, b.path.words), 0)
    main = [b for b, y in zip(blocks, labels, strict=True) if y]
    head, tail = [below(header, b) for b in main[:1]], [below(comments, b) for b in main[-2:]]
    return [*head, *blocks, *tail], [0] * len(head) + labels + [0] * len(tail)


def train(pages: list[tuple[list[Block], list[int]]], epochs: int = 5, rate: float = 0.3, l2: float = 1e-4) -> Field:
    """Adaptive stochastic gradient over pages, each also with its article mark hidden."""
    f, features = Field(np.zeros((FEATURES, 2)), np.zeros((2, 2))), Features()
    cases = [([features.vector(b, hide) for b in bs], ys) for page in pages if page[0] for bs, ys in (page, with_moved(*page)) for hide in (False, True)]
    seen_e, seen_m = np.full((FEATURES, 2), 1e-8), np.full((2, 2), 1e-8)
    for epoch in range(epochs):
        for i in np.random.default_rng(epoch).permutation(len(cases)):
            vectors, labels = cases[i]
            single, pair = gradient(f, vectors, labels)
            used, place = np.unique(np.concatenate(vectors), return_inverse=True)
            g = np.zeros((len(used), 2))
            np.add.at(g, place, np.repeat(single, [len(v) for v in vectors], axis=0))
            step = g + l2 * f.emit[used]
            seen_e[used] += step**2
            f.emit[used] -= rate * step / np.sqrt(seen_e[used])
            pair += l2 * f.move
            seen_m += pair**2
            f.move -= rate * pair / np.sqrt(seen_m)
    return f


def training_pages(source: DataFrame, max_pages: int, max_page_chars: int) -> list[str]:
    """At most max_pages different pages that mark their article, those of the smallest hashes: copies count once, and
    the rate of the hashes looked at follows the number of marked pages, however rare they are."""
    h = F.xxhash64("html")
    chosen = source.select("html", h.alias("h"), F.pmod(h, F.lit(1 << 30)).alias("at")).where(F.col("html").rlike("(?i)<(article|main)[ >]") & (F.length("html") <= max_page_chars))
    found = chosen.agg(F.approx_count_distinct("h")).first()[0]
    near = chosen.where(F.col("at") <= int(min(1.0, 4 * max_pages / max(1, found)) * (1 << 30)))
    keys = [r[0] for r in near.select("at", "h").distinct().orderBy("at", "h").limit(max_pages).select("h").collect()]
    rows = near.where(F.col("h").isin(keys)).groupBy("h").agg(F.min("html").alias("html")).collect() if keys else []  # at most max_pages
    return [r["html"] for r in sorted(rows, key=lambda r: (r["h"], r["html"]))]


def extract(pages: DataFrame, labelled: DataFrame | None = None, max_pages: int = 200, max_page_chars: int = 100_000, keep: tuple[str, ...] = ()) -> DataFrame:
    """Per row: page_id, columns of keep, text, n_blocks and n_main.

    The field is fitted on at most max_pages different pages of labelled (html column; default: pages itself) that
    mark their article, in hashed order and of at most max_page_chars characters; every page is decoded in full, however
    long or deep. A null or empty page has an empty text, repeated rows the same text; blocks of equal scores are no
    main text. With no page to learn from, the pages' own marks decide.
    """
    spark = pages.sparkSession
    cases = [(bs, [marked(b) for b in bs]) for bs in map(blocks_of, training_pages(labelled if labelled is not None else pages, max_pages, max_page_chars)) if bs]
    shared = spark.sparkContext.broadcast(train(cases) if cases else None)
    carried = list(dict.fromkeys(("page_id", *keep)))
    rows = pages.select(*dict.fromkeys((*carried, "html")))
    fields = ", ".join(f"`{x.name}` {x.dataType.simpleString()}" for x in rows.select(*carried).schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, features = shared.value, Features()
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                texts, counts, mains = [], [], []
                for page in part.column("html").to_pylist():
                    bs = blocks_of(page) if page else []
                    ys = [] if not bs else [marked(b) for b in bs] if model is None else model.decode(model.scores([features.vector(b) for b in bs]))
                    texts.append("\n".join(b.text for b, y in zip(bs, ys, strict=True) if y))
                    counts.append(len(bs))
                    mains.append(sum(ys))
                yield pa.RecordBatch.from_arrays([*(part.column(x) for x in carried), pa.array(texts, pa.string()), pa.array(counts, pa.int64()), pa.array(mains, pa.int64())], [*carried, "text", "n_blocks", "n_main"])

    return rows.mapInArrow(run, f"{fields}, text string, n_blocks long, n_main long")
