"""Main text of web pages: a linear-chain conditional random field over DOM leaf blocks."""

from __future__ import annotations

import html
import random
import re
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, row_slices

#: Pages that the field is trained on, and its training.
TRAINING_PAGES, ROUNDS, RATE, DECAY = 400, 150, 0.1, 2e-3

BLOCK_TAGS = frozenset("address article aside blockquote body button caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol optgroup option p pre search section select summary table tbody td tfoot th thead title tr ul".split())
VOID_TAGS = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW_TAGS = frozenset("script style noscript template svg math iframe object textarea xmp noembed noframes canvas".split())
#: Elements that a new one of the same kind, or of another given kind, ends.
ENDS = {"li": {"li"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}, "body": {"head"}}
SCOPES = frozenset("table ul ol dl select body html div section article aside main nav header footer td th form".split())

MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*+>|<(/?)([a-zA-Z][^\s/>]*+)((?:[^<>\"']++|\"[^\"]*+\"|'[^']*+')*+)>", re.S)
ATTRIBUTE = re.compile(r"(?:\s|\A)(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
NAMES = re.compile(r"[a-z]+")
HIDDEN = re.compile(r"(?:\s|\A)hidden(?:\s|=|/|\Z)|display\s*:\s*none", re.I)
CLASS_WORDS = frozenset("ad ads advert advertisement banner sponsor sponsored promo nav navigation menu menubar breadcrumb breadcrumbs header masthead topbar footer foot copyright legal sidebar side aside widget related recommended more comment comments commentlist reply respond discussion disqus form login signup subscribe newsletter search share social cookie cookies consent gdpr notice alert popup modal overlay article content main post entry story body text page hentry container wrapper title headline byline author caption pagination pager tags meta toc skip complementary contentinfo".split())


@dataclass
class Block:
    tag: str
    tags: frozenset[str]
    words: frozenset[str]
    text: str
    linked: int


@dataclass
class _Open:
    """An open element with what its ancestors and it have: nearest block tag, block tags, class words."""

    tag: str
    block: str
    tags: frozenset[str]
    words: frozenset[str]
    hidden: bool = False


class _Stack:
    """The open elements, and for each kind of them the depths where they stand, so that no search walks the path."""

    def __init__(self) -> None:
        self.open: list[_Open] = [_Open("", "body", frozenset(), frozenset())]
        self.at: dict[str, list[int]] = {}
        self.blocks: list[int] = []
        self.links = self.unseen = 0

    def depth(self, *tags: str) -> int:
        """Depth of the innermost element with one of the tags; -1 without one."""
        return max((self.at[t][-1] for t in tags if self.at.get(t)), default=-1)

    def push(self, tag: str, words: frozenset[str], hidden: bool) -> None:
        over, depth, block = self.open[-1], len(self.open), tag in BLOCK_TAGS
        tags = over.tags | {tag} if block and tag not in over.tags and tag not in ("html", "body") else over.tags
        self.open.append(_Open(tag, tag if block else over.block, tags, over.words if words <= over.words else over.words | words, hidden))
        self.at.setdefault(tag, []).append(depth)
        if block:
            self.blocks.append(depth)
        self.links += tag == "a"
        self.unseen += hidden

    def close(self, depth: int) -> None:
        while len(self.open) > depth:
            o = self.open.pop()
            self.at[o.tag].pop()
            if o.tag in BLOCK_TAGS:
                self.blocks.pop()
            self.links -= o.tag == "a"
            self.unseen -= o.hidden


def leaf_blocks(page: str) -> list[Block]:
    """The runs of text between starts and ends of block elements, in page order.

    Scripts, styles and other raw elements, comments, declarations and elements marked hidden give no
    text. Character references are decoded, white space becomes one space. A `<` that starts no tag is text.
    Time and memory follow the page's length, however deep its elements lie.
    """
    stack, out, parts = _Stack(), [], []
    linked, at, end = 0, 0, page.rfind(">") + 1  # no markup but an open comment ends after the last >

    def flush() -> None:
        nonlocal linked
        if parts:
            text = " ".join(html.unescape("".join(parts)).split())
            if text:
                top = stack.open[-1]
                out.append(Block(top.block, top.tags, top.words, text, min(linked, len(text))))
            parts.clear()
        linked = 0

    while m := MARKUP.search(page, at, end):
        if m.start() > at and not stack.unseen:
            piece = page[at : m.start()]
            parts.append(piece)
            linked += len(piece) if stack.links else 0
        at = m.end()
        tag = m[2]
        if not tag:
            if m[0].startswith("<!--") and not m[0].endswith("-->"):
                at = len(page)
            elif m[0].startswith("<![CDATA["):
                if not m[0].endswith("]]>"):
                    at = len(page)
                if not stack.unseen:
                    parts.append(html.escape(page[m.start() + 9 : at].removesuffix("]]>")))
            continue
        tag = tag.lower()
        if m[1]:
            depth = stack.depth(tag)
            if tag in BLOCK_TAGS:
                flush()
            if depth >= 0 and (tag in BLOCK_TAGS or not (stack.blocks and stack.blocks[-1] >= depth)):
                stack.close(depth)
            continue
        if tag in RAW_TAGS:
            if not m[3].endswith("/"):
                close = re.compile(rf"</{re.escape(tag)}\b[^<>]*+>", re.I).search(page, at)
                at = close.end() if close else len(page)
            continue
        if tag in BLOCK_TAGS:
            flush()
            ended = stack.depth("p", *ENDS.get(tag, ()))
            if ended >= 0 and ended >= stack.depth(*SCOPES):
                stack.close(ended)
        elif tag == "br":
            parts.append(" ")
        if tag not in VOID_TAGS and not m[3].endswith("/"):
            words = frozenset(w for a in ATTRIBUTE.finditer(m[3]) for w in NAMES.findall((a[2] or a[3] or a[4] or "").lower()) if w in CLASS_WORDS) if m[3] else frozenset()
            hidden = bool(m[3]) and HIDDEN.search(re.sub(r"\"[^\"]*\"", lambda q: q[0] if "display" in q[0] else "", m[3])) is not None
            stack.push(tag, words, hidden)
    if not stack.unseen:
        parts.append(page[at:])
    flush()
    return out


def _bin(n: int) -> int:
    return min(8, (n // 12).bit_length())


def features(blocks: list[Block]) -> Iterator[list[str]]:
    """Names of the features that hold for each block."""
    n = len(blocks)
    for k, b in enumerate(blocks):
        size, share = len(b.text), b.linked / max(len(b.text), 1)
        last = b.text[-1]
        f = ["any", f"tag={b.tag}", f"size={_bin(size)}", f"linked={0 if share == 0 else 1 if share < 0.3 else 2 if share < 0.9 else 3}"]
        f += [f"in={t}" for t in b.tags] + [f"class={w}" for w in b.words]
        f.append("ends" if last in ".!?…\"'”»:;。" or not last.isalnum() else "open")
        f.append(f"place={min(4, 5 * k // n)}")
        if k == 0:
            f.append("first")
        if "©" in b.text or "(c)" in b.text.lower():
            f.append("copyright")
        if size < 60 and b.tag[:1] == "h" and b.tag[1:].isdigit():
            f.append("short heading")
        yield f


class ChainField:
    """Binary labels along a page: a weight a feature for label 1, and a weight a pair of neighbouring labels."""

    def __init__(self) -> None:
        self.index: dict[str, int] = {}
        self.weights = np.zeros(0)
        self.steps = np.zeros((2, 2))

    def _scores(self, names: Iterable[list[str]]) -> list[float]:
        index, w = self.index, self.known
        return [sum(w[index[f]] for f in fs if f in index) for fs in names]

    def fit(self, pages: list[tuple[list[list[str]], list[int]]], rounds: int = ROUNDS) -> "ChainField":
        """Maximises the labels' log-likelihood, less a square penalty, by Adam; forward-backward over all pages at once."""
        for f in sorted({f for names, _ in pages for fs in names for f in fs}):
            self.index[f] = len(self.index)
        n, longest = len(pages), max(len(y) for _, y in pages)
        page, place, column = (np.array(v) for v in zip(*((p, t, self.index[f]) for p, (names, _) in enumerate(pages) for t, fs in enumerate(names) for f in fs), strict=True))
        y, live = np.zeros((n, longest), np.int64), np.zeros((n, longest), bool)
        for p, (_, labels) in enumerate(pages):
            y[p, : len(labels)], live[p, : len(labels)] = labels, True
        pairs = live[:, 1:]
        seen = np.zeros((2, 2))
        np.add.at(seen, (y[:, :-1][pairs], y[:, 1:][pairs]), 1)
        m = len(self.index)
        flat = np.zeros(m + 4)
        first, second = np.zeros(m + 4), np.zeros(m + 4)
        for r in range(1, rounds + 1):
            w, steps = flat[:m], flat[m:].reshape(2, 2)
            unary = np.zeros((n, longest, 2))
            np.add.at(unary[:, :, 1], (page, place), w[column])
            ahead, back = np.zeros((n, longest, 2)), np.zeros((n, longest, 2))
            ahead[:, 0] = unary[:, 0]
            for t in range(1, longest):
                new = np.logaddexp.reduce(ahead[:, t - 1, :, None] + steps[None], axis=1) + unary[:, t]
                ahead[:, t] = np.where(live[:, t, None], new, ahead[:, t - 1])
            for t in range(longest - 2, -1, -1):
                new = np.logaddexp.reduce(steps[None] + (unary[:, t + 1] + back[:, t + 1])[:, None, :], axis=2)
                back[:, t] = np.where(live[:, t + 1, None], new, 0)
            total = np.logaddexp.reduce(ahead[:, -1], axis=1)
            one = np.where(live, np.exp(ahead[:, :, 1] + back[:, :, 1] - total[:, None]), 0)
            both = np.exp(ahead[:, :-1, :, None] + steps[None, None] + (unary[:, 1:] + back[:, 1:])[:, :, None, :] - total[:, None, None, None]) * pairs[:, :, None, None]
            slope = np.concatenate((np.bincount(column, (one - y)[page, place], m), (both.sum(axis=(0, 1)) - seen).ravel())) / n + DECAY * flat
            first, second = 0.9 * first + 0.1 * slope, 0.999 * second + 0.001 * slope**2
            flat = flat - RATE * (first / (1 - 0.9**r)) / (np.sqrt(second / (1 - 0.999**r)) + 1e-9)
        self.weights, self.steps = flat[:m], flat[m:].reshape(2, 2)
        return self

    @property
    def known(self) -> list[float]:
        if getattr(self, "_known", None) is None or len(self._known) != len(self.weights):
            self._known = self.weights.tolist()
        return self._known

    def decode(self, names: Iterable[list[str]]) -> list[int]:
        """The most likely labels, by Viterbi; ties go to label 0."""
        (s00, s01), (s10, s11) = self.steps.tolist()
        scores = self._scores(names)
        if not scores:
            return []
        zero, one, came = 0.0, scores[0], []
        for s in scores[1:]:
            a, b = zero + s00 < one + s10, zero + s01 < one + s11
            came.append((a, b))
            zero, one = (one + s10 if a else zero + s00), (one + s11 if b else zero + s01) + s
        label = int(one > zero)
        out = [label]
        for a, b in reversed(came):
            label = int(b if label else a)
            out.append(label)
        return out[::-1]


SYLLABLES = "an be co da el fi go hu in jo ka le mi no or pa qua re si to un ve wi xa yo ze tion ment able ing er est".split()


def labelled_page(rng: random.Random) -> list[tuple[str, int, str]]:
    """Parts of a made page: (markup before, label, text); label 1 is main text. Layouts, class names and order vary."""
    word = lambda: "".join(rng.choice(SYLLABLES) for _ in range(rng.randint(1, 4)))
    tail = rng.choice(["", "", "", "***", "%%%", " &amp;", "$$$"])

    def words(a: int, b: int) -> str:
        return " ".join(word() + (tail if rng.random() < 0.5 else "") for _ in range(rng.randint(a, b)))

    def sentence(a: int = 4, b: int = 18) -> str:
        return words(a, b).capitalize() + rng.choice([".", ".", ".", "!", "?", "", tail])

    paragraph = lambda: " ".join(sentence() for _ in range(rng.choice([1, 1, 2, 3, 5, 8])))
    out: list[tuple[str, int, str]] = []
    add = lambda before, text, label=0: out.append((before, label, text))
    pick = rng.choice

    def wrap(options: list[str], body) -> None:
        o = pick(options)
        name = NAMES.match(o[1:])[0]
        add(o, "")
        body()
        add(f"</{name}>", "")

    def links() -> None:
        add("<ul>", "")
        for _ in range(rng.randint(2, 8)):
            add(f'<li><a href="/{word()}">', words(1, 3))
            add("</a></li>", "")
        add("</ul>", "")

    def line(a: int = 3, b: int = 25):
        return lambda: add(pick(["", "<p>", "<span>", "<div>"]), sentence(a, b))

    def header() -> None:
        wrap(["<header>", '<div class="header">', '<div id="masthead">', '<div class="top-header site-header">'], lambda: (add(pick(["<h1>", "<p>", "<div>", "<a href='/'>"]), words(1, 4)), add("</h1>", "") if rng.random() < 0.5 else None, links() if rng.random() < 0.5 else None))

    def comments() -> None:
        def one() -> None:
            if rng.random() < 0.7:
                add(pick(["<h2>", "<h3>", "<h4>"]), pick(["Comments", words(1, 3)]))
            for _ in range(rng.randint(1, 5)):
                add(pick(['<div class="comment">', '<article class="comment">', "<li>", '<li class="comment">']), "")
                add(pick(["<b>", "<cite>", "<p class='author'>"]), words(1, 2))
                add("<p>", paragraph())
                add("</p></li></article></div>", "") if rng.random() < 0.0 else add("</p>", "")

        wrap(['<div class="comments">', '<section id="comments">', '<ol class="commentlist">', '<div id="disqus_thread" class="discussion">', '<aside class="comments">', '<section class="comments">'], one)

    def form() -> None:
        wrap(["<form>", '<form class="search">', '<form id="login">', '<div class="newsletter signup">'], lambda: (add("<label>", words(1, 4)), add("<input><button>", words(1, 2)), add("</button>", "")))

    def advert() -> None:
        wrap(['<div class="ad">', '<div class="advert">', '<div class="sponsored promo">', '<aside class="ads">', '<section class="banner">', '<div id="ad-top">'], line(3, 20))

    def notice() -> None:
        wrap(['<div class="cookie-notice">', '<div id="consent">', '<div class="notice">', '<section class="gdpr popup">', '<div role="alert">', '<dialog class="modal">', '<div class="cookie banner">'], lambda: (add("<p>", sentence(5, 25)), add("<button>", words(1, 2)), add("</button>", "")))

    def sidebar() -> None:
        wrap(["<aside>", '<div class="sidebar">', '<div id="side" class="widget">', '<section class="related">', '<div class="more recommended">'], lambda: (add(pick(["<h2>", "<h3>", "<h4>"]), words(1, 4)), pick([links, line(5, 30)])()))

    def footer() -> None:
        wrap(["<footer>", '<div class="footer">', '<div id="foot" class="legal">', '<div class="copyright">'], lambda: (add(pick(["", "<p>", "<small>"]), pick(["&copy; ", ""]) + words(2, 12) + pick([" &middot; ", ". ", ""]) + sentence(2, 8)), links() if rng.random() < 0.4 else None))

    def article() -> None:
        def body() -> None:
            if rng.random() < 0.85:
                add(pick(["<h1>", "<h1>", "<h2>"]), pick([words(2, 9), sentence(2, 9)]), 1)
                add("</h1></h2>", "")
            for _ in range(pick([1, 2, 4, 8, 14])):
                kind = rng.random()
                if kind < 0.72:
                    add(pick(["<p>", "<p>", "<p>", "<div>", "<p><b>"]), paragraph(), 1)
                    add(pick(["</p>", "</p>", "", "<br>"]), "")
                elif kind < 0.8:
                    add(pick(["<h2>", "<h3>"]), words(1, 6), 1)
                    add("</h2></h3>", "")
                elif kind < 0.87:
                    add("<ul>", "")
                    for _ in range(rng.randint(2, 4)):
                        add("<li>", pick([words(1, 8), sentence()]), 1)
                    add("</li></ul>", "")
                elif kind < 0.93:
                    add(pick(["<blockquote>", "<pre>", "<figure><figcaption>"]), sentence(5, 20), 1)
                    add("</blockquote></pre></figcaption></figure>", "")
                elif kind < 0.96:
                    advert()
                else:
                    add("<table><tr><td>", words(1, 4), 1)
                    add("<td>", words(1, 4), 1)
                    add("</table>", "")

        wrap(["<article>", "<article>", "<article>", "<main>", '<div class="content">', '<div class="article-body">', '<div id="main">', '<section class="post entry">', '<div class="story text">', '<article class="post">'], body)

    middle = [advert] * (rng.random() < 0.6) + [sidebar] * (rng.random() < 0.5) + [form] * (rng.random() < 0.3) + [notice] * (rng.random() < 0.4)
    rng.shuffle(middle)
    cut = rng.randint(0, len(middle))
    if rng.random() < 0.8:
        add("<head><title>", words(2, 8))
        add("</title></head><body>", "")
    for part in [header] * (rng.random() < 0.5):
        part()
    if rng.random() < 0.85:
        wrap(["<nav>", '<div class="menu">', '<div id="nav" class="navigation">', '<ul class="menubar">'], links)
    for part in middle[:cut]:
        part()
    if rng.random() < 0.97:
        article()
    for part in middle[cut:] + [comments] * (rng.random() < 0.45):
        part()
    if rng.random() < 0.85:
        footer()
    return out


def training_set(pages: int = TRAINING_PAGES, seed: int = 31) -> list[tuple[list[list[str]], list[int]]]:
    """Features and labels of the blocks of made pages; a mark in each labelled text tells its blocks."""
    rng, out = random.Random(seed), []
    for _ in range(pages):
        parts = labelled_page(rng)
        blocks = leaf_blocks("".join(before + (f"{text}" if label else text) for before, label, text in parts))
        labels = [int("" in b.text) for b in blocks]
        for b in blocks:
            b.text = b.text.replace("", "") or "x"
        if blocks:
            out.append((list(features(blocks)), labels))
    return out


_trained: dict[tuple[int, int], ChainField] = {}


def trained_field(pages: int = TRAINING_PAGES, seed: int = 31) -> ChainField:
    if (pages, seed) not in _trained:
        _trained[pages, seed] = ChainField().fit(training_set(pages, seed))
    return _trained[pages, seed]


def main_text(page: str, model: ChainField) -> str:
    blocks = leaf_blocks(page)
    return "\n\n".join(b.text for b, label in zip(blocks, model.decode(features(blocks)), strict=True) if label)


def extract_pages(pages: DataFrame, model: ChainField | None = None, key: str = "page_id", url: str = "url", markup: str = "html") -> DataFrame:
    """Per row: key, url, text, n_chars: the main text of the whole page; empty if there is none.

    Null and empty pages give an empty text. Repeated rows are treated alike; other columns are ignored.
    """
    shared = pages.sparkSession.sparkContext.broadcast(model or trained_field())

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for rows in row_slices(batches, "html"):
            texts = [main_text(p, own) if p else "" for p in rows.column(2).to_pylist()]
            yield pa.RecordBatch.from_arrays([rows.column(0), rows.column(1), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["id", "url", "text", "n_chars"])

    source = pages.select(F.col(key).alias("id"), F.col(url).alias("url"), F.col(markup).alias("html"))
    return map_batches(source, run, f"id {source.schema['id'].dataType.simpleString()}, url string, text string, n_chars long").withColumnRenamed("id", key)
