"""HTML main-text extraction by a recurrent block labeller.

A page becomes its sequence of leaf blocks (text between block-level tags). A block's vector has its hashed tag path
(tags, class and id words of all open elements, and of the innermost ones apart), its hashed words, and a few counts.
A bidirectional LSTM in numpy reads the whole sequence, so each block is judged with the page around it, and says
whether it belongs to the article.

The labeller is trained here, from pages that `training_page` makes up: random layouts, tag and class names, words
and lengths, with notices, menus, adverts, forms and comments as long as article text. Nothing of a given page is
learned, so predictions are alike whatever the input. Training takes some seconds once per query and its weights
(about 150 KB) are broadcast.

Defined cases: null or empty html gives an empty text; text without tags is one block and judged like any other;
unclosed, crossed and unknown tags are taken as browsers roughly do; nothing is cut off however long a page is; a
null page_id or url stays null; repeated rows get equal results; other columns are ignored. Only scripts, styles,
comments and what drawings and formulas never show (their titles, descriptions, sources) are no text; the content of
every other element is read and judged. A tag that never ends is text. Parsing takes time in proportion to the page.
"""

from __future__ import annotations

import html as entities
import re
import zlib
from collections.abc import Iterator
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutlearn.llm import textblocks as tb

PATH_DIM, LEAF_DIM, WORD_DIM, COUNTS = 256, 256, 24, 6
WIDTH, HIDDEN = PATH_DIM + LEAF_DIM + WORD_DIM + COUNTS, 20
BATCH_PAGES, BATCH_BLOCKS = 128, 20_000
#: Characters of html that are parsed together (a longer page by itself), and blocks whose rows are made at once.
BATCH_CHARS, PIECE = 4 << 20, 4096
TRAIN_PAGES, EPOCHS, SEED = 1000, 6, 11

#: Elements of HTML that begin a block of their own, those without content, and those whose content is no text.
BLOCK = set("address article aside blockquote body button center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html legend li main menu nav ol option p pre section select summary table tbody td tfoot th thead title tr ul".split())
VOID = set("area base br col embed hr img input link meta param source track wbr".split())
RAW = {x: re.compile(rf"</{x}(?=[\s/>])", re.I) for x in ("script", "style")}
ENDS_P = BLOCK - {"button", "option", "legend", "summary"}
SAME_CLOSES = {"p", "li", "dt", "dd", "option", "tr", "td", "th"}
#: Drawings and formulas, what they hold but never show, where HTML begins again in them, and what ends them unclosed.
FOREIGN = {"svg", "math"}
UNSHOWN = {x: re.compile(rf"</{x}(?=[\s/>])", re.I) for x in "title desc metadata script style annotation annotation-xml".split()}
HTML_AGAIN = {"foreignobject"}
BREAKS_OUT = (BLOCK - {"title", "option", "select", "button"}) | set("b big br code em embed i img meta nobr ruby s small span strike strong sub sup tt u var".split())

BEGIN = re.compile(r"</?[a-zA-Z]|<[!?/]")
TAG = re.compile(r"</?([a-zA-Z][^\s/>]*+)((?:[^>=]++|=\s*+\"[^\"]*+\"|=\s*+'[^']*+'|=)*+)>")
LOOSE_TAG = re.compile(r"</?([a-zA-Z][^\s/>]*+)([^>]*+)>")
END_OF_COMMENT = re.compile(r"--!?>")
NAMED = re.compile(r"(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
LINK_TEXT = "a"
MARK, STOP = (np.isin(np.arange(256), list(x)) for x in (b".,;", b".!?"))


class Place:
    """An open element with all those around it. Equal elements in one place are one, so its vector is made once."""

    __slots__ = ("label", "parent", "inner", "vector")

    def __init__(self, label: str = "", parent: Place | None = None):
        self.label, self.parent, self.inner = label, parent, {}
        self.vector = np.zeros(PATH_DIM, np.int8) if parent is None else None

    def within(self, label: str) -> Place:
        if label not in self.inner:
            self.inner[label] = Place(label, self)
        return self.inner[label]

    def path_vector(self) -> np.ndarray:
        todo, p = [], self
        while p.vector is None:
            todo.append(p)
            p = p.parent
        for p in reversed(todo):
            p.vector = p.parent.vector.copy()
            for i, sign in _label_slots(p.label):
                p.vector[i] = min(1, max(-1, p.vector[i] + sign))
        return self.vector


class Block(NamedTuple):
    place: Place
    text: str
    linked: int  # characters of the text inside links

    @property
    def path(self) -> tuple[str, ...]:
        """Labels of the open elements, the outermost first."""
        out, p = [], self.place
        while p.parent is not None:
            out.append(p.label)
            p = p.parent
        return tuple(reversed(out))


def blocks(page: str, root: Place | None = None) -> list[Block]:
    """The leaf blocks of a page in order, with references decoded and white space folded. Each character is looked at
    a bounded number of times: open elements are found by name, and no search that failed is tried again."""
    out: list[Block] = []
    names: list[str] = []
    places = [root or Place()]
    at_name: dict[str, list[int]] = {}  # where elements of a name stand among the open ones
    fences: list[int] = []  # where open block elements stand
    modes: list[tuple[int, bool]] = []  # where drawings and formulas begin (True), and HTML again inside them
    unclosed: set[str] = set()  # names that no closing tag follows any more
    parts: list[tuple[str, bool]] = []
    links, loose = 0, False

    def say(text: str) -> None:
        parts.append((entities.unescape(text) if "&" in text else text, links > 0))

    def flush() -> None:
        if parts:
            text = " ".join("".join(p for p, _ in parts).split())
            if text:
                out.append(Block(places[-1], text, min(len(text), sum(len(p) for p, on in parts if on))))
            parts.clear()

    def close_to(k: int) -> None:
        nonlocal links
        while len(names) > k:
            name = names.pop()
            places.pop()
            at_name[name].pop()
            links -= name == LINK_TEXT
        while fences and fences[-1] >= k:
            fences.pop()
        while modes and modes[-1][0] >= k:
            modes.pop()

    def open_(name: str, attributes: str, fence: bool) -> None:
        nonlocal links
        labels = " ".join([name, *(v.lower() for t in NAMED.findall(attributes) for v in t if v)]) if attributes else name
        if fence:
            fences.append(len(names))
        at_name.setdefault(name, []).append(len(names))
        names.append(name)
        places.append(places[-1].within(labels))
        links += name == LINK_TEXT

    def close(name: str) -> None:
        at = at_name.get(name)
        if at and (name in BLOCK or not fences or fences[-1] < at[-1]):
            close_to(at[-1])

    def skip(name: str, closing: re.Pattern, begin: int) -> int:
        """Where the closing tag of a name begins, or -1."""
        if name in unclosed:
            return -1
        end = closing.search(page, begin)
        if end is None:
            unclosed.add(name)
        return end.start() if end else -1

    at, n, last_end = 0, len(page), page.rfind(">")
    while at < n:
        begin = page.find("<", at)
        if begin < 0 or begin > last_end and not page.startswith("<!--", begin):  # no tag ends any more
            say(page[at:])
            break
        if begin > at:
            say(page[at:begin])
        kind = BEGIN.match(page, begin)
        if not kind:
            say("<")
            at = begin + 1
            continue
        if not kind[0][-1].isalpha():
            if page.startswith("<!--", begin):
                end = END_OF_COMMENT.search(page, begin + 2 if page.startswith(("<!-->", "<!--->"), begin) else begin + 4)
                at = end.end() if end else n
            else:
                at = page.find(">", begin) + 1
            continue
        m = None if loose else TAG.match(page, begin)
        if m is None:  # a quote that never ends: from here on a tag ends with its first bracket
            loose = True
            m = LOOSE_TAG.match(page, begin)
        at = m.end()
        name, attributes, closing = m[1].lower(), m[2], page[begin + 1] == "/"
        if modes and modes[-1][1]:
            if not closing and name in BREAKS_OUT or closing and name == "p":
                while modes and modes[-1][1]:
                    close_to(modes[-1][0])
            else:
                if closing:
                    close(name)
                elif not attributes.endswith("/"):
                    if name in UNSHOWN and (end := skip(name, UNSHOWN[name], at)) >= 0:
                        at = end
                        continue
                    if name in FOREIGN or name in HTML_AGAIN:
                        modes.append((len(names), name in FOREIGN))
                    open_(name, attributes, False)
                continue
        if name in RAW and not closing:
            end = skip(name, RAW[name], at)
            at = n if end < 0 else end
            parts.append((" ", False))
            continue
        if name == "br":
            parts.append((" ", False))
            continue
        if name in BLOCK:
            flush()
        if closing:
            close(name)
        elif name not in VOID:
            if name in FOREIGN:
                if attributes.endswith("/"):
                    continue
                modes.append((len(names), True))
            if name in ENDS_P:
                if fences and names[fences[-1]] == "p":
                    close_to(fences[-1])
                if fences and name in SAME_CLOSES and names[fences[-1]] == name:
                    close_to(fences[-1])
            open_(name, attributes, name in BLOCK)
    flush()
    return out


def _slot(word: str, size: int, salt: str) -> tuple[int, int]:
    h = zlib.crc32(f"{salt}{word}".encode("utf-8", "surrogatepass"))
    return (h >> 1) % size, 1 if h & 1 else -1


@lru_cache(maxsize=20_000)
def _label_slots(label: str) -> list[tuple[int, int]]:
    return [_slot(word, PATH_DIM, "path ") for word in re.findall(r"[a-z0-9]+", label)]


@lru_cache(maxsize=20_000)
def _leaf_vector(labels: tuple[str, ...]) -> np.ndarray:
    """Of the innermost labels, the innermost first."""
    v = np.zeros(LEAF_DIM, np.int8)
    for depth, label in enumerate(labels):
        for word in re.findall(r"[a-z0-9]+", label):
            i, sign = _slot(word, LEAF_DIM, f"leaf{depth} ")
            v[i] = min(1, max(-1, v[i] + sign))
    return v


def _leaves(place: Place) -> tuple[str, ...]:
    return tuple(p.label for p in (place, place.parent) if p is not None and p.parent is not None)


def rows_of(every: list[Block], place: np.ndarray) -> np.ndarray:
    """A row of WIDTH for each block. place: how far down its page each one stands. Words are hashed for all at once."""
    n = len(every)
    v = np.zeros((n, WIDTH))
    if not n:
        return v
    raw = [b.text.encode("utf-8", "surrogatepass") for b in every]
    offsets = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
    data = np.frombuffer(b"".join(raw), np.uint8)
    s, e, first = tb.words_of(data, offsets)
    h = tb.RangeHash(data).of(s, e)
    words = np.diff(first)
    at = np.repeat(np.arange(n), words) * WORD_DIM + (h % np.uint64(WORD_DIM)).astype(np.int64)
    sign = np.where(h >> np.uint64(63), 1.0, -1.0)
    v[:, :PATH_DIM] = [b.place.path_vector() for b in every]
    v[:, PATH_DIM : PATH_DIM + LEAF_DIM] = [_leaf_vector(_leaves(b.place)) for b in every]
    # \x1c to \x1f and \x85 part words for str.split() alone, so a block may have none by the rule for documents
    bag = np.bincount(at, sign, n * WORD_DIM).reshape(n, WORD_DIM) / np.sqrt(np.maximum(words, 1))[:, None]
    v[:, PATH_DIM + LEAF_DIM : WIDTH - COUNTS] = np.clip(bag * 0.3, -1, 1)  # one word over and over must not outweigh all else
    size = np.array([len(b.text) for b in every])
    marks = tb.sums_by(MARK[data].astype(np.int64), offsets)
    counts = (np.log1p(words) / 4, np.array([b.linked for b in every]) / size, STOP[data[offsets[1:] - 1]], np.log1p(size) / 8, place, marks / np.maximum(words, 1))
    v[:, WIDTH - COUNTS :] = np.stack(counts, axis=1)
    return v


def _down_the_page(pages: list[list[Block]]) -> np.ndarray:
    return np.concatenate([np.arange(len(p)) / max(len(p), 1) for p in pages]) if pages else np.zeros(0)


def vectors_of(pages: list[list[Block]]) -> list[np.ndarray]:
    """A row of WIDTH for each block of each page."""
    v = rows_of([b for page in pages for b in page], _down_the_page(pages))
    return np.split(v, np.cumsum([len(p) for p in pages])[:-1]) if pages else []


def vectors(page: list[Block]) -> np.ndarray:
    return vectors_of([page])[0]


def new_weights(rng: np.random.Generator) -> dict[str, np.ndarray]:
    w = {}
    for side in ("f", "b"):
        w[f"x{side}"] = rng.normal(0, 1 / np.sqrt(WIDTH), (WIDTH, 4 * HIDDEN))
        w[f"h{side}"] = rng.normal(0, 1 / np.sqrt(HIDDEN), (HIDDEN, 4 * HIDDEN))
        w[f"c{side}"] = np.concatenate([np.zeros(HIDDEN), np.ones(HIDDEN), np.zeros(2 * HIDDEN)])
    w["out"] = rng.normal(0, 1 / np.sqrt(2 * HIDDEN), 2 * HIDDEN)
    w["bias"] = np.zeros(1)
    return w


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def _scan(w: dict, side: str, x: np.ndarray, real: np.ndarray, keep: list | None = None) -> np.ndarray:
    """Hidden states (time, page, HIDDEN) of one direction; padding leaves the state as it is. x: rows of WIDTH, or rows
    already projected for this direction."""
    steps, n, _ = x.shape
    pre = x @ w[f"x{side}"] + w[f"c{side}"] if x.shape[2] == WIDTH else x
    h, c, out = np.zeros((n, HIDDEN)), np.zeros((n, HIDDEN)), np.zeros((steps, n, HIDDEN))
    for t in range(steps) if side == "f" else range(steps - 1, -1, -1):
        z = pre[t] + h @ w[f"h{side}"]
        i, f, o = (_sigmoid(z[:, k * HIDDEN : (k + 1) * HIDDEN]) for k in range(3))
        g = np.tanh(z[:, 3 * HIDDEN :])
        c2 = f * c + i * g
        tc = np.tanh(c2)
        m = real[t][:, None]
        if keep is not None:
            keep.append((t, i, f, o, g, c, tc, h, m))
        h, c = np.where(m, o * tc, h), np.where(m, c2, c)
        out[t] = h
    return out


def _back(w: dict, side: str, x: np.ndarray, kept: list, dout: np.ndarray, grad: dict) -> None:
    dh_next, dc_next = np.zeros(dout.shape[1:]), np.zeros(dout.shape[1:])
    for t, i, f, o, g, c, tc, h, m in reversed(kept):
        dh = dout[t] + dh_next
        dh_own, dc_own = np.where(m, dh, 0), np.where(m, dc_next, 0)
        dc = dc_own + dh_own * o * (1 - tc * tc)
        dz = np.hstack([dc * g * i * (1 - i), dc * c * f * (1 - f), dh_own * tc * o * (1 - o), dc * i * (1 - g * g)])
        grad[f"x{side}"] += x[t].T @ dz
        grad[f"h{side}"] += h.T @ dz
        grad[f"c{side}"] += dz.sum(axis=0)
        dh_next = dz @ w[f"h{side}"].T + np.where(m, 0, dh)
        dc_next = dc * f + np.where(m, 0, dc_next)


def _padded(pages: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    steps = max(map(len, pages))
    x, real = np.zeros((steps, len(pages), pages[0].shape[1]), pages[0].dtype), np.zeros((steps, len(pages)), bool)
    for k, v in enumerate(pages):
        x[: len(v), k], real[: len(v), k] = v, True
    return x, real


def projected(w: dict, pages: list[list[Block]]) -> list[np.ndarray]:
    """What both directions see of each block, PIECE blocks at a time, so wide rows never stand for a whole long page."""
    every, place = [b for page in pages for b in page], _down_the_page(pages)
    out = np.zeros((len(every), 8 * HIDDEN), np.float32)
    both, shift = np.hstack([w["xf"], w["xb"]]), np.concatenate([w["cf"], w["cb"]])
    for k in range(0, len(every), PIECE):
        out[k : k + PIECE] = rows_of(every[k : k + PIECE], place[k : k + PIECE]) @ both + shift
    return np.split(out, np.cumsum([len(p) for p in pages])[:-1]) if pages else []


def chances(w: dict, pages: list[np.ndarray]) -> list[np.ndarray]:
    """For each page (rows of its blocks, plain or projected) the chance of each block to be main text."""
    out: list[np.ndarray] = [np.zeros(0)] * len(pages)
    order = sorted((k for k in range(len(pages)) if len(pages[k])), key=lambda k: len(pages[k]))
    at = 0
    while at < len(order):
        z = at + 1
        while z < len(order) and z - at < BATCH_PAGES and (z - at + 1) * len(pages[order[z]]) <= BATCH_BLOCKS:
            z += 1
        part = order[at:z]
        x, real = _padded([pages[k] for k in part])
        ahead, back = (x, x) if x.shape[2] == WIDTH else (x[:, :, : 4 * HIDDEN], x[:, :, 4 * HIDDEN :])
        states = np.concatenate([_scan(w, "f", ahead, real), _scan(w, "b", back, real)], axis=2)
        p = _sigmoid(states @ w["out"] + w["bias"])
        for col, k in enumerate(part):
            out[k] = p[: len(pages[k]), col]
        at = z
    return out


def gradient(w: dict, pages: list[np.ndarray], labels: list[np.ndarray]) -> tuple[float, dict]:
    """Mean cross entropy per block and its gradient."""
    x, real = _padded(pages)
    y = np.zeros(real.shape)
    for k, v in enumerate(labels):
        y[: len(v), k] = v
    kept = {"f": [], "b": []}
    states = np.concatenate([_scan(w, s, x, real, kept[s]) for s in "fb"], axis=2)
    p = _sigmoid(states @ w["out"] + w["bias"])
    n = real.sum()
    loss = -np.where(real, y * np.log(p + 1e-12) + (1 - y) * np.log(1 - p + 1e-12), 0).sum() / n
    d = np.where(real, p - y, 0) / n
    grad = {k: np.zeros_like(v) for k, v in w.items()}
    grad["out"], grad["bias"] = np.einsum("tnh,tn->h", states, d), np.array([d.sum()])
    for k, s in enumerate("fb"):
        _back(w, s, x, kept[s], d[:, :, None] * w["out"][k * HIDDEN : (k + 1) * HIDDEN], grad)
    return float(loss), grad


#: Fixed values for made-up pages: names that sites give to the parts of a page.
MAIN = ["<article>", "<main>", '<div class="content">', '<div id="main-content">', '<section class="post">', '<div class="entry-content">', '<div class="article-body">', '<main><article>', '<div class="story">']
SIDE = {
    "nav": ["<nav>", '<div class="menu">', '<div id="navbar">', '<ul class="nav">', '<div class="breadcrumb">', '<div role="navigation">', '<div class="pagination">'],
    "head": ["<header>", '<div class="header">', '<div id="masthead">', '<div class="site-header">', '<div role="banner">'],
    "foot": ["<footer>", '<div class="footer">', '<div id="footer">', '<div class="copyright">', '<div role="contentinfo">'],
    "side": ["<aside>", '<div class="sidebar">', '<div id="sidebar">', '<div class="related">', '<div class="widget">', '<aside class="recommended">'],
    "ad": ['<div class="ad">', '<div class="ads">', '<div class="advert">', '<div class="sponsored">', '<div class="advertisement">', '<div class="promo">', '<div id="banner-ad">', '<aside class="ad">'],
    "notice": ['<div class="cookie">', '<div class="notice">', '<div class="alert">', '<div id="cookie-banner">', '<div class="consent">', '<div class="popup">', '<div class="notification">', '<section class="notice">', '<div role="dialog">'],
    "form": ["<form>", '<form class="search">', '<form id="newsletter">', '<div class="subscribe"><form>', '<form class="login">'],
    "comments": ['<div class="comments">', '<section id="comments">', '<div id="disqus">', '<ol class="comment-list">', '<section class="comments">', '<div class="discussion">', '<ul class="replies">', '<div class="reader-comments">'],
}


def training_page(rng: np.random.Generator) -> tuple[str, list[int]]:
    """A made-up page and, for each of its leaf blocks, whether it is main text."""
    letters = "abcdefghijklmnopqrstuvwxyzéüñç"
    pool = ["".join(rng.choice(list(letters), rng.integers(2, 10))) for _ in range(60)]
    out, labels = [], []
    pick = lambda xs: xs[rng.integers(len(xs))]
    usual = lambda xs: xs[0] if rng.random() < 0.4 else pick(xs)  # noqa: E731  the elements that HTML has for a part come first

    def words(n: int, stop: bool = True) -> str:
        text = " ".join(pick(pool) for _ in range(max(1, n)))
        if rng.random() < 0.15:
            text = re.sub(r"(\w)( |$)", r"\1&amp;&amp;\2", text) if rng.random() < 0.5 else text.upper()
        return text.capitalize() + (pick([".", ".", "!", "?", ""]) if stop else "")

    def put(text: str, label: int) -> str:
        labels.append(label)
        return text

    def closing(tag: str) -> str:
        return "".join(f"</{t}>" for t in reversed(re.findall(r"<(\w+)", tag)))

    def prose(tag: str, n: int, label: int) -> str:
        inner = words(n)
        if rng.random() < 0.05:
            inner = " ".join([pick(pool)] * (5 * n)) + "."
        if rng.random() < 0.2:
            inner += f' <a href="/{pick(pool)}">{words(2, False)}</a> {words(n // 2 + 1)}'
        if rng.random() < 0.15:
            inner = f"<b>{inner}" + pick(["</b>", "<br>"])
        noise = f' class="{pick(pool)}"' if rng.random() < 0.2 else ""
        return put(f"<{tag}{noise}>{inner}" + (f"</{tag}>" if rng.random() < 0.9 else ""), label)

    def part(kind: str) -> str:
        tag = usual(SIDE[kind])
        inner = []
        if kind in ("nav", "side", "foot", "head") and rng.random() < 0.8:
            inner += ["<ul>", *(put(f'<li><a href="/{pick(pool)}">{words(rng.integers(1, 4), False)}</a></li>', 0) for _ in range(rng.integers(2, 9))), "</ul>"]
        if kind == "form":
            inner += [put(f"<label>{words(2)}</label><input name=q>", 0), put(f"<button>{words(1, False)}</button>", 0)]
        if kind == "comments":
            inner += [x for _ in range(rng.integers(1, 6)) for x in (f'<div class="{pick(["comment", "reply", "comment-body"])}">', *(put(f"<span>{words(2, False)}</span>", 0) for _ in range(1)), prose("p", int(rng.integers(3, 60)), 0), "</div>")]
        if kind in ("side", "head", "ad", "notice") and rng.random() < 0.5:
            inner += [prose(pick(["h2", "h3", "p", "div"]), int(rng.integers(2, 40)), 0)]
        if not inner or kind in ("ad", "notice", "foot") and rng.random() < 0.6:
            inner.insert(0, put(("&copy; " + pick(["", "2024 ", f"{pick(pool)}.example &middot; "]) if kind == "foot" else "") + words(int(rng.integers(2, 40))), 0))
        return tag + "".join(inner) + closing(tag)

    title = words(int(rng.integers(2, 10)), False)
    out.append(f'<!DOCTYPE html><html><head><meta charset="utf-8">{put(f"<title>{title}</title>", 0)}<style>p{{margin:0}}</style></head><body>')
    for kind in ("notice", "head", "nav", "ad", "form"):
        if rng.random() < 0.5:
            out.append(part(kind))
    wrap = pick(["", "", '<div class="container">', '<div id="page"><div class="row">'])
    main = usual(MAIN)
    out += [wrap, main]
    if rng.random() < 0.8:
        out.append(put(f"<h1>{title}</h1>", 1))
    for _ in range(int(rng.integers(1, 14))):
        draw = rng.random()
        if draw < 0.75:
            out.append(prose("p", int(rng.integers(1, 80)), 1))
        elif draw < 0.85:
            out.append(put(f"<h2>{words(4, False)}</h2>", 1))
        elif draw < 0.92:
            out += ["<ul>", *(prose("li", int(rng.integers(1, 15)), 1) for _ in range(rng.integers(1, 5))), "</ul>"]
        elif draw < 0.96:
            out.append(prose("blockquote", int(rng.integers(5, 40)), 1))
        else:
            out.append(part(pick(["ad", "form", "notice", "side", "nav"])))
    if rng.random() < 0.15:
        out.append(part("comments"))
    out += [closing(main)]
    for kind in ("side", "comments", "ad", "form", "nav", "notice", "foot"):
        if rng.random() < 0.45:
            out.append(part(kind))
    out += [closing(wrap), "</body></html>"]
    return "".join(out), labels


@lru_cache(maxsize=2)
def train(pages: int = TRAIN_PAGES, epochs: int = EPOCHS, seed: int = SEED) -> dict[str, np.ndarray]:
    """Weights by Adam on made-up pages."""
    rng = np.random.default_rng(seed)
    data = []
    while len(data) < pages:
        page, labels = training_page(rng)
        found = blocks(page)
        if len(found) == len(labels):
            data.append((vectors(found), np.array(labels, float)))
    data.sort(key=lambda x: len(x[1]))
    w = new_weights(rng)
    m, v, step = {k: np.zeros_like(x) for k, x in w.items()}, {k: np.zeros_like(x) for k, x in w.items()}, 0
    size = 20
    for epoch in range(epochs):
        rate = 0.02 * (1 - epoch / epochs) ** 1.5
        for k in rng.permutation(-(-pages // size)):
            part = data[k * size : (k + 1) * size]
            _, grad = gradient(w, [x for x, _ in part], [y for _, y in part])
            step += 1
            for name, g in grad.items():
                m[name] = 0.9 * m[name] + 0.1 * g
                v[name] = 0.99 * v[name] + 0.01 * g * g
                w[name] = w[name] - rate * (m[name] / (1 - 0.9**step)) / (np.sqrt(v[name] / (1 - 0.99**step)) + 1e-8)
    return w


EXTRACTED = "page_id long, url string, text string, n_chars long"


def main_text(w: dict, pages: list[str]) -> list[str]:
    root = Place()
    found = [blocks(p, root) for p in pages]
    return ["\n".join(b.text for b, p in zip(page, chance, strict=True) if p >= 0.5) for page, chance in zip(found, chances(w, projected(w, found)), strict=True)]


def _parts(pages: list[str]) -> Iterator[tuple[int, int]]:
    """Runs of pages that are parsed together."""
    a, chars = 0, 0
    for k, p in enumerate(pages):
        if k > a and (k - a == BATCH_PAGES or chars + len(p) > BATCH_CHARS):
            yield a, k
            a, chars = k, 0
        chars += len(p)
    if len(pages) > a:
        yield a, len(pages)


def _extractor(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            pages = [p or "" for p in batch.column(2).to_pylist()]
            for a, z in _parts(pages):
                part, text = batch.slice(a, z - a), main_text(shared.value, pages[a:z])
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return run


def extract(pages: DataFrame, weights: dict[str, np.ndarray] | None = None) -> DataFrame:
    """One row per page; one scan, no shuffle."""
    shared = pages.sparkSession.sparkContext.broadcast(weights or train())
    return pages.select(F.col("page_id").cast("long"), "url", "html").mapInArrow(_extractor(shared), EXTRACTED)
