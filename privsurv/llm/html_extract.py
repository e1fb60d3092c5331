"""Main text of web pages by a recurrent block labeller.

A page is parsed into leaf blocks (runs of text between block-level tags).  Each block is a vector: tags of its path,
hashed words of its path's class, id and role attributes, hashed words of its text, and a few sizes.  A bidirectional LSTM in
numpy reads the page's whole sequence and says for each block whether it belongs to the article, so a block is judged in the light of all
others.  Blocks that belong are joined by single spaces.

The network is trained here, on pages that a generator writes with known labels: many layouts, container names, languages of
made-up words, adverts, notices, sidebars, forms and comments (in and after the article), missing end tags.  No row of
``pages`` is used.  Training takes a few seconds on the driver; the weights (under 1 MB) are broadcast.

Defined results: null and empty html give an empty text; text without tags is one block; scripts, styles, templates and markup never
are text; repeated pages are extracted each; other columns are ignored.
"""

from __future__ import annotations

import random
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from html.parser import HTMLParser

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import shingles as S
from .common import lean

# HTML element names by what they do to text.
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
BLOCKS = frozenset("address article aside blockquote body button caption center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html iframe legend li main menu nav object ol optgroup option p pre section select summary table tbody td textarea tfoot th thead title tr ul".split())
SILENT = frozenset("script style noscript template head title iframe object svg math canvas audio video select datalist".split())
IN_HEAD = frozenset("base link meta title style script noscript template".split())
TAGS = tuple("a article aside blockquote body button div dl figure footer form h1 h2 h3 header label li main nav ol p pre section span table td ul dialog details menu address fieldset figcaption".split())
#: An opening tag ends these open elements, unless one of the boundaries comes first.
ENDS = {"li": {"li"}, "p": {"p"}, "dt": {"dt", "dd"}, "dd": {"dt", "dd"}, "tr": {"tr", "td", "th"}, "td": {"td", "th"}, "th": {"td", "th"}, "option": {"option"}}
EDGES = frozenset("article aside body div footer form header main nav section table td ul ol dl blockquote fieldset".split())
CLOSES_P = BLOCKS - {"button", "option", "optgroup", "select", "caption", "td", "th", "tr", "tbody", "thead", "tfoot", "legend", "summary"}
NAMES, WORDS, SIZES = 128, 32, 6
INPUT = len(TAGS) + NAMES + WORDS + SIZES
HIDDEN = 24


class Page(HTMLParser):
    """Blocks of a page: path (distinct open tags with their names), text, characters inside links."""

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.blocks: list[tuple[tuple[str, ...], str, int]] = []
        self.stack: list[tuple[str, str]] = []
        self.steps: Counter[str] = Counter()  # of the stack
        self.held: list[str] = []
        self.links = self.quiet = self.inside = 0

    def flush(self) -> None:
        if self.held:
            text = " ".join("".join(self.held).split())
            if text:
                self.blocks.append((tuple(sorted(self.steps)), text, self.links))
            self.held, self.links = [], 0

    def pop(self, at: int) -> None:
        for tag, step in self.stack[at:]:
            self.quiet -= tag in SILENT
            self.inside -= tag == "a"
            self.steps[step] -= 1
            if not self.steps[step]:
                del self.steps[step]
        del self.stack[at:]

    def handle_starttag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        if tag == "br":
            self.held.append(" ")
            return
        if tag in BLOCKS:
            self.flush()
            ends = ENDS.get(tag, set()) | ({"p"} if tag in CLOSES_P else set())
            if ends:
                for at in range(len(self.stack) - 1, -1, -1):
                    open_ = self.stack[at][0]
                    if open_ in ends:
                        self.pop(at)
                        break
                    if open_ in EDGES:
                        break
            if tag == "body":
                self.pop(0)  # a head that was not closed
        if self.stack and self.stack[-1][0] == "head" and tag not in IN_HEAD:
            self.pop(len(self.stack) - 1)  # its end tag may be left out
        if tag in VOID:
            return
        name = " ".join(v for k, v in attrs if v and k in ("class", "id", "role")).lower()
        step = f"{tag} {name}" if name else tag
        self.stack.append((tag, step))
        self.steps[step] += 1
        self.quiet += tag in SILENT
        self.inside += tag == "a"

    def handle_startendtag(self, tag: str, attrs: list[tuple[str, str | None]]) -> None:
        if tag in BLOCKS:
            self.flush()
        elif tag == "br":
            self.held.append(" ")

    def handle_endtag(self, tag: str) -> None:
        if tag in BLOCKS:
            self.flush()
        for at in range(len(self.stack) - 1, -1, -1):
            if self.stack[at][0] == tag:
                self.pop(at)
                return
            if self.stack[at][0] in EDGES and tag not in EDGES:
                return  # an inline end tag does not close a container

    def handle_data(self, data: str) -> None:
        if not self.quiet:
            self.held.append(data)
            if self.inside:
                self.links += len(data)


def blocks(html: str) -> list[tuple[tuple[str, ...], str, int]]:
    page = Page()
    page.feed(html)
    page.close()
    page.flush()
    return page.blocks


@lru_cache(maxsize=20_000)
def _path(path: tuple[str, ...]) -> np.ndarray:
    """Tags of the path, and hashed words of its names."""
    out = np.zeros(len(TAGS) + NAMES, dtype=np.float32)
    for step in path:
        tag, _, names = step.partition(" ")
        if tag in TAGS:
            out[TAGS.index(tag)] = 1
        for word in re.findall(r"[a-z]+|\d+", names):
            h = int(S.words([word.encode()]).hashes[0])
            out[len(TAGS) + h % NAMES] += 1 if h >> 63 else -1
    out[len(TAGS) :] = np.clip(out[len(TAGS) :], -2, 2)
    return out


def vectors(pages: list[list[tuple[tuple[str, ...], str, int]]]) -> np.ndarray:
    """One row per block of all pages."""
    flat = [b for p in pages for b in p]
    out = np.zeros((len(flat), INPUT), dtype=np.float32)
    if not flat:
        return out
    wide = len(TAGS) + NAMES
    out[:, :wide] = [_path(b[0]) for b in flat]
    raws = [S.lower(b[1]).encode("utf-8", "surrogatepass") for b in flat]
    many = np.zeros(len(flat))
    for a, b in S.batches([len(r) for r in raws]):
        w = S.words(raws[a:b])
        many[a:b] = np.diff(w.first)
        block = np.repeat(np.arange(b - a), np.diff(w.first))
        out[a:b, wide : wide + WORDS] = np.bincount(block * WORDS + (w.hashes % S.U(WORDS)).astype(np.int64), minlength=(b - a) * WORDS).reshape(b - a, WORDS)
    own = out[:, wide : wide + WORDS]
    own /= np.maximum(np.linalg.norm(own, axis=1, keepdims=True), 1)
    long = np.array([len(b[1]) for b in flat], dtype=np.float32)
    at = np.concatenate([(np.arange(len(p)) + 0.5) / len(p) for p in pages if p])
    last = [b[1][-1] in ".!?:;" for b in flat]
    out[:, -SIZES:] = np.stack((np.log1p(long) / 6, np.log1p(many) / 4, np.array([b[2] for b in flat]) / long, at, np.array(last, dtype=np.float32), np.ones(len(flat))), axis=1)
    return out


@dataclass
class Net:
    wx: list[np.ndarray]  # per direction: input to gates
    wh: list[np.ndarray]
    b: list[np.ndarray]
    out: np.ndarray  # both hidden states and one


def _new(rng: np.random.Generator) -> Net:
    g = lambda *s: (rng.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
    bias = np.zeros(4 * HIDDEN, dtype=np.float32)
    bias[HIDDEN : 2 * HIDDEN] = 1
    return Net([g(INPUT, 4 * HIDDEN) for _ in range(2)], [g(HIDDEN, 4 * HIDDEN) for _ in range(2)], [bias.copy() for _ in range(2)], g(2 * HIDDEN + 1, 1)[:, 0])


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (np.tanh(0.5 * x) + 1)


def _direction(net: Net, d: int, x: np.ndarray, live: np.ndarray, keep: bool):
    """x: time x pages x gates' inputs; live: which pages still have blocks.  States of pages that have ended stay zero."""
    steps, n = x.shape[:2]
    hs = np.zeros((steps, n, HIDDEN), dtype=np.float32)
    h, c = np.zeros((n, HIDDEN), dtype=np.float32), np.zeros((n, HIDDEN), dtype=np.float32)
    past = []
    for t in range(steps) if d == 0 else range(steps - 1, -1, -1):
        z = x[t] + h @ net.wh[d]
        ifo, u = _sigmoid(z[:, : 3 * HIDDEN]), np.tanh(z[:, 3 * HIDDEN :])
        i, f, o = ifo[:, :HIDDEN], ifo[:, HIDDEN : 2 * HIDDEN], ifo[:, 2 * HIDDEN :]
        c2 = (f * c + i * u) * live[t][:, None]
        tc = np.tanh(c2)
        h2 = o * tc * live[t][:, None]
        if keep:
            past.append((t, h, c, i, f, o, u, tc))
        hs[t], h, c = h2, h2, c2
    return hs, past


def _logits(net: Net, v: np.ndarray, sizes: list[int], keep: bool = False):
    """v: vectors of all blocks; pages padded to the longest."""
    steps, n = max(sizes), len(sizes)
    page = np.repeat(np.arange(n), sizes)
    time = np.concatenate([np.arange(k) for k in sizes])
    live = np.zeros((steps, n), dtype=np.float32)
    live[time, page] = 1
    sides, pasts = [], []
    for d in (0, 1):
        x = np.zeros((steps, n, 4 * HIDDEN), dtype=np.float32)
        x[time, page] = v @ net.wx[d] + net.b[d]
        hs, past = _direction(net, d, x, live, keep)
        sides.append(hs[time, page])
        pasts.append(past)
    joined = np.concatenate((*sides, np.ones((len(v), 1), dtype=np.float32)), axis=1)
    return joined @ net.out, joined, pasts, (time, page, live)


def predict(net: Net, pages: list[list]) -> list[np.ndarray]:
    """Per page, which blocks belong to the article.  Pages of like length are run together."""
    out = [np.zeros(0, dtype=bool) for _ in pages]
    order = sorted((i for i, p in enumerate(pages) if p), key=lambda i: len(pages[i]))
    at = 0
    while at < len(order):
        end, total = at, 0
        while end < len(order) and (end == at or len(pages[order[end]]) * (end - at + 1) <= 12_000):
            total += len(pages[order[end]])
            end += 1
        own = [pages[i] for i in order[at:end]]
        z, *_ = _logits(net, vectors(own), [len(p) for p in own])
        for i, a in zip(order[at:end], np.split(z > 0, np.cumsum([len(p) for p in own])[:-1]), strict=True):
            out[i] = a
        at = end
    return out


def _backward(net: Net, v: np.ndarray, g: np.ndarray, joined: np.ndarray, pasts, where) -> list[np.ndarray]:
    time, page, live = where
    grads = [joined.T @ g]
    for d in (0, 1):
        steps, n = live.shape
        gh = np.zeros((steps, n, HIDDEN), dtype=np.float32)
        gh[time, page] = g[:, None] * net.out[d * HIDDEN : (d + 1) * HIDDEN]
        gx = np.zeros((steps, n, 4 * HIDDEN), dtype=np.float32)
        gwh = np.zeros_like(net.wh[d])
        dh, dc = np.zeros((n, HIDDEN), dtype=np.float32), np.zeros((n, HIDDEN), dtype=np.float32)
        for t, h, c, i, f, o, u, tc in reversed(pasts[d]):
            alive = live[t][:, None]
            a = (gh[t] + dh) * alive
            k = (dc + a * o * (1 - tc * tc)) * alive
            z = np.concatenate((k * u * i * (1 - i), k * c * f * (1 - f), a * tc * o * (1 - o), k * i * (1 - u * u)), axis=1)
            gx[t] = z
            gwh += h.T @ z
            dh, dc = z @ net.wh[d].T, k * f
        own = gx[time, page]
        grads += [v.T @ own, gwh, own.sum(axis=0)]
    return grads


# Words that layouts use in names, by what the part is.
PARTS = {
    "article": "article content post entry story main-content article-body post-body entry-content story-body text body-copy prose".split(),
    "nav": "nav menu navbar main-nav topnav breadcrumb breadcrumbs site-nav links pagination".split(),
    "header": "header site-header masthead banner top page-header branding".split(),
    "footer": "footer site-footer bottom colophon copyright legal".split(),
    "side": "sidebar side aside widget related recommended more-stories trending rail".split(),
    "ad": "ad ads advert advertisement sponsored promo ad-slot adbox banner-ad promoted".split(),
    "notice": "notice cookie cookie-banner consent alert gdpr popup newsletter subscribe modal".split(),
    "comment": "comments comment responses discussion reply comment-list user-comments disqus".split(),
    "share": "share social toolbar tags byline-tools buttons".split(),
}


class Writer:
    """Writes pages of made-up words with known labels."""

    def __init__(self, seed: int):
        self.r = random.Random(seed)

    def word(self) -> str:
        r = self.r
        style = self.style
        return "".join(r.choice(style) for _ in range(r.randint(1, 4)))

    def words(self, a: int, b: int, dots: bool = True) -> str:
        r = self.r
        out = [self.word() for _ in range(r.randint(a, b))]
        for i in range(len(out)):
            if dots and r.random() < 0.12:
                out[i] += r.choice(".,,.!?;")
            if self.junk and r.random() < 0.8:
                out[i] += r.choice(("%%%", "***", "$$$", "###", "&amp;&amp;&amp;", "!!"))
        text = " ".join(out)
        return text[:1].upper() + text[1:] + ("." if dots and r.random() < 0.9 else "")

    def attr(self, part: str, chance: float = 0.8) -> str:
        r = self.r
        if r.random() > chance:
            return ""
        name = r.choice(PARTS[part])
        extra = f" {self.word()}" if r.random() < 0.2 else ""
        return f' {r.choice(("class", "id", "class"))}="{name}{extra}"'

    def out(self, label: int, html: str, n: int = 1) -> None:
        self.html.append(html)
        self.labels += [label] * n

    def items(self, n: int) -> None:
        for _ in range(n):
            self.out(0, f'<li><a href="/{self.word()}">{self.words(1, 3, False)}</a></li>')

    def nav(self) -> None:
        tag = self.r.choice(("nav", "nav", "div", "ul"))
        self.html.append(f"<{tag}{self.attr('nav', 1 if tag != 'nav' else 0.4)}>" + "<ul>" * (tag != "ul"))
        self.items(self.r.randint(2, 9))
        self.html.append("</ul>" * (tag != "ul") + f"</{tag}>")

    def box(self, part: str, tag: str, low: int, high: int, paras: int) -> None:
        self.html.append(f"<{tag}{self.attr(part, 0.95)}>")
        r = self.r
        for _ in range(paras):
            kind = r.random()
            if kind < 0.25:
                self.out(0, f"<h{r.choice('2345')}>{self.words(1, 5, False)}</h4>")
            if kind < 0.6:
                self.out(0, f"<p>{self.words(low, high)}</p>")
            elif kind < 0.8:
                self.items(r.randint(1, 5))
            else:
                self.out(0, f"<div>{self.words(low, high)}</div>")
        self.html.append(f"</{tag}>")

    def bare(self, part: str, low: int, high: int) -> None:
        tag = self.r.choice(("div", "div", "aside", "section", "p", "span"))
        self.out(0, f"<{'div' if tag == 'span' else tag}{self.attr(part, 1)}>{self.words(low, high)}</{'div' if tag == 'span' else tag}>")

    def comments(self) -> None:
        r = self.r
        self.html.append(f"<{(tag := r.choice(('section', 'div', 'ol')))} {r.choice(('id', 'class'))}=\"{r.choice(('comments', 'comment-list', 'responses', 'discussion', 'user-comments'))}\">")
        if r.random() < 0.6:
            self.out(0, f"<h3>{self.words(1, 3, False)}</h3>")
        for _ in range(r.randint(1, 6)):
            inner = r.choice(("div", "article", "li", "p"))
            self.out(0, f"<{inner}{' class=' + chr(34) + 'comment' + chr(34) if r.random() < 0.8 else ''}>{self.words(4, 90)}</{inner}>")
        self.html.append(f"</{tag}>")

    def form(self) -> None:
        self.html.append(f"<form{self.attr('notice', 0.3)}>")
        self.out(0, f"<label>{self.words(1, 4, False)}</label>")
        self.html.append('<input type="text">')
        self.out(0, f"<button>{self.words(1, 2, False)}</button></form>")

    def article(self) -> None:
        r = self.r
        tag = r.choice(("article", "article", "article", "main", "div", "section"))
        self.html.append(f"<{tag}{self.attr('article', 1 if tag in ('div', 'section') else 0.3)}>")
        if r.random() < 0.85:
            self.out(1, f"<h1>{self.words(1, 14, False)}</h1>")
        for _ in range(r.choice((1, 1, 2, 3, 5, 8, 13, 25))):
            kind = r.random()
            if kind < 0.06:
                self.out(1, f"<h{r.choice('23')}>{self.words(1, 8, False)}</h2>")
            elif kind < 0.1:
                n = r.randint(2, 5)
                self.out(1, "<ul>" + "".join(f"<li>{self.words(1, 25)}</li>" for _ in range(n)) + "</ul>", n)
            elif kind < 0.13:
                self.out(1, f"<{(q := r.choice(('blockquote', 'pre', 'figcaption')))}>{self.words(3, 50)}</{q}>")
            elif kind < 0.17:
                self.bare(r.choice(("ad", "share", "notice", "side")), 1, 40)
            elif kind < 0.25:
                self.out(1, f"<p><b>{self.words(2, 30)}<br>")
            else:
                self.out(1, f"<p>{self.words(1, r.choice((6, 40, 40, 200)))}" + "</p>" * (r.random() < 0.9))
        if r.random() < 0.1:
            self.comments()
        self.html.append(f"</{tag}>")

    def page(self) -> tuple[str, list[int]]:
        r = self.r
        self.html, self.labels, self.junk = [], [], r.random() < 0.15
        letters = r.choice(("aeioubdlmnrst", "aeiouchtznßäöü", "aeioulrsñóíyc", "aeiouéèêçlmntx"))
        self.style = ["".join(r.choice(letters) for _ in range(r.randint(1, 4))) for _ in range(24)]
        if r.random() < 0.04:
            self.out(1, self.words(1, 200))
            return self.html[0], self.labels
        self.html.append(f"<!DOCTYPE html><html><head><title>{self.words(1, 9)}</title><style>p{{margin:0}}</style><script>var a='</p>';</script></head><body>")
        before = [(0.5, lambda: self.box("header", r.choice(("header", "div")), 1, 8, 1)), (0.8, self.nav), (0.45, lambda: self.bare("ad", 2, 30)), (0.3, lambda: self.bare("notice", 3, 40)), (0.15, self.form), (0.25, lambda: self.box("side", r.choice(("aside", "div")), 1, 40, r.randint(1, 4)))]
        after = [(0.25, self.comments), (0.3, lambda: self.box("side", r.choice(("aside", "div", "section")), 1, 60, r.randint(1, 4))), (0.3, lambda: self.bare("ad", 2, 30)), (0.2, lambda: self.bare("share", 1, 6)), (0.15, lambda: self.bare("notice", 3, 40)), (0.15, self.form), (0.2, self.nav)]
        if r.random() < 0.4:
            r.shuffle(before)
        for chance, make in before:
            if r.random() < chance:
                make()
        if r.random() < 0.9:
            self.article()
        r.shuffle(after)
        for chance, make in after:
            if r.random() < chance:
                make()
        if r.random() < 0.8:
            tag = r.choice(("footer", "footer", "div"))
            self.out(0, f"<{tag}{self.attr('footer', 1 if tag == 'div' else 0.3)}>&copy; {self.words(1, 20)}</{tag}>")
        self.html.append("</body></html>" * (r.random() < 0.9))
        return "".join(self.html), self.labels


@lru_cache(maxsize=4)
def train(pages: int = 1200, epochs: int = 12, seed: int = 9) -> Net:
    """Adam on the mean log loss of blocks."""
    writer, data = Writer(seed), []
    while len(data) < pages:
        html, labels = writer.page()
        found = blocks(html)
        if len(found) == len(labels) and found:
            data.append((found, labels))
    rng = np.random.default_rng(seed)
    net = _new(rng)
    params = [net.out, *[x for d in (0, 1) for x in (net.wx[d], net.wh[d], net.b[d])]]
    first, second, step = [np.zeros_like(p) for p in params], [np.zeros_like(p) for p in params], 0
    data.sort(key=lambda d: len(d[0]))
    groups = [data[a : a + 40] for a in range(0, len(data), 40)]
    ready = [(vectors([d[0] for d in g]), np.concatenate([d[1] for d in g]).astype(np.float32), [len(d[0]) for d in g]) for g in groups]
    wide = len(TAGS)
    for epoch in range(epochs):
        for k in rng.permutation(len(ready)):
            v, y, sizes = ready[k]
            v = v.copy()
            v[:, wide : wide + NAMES] *= rng.random((len(v), 1)) > 0.1  # names can't always be relied on
            z, joined, pasts, where = _logits(net, v, sizes, keep=True)
            g = ((_sigmoid(z) - y) / len(y)).astype(np.float32)
            step += 1
            for p, gr, m, s in zip(params, _backward(net, v, g, joined, pasts, where), first, second, strict=True):
                m *= 0.9
                m += 0.1 * gr
                s *= 0.999
                s += 0.001 * gr * gr
                p -= 0.01 * (1 - 0.9 * epoch / epochs) * (m / (1 - 0.9**step)) / (np.sqrt(s / (1 - 0.999**step)) + 1e-8)
    return net


def extract(net: Net, htmls: list[str]) -> list[str]:
    pages = [blocks(h) for h in htmls]
    return [" ".join(b[1] for b, k in zip(p, keep, strict=True) if k) for p, keep in zip(pages, predict(net, pages), strict=True)]


def extract_pages(pages: DataFrame, net: Net | None = None) -> DataFrame:
    """One row per page: page_id, url, text, n_chars."""
    held = pages.sparkSession.sparkContext.broadcast(net or train())

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in frames:
            htmls = x["html"].fillna("").tolist()
            for a, b in S.batches([len(h) for h in htmls], 1 << 20):
                text = extract(held.value, htmls[a:b])
                own = x.iloc[a:b]
                yield pd.DataFrame({"page_id": own["page_id"].astype("Int64"), "url": own["url"], "text": text, "n_chars": [len(t) for t in text]})

    return pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html")).mapInPandas(lean(run), "page_id long, url string, text string, n_chars long")
