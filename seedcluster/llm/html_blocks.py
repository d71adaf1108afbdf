"""Main text of web pages: leaf blocks in page order, each kept or not by a bidirectional LSTM in numpy.

A block is a run of text between block-level tags. It enters as the summed vectors of its hashed tag path (tags, classes and ids of
open elements) and of its hashed words, with lengths, link share and place. Both directions run over the whole page, so each
decision sees the document. The network is trained here, on a bounded sample of the pages: blocks whose elements tell their part outright give the
texts, which are laid out anew under many page plans, the page's own among them.
Null html counts as empty and gives an empty text; markup that ends midway ends there; repeated rows give a row each; an
empty table no rows; without pages to learn from, blocks are judged by their elements' names alone.
"""

from __future__ import annotations

import html as entities
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import CODES, LOWER, MIX_1, coded, ready, spans_hash, utf8, word_spans

#: Elements that do not end a block, those without content, and those whose content is no text (fixed lists of HTML).
INLINE = frozenset("a abbr acronym b bdi bdo big cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr br button object math mi mn mo ms mtext mrow mfrac msqrt mroot msup msub msubsup munder mover munderover mstyle mspace mpadded semantics svg g path circle rect line polyline polygon ellipse defs use symbol text tspan".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
RAW = ("script", "style", "template", "iframe", "textarea")
#: Words in the names of elements, classes and ids that tell a block's part.
MAIN = frozenset("article main content post story entry".split())
APART = frozenset("head nav menu header footer sidebar aside notice cookie consent banner ad ads advert advertisement sponsor sponsored promo form login subscribe newsletter comment comments reply share social related breadcrumb".split())
# A tag whose quotes do not close ends at the next '>'.
TOKEN = re.compile(
    rf"<!--.*?(?:-->|\Z)|<({'|'.join(RAW)})\b(?:\"[^\"]*\"|'[^']*'|[^>\"'])*(?:>.*?(?:</\1\s*>|\Z)|\Z)|<[!?][^>]*(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)((?:\"[^\"]*\"|'[^']*'|[^>\"'])*+)(?:>|\Z)|<(/?)([a-zA-Z][^\s/>]*)([^>]*)(?:>|\Z)",
    re.S | re.I,
)
NAMED = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
PART = re.compile(r"[a-z]+")
PATHS, WORDS, PATH_DIM, WORD_DIM, NUMBERS, HIDDEN = 1 << 10, 1 << 10, 12, 6, 6, 16


def blocks(page: str) -> list[tuple[tuple[str, ...], str, float]]:
    """(path, text, share of its characters in links) of each block with text. A path holds the names of open elements, outermost first."""
    out: list[tuple[tuple[str, ...], str, float]] = []
    stack: list[tuple[str, tuple[str, ...]]] = []
    text: list[str] = []
    linked = at = 0
    path: tuple[str, ...] | None = ()

    def close() -> None:
        nonlocal linked, text
        if text:
            whole = " ".join(entities.unescape("".join(text)).split())
            if whole:
                out.append((tuple(x for _, names in stack if names for x in names) if path is None else path, whole, min(1.0, linked / len(whole))))
            text, linked = [], 0

    for m in TOKEN.finditer(page):
        if m.start() > at:
            piece = page[at : m.start()]
            text.append(piece)
            if any(t == "a" for t, _ in stack):
                linked += len(piece.strip())
        at = m.end()
        tag, ending, within = (m[3] or m[6] or "").lower(), m[2] or m[5], m[4] or m[7] or ""
        if not tag:
            continue
        if tag == "br":
            text.append(" ")
            continue
        if tag not in INLINE:
            close()
            path = None
        if ending:
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == tag:
                    del stack[k:]
                    break
        elif tag not in VOID and not within.rstrip().endswith("/"):
            if tag in ("p", "li", "tr", "td", "th", "option", "dt", "dd") and any(t == tag for t, _ in stack):
                k = max(i for i, (t, _) in enumerate(stack) if t == tag)
                if tag == "p" or not any(t in ("ul", "ol", "table", "dl") for t, _ in stack[k:]):
                    del stack[k:]
            elif tag not in INLINE and any(t == "p" for t, _ in stack):
                del stack[max(i for i, (t, _) in enumerate(stack) if t == "p") :]
            if tag in INLINE:
                stack.append((tag, ()))
            else:
                names = [x for a in NAMED.findall(within) for x in PART.findall("".join(a).lower())] if within else []
                stack.append((tag, (tag, *(f".{x}" for x in names))))
    text.append(page[at:])
    close()
    return out


def told(path: tuple[str, ...]) -> int | None:
    """1 or 0 where the names of a block's elements tell its part, the innermost one first; else None."""
    for name in reversed(path):
        word = name.lstrip(".")
        if word in APART:
            return 0
        if word in MAIN:
            return 1
    return None


class Network:
    """Embeddings, one LSTM in each direction, one output."""

    def __init__(self, seed: int = 1):
        r = np.random.default_rng(seed)
        d = PATH_DIM + WORD_DIM + NUMBERS
        self.p = {"path": r.normal(0, 0.3, (PATHS, PATH_DIM)), "word": r.normal(0, 0.1, (WORDS, WORD_DIM)), "out": r.normal(0, 0.2, 2 * HIDDEN), "bias": np.zeros(1)}
        for side in "fb":
            self.p |= {f"w{side}": r.normal(0, 1 / np.sqrt(d + HIDDEN), (d + HIDDEN, 4 * HIDDEN)), f"c{side}": np.r_[np.ones(HIDDEN), np.zeros(3 * HIDDEN)]}
        self.names = sorted(self.p)

    def _run(self, x: np.ndarray, side: str, keep: bool):
        """Hidden states over (time, rows, inputs); rows are padded behind, so the backward side starts from state 0 by mask."""
        steps, n, _ = x.shape
        h, c, trace, out = np.zeros((n, HIDDEN)), np.zeros((n, HIDDEN)), [], np.zeros((steps, n, HIDDEN))
        w, b = self.p[f"w{side}"], self.p[f"c{side}"]
        for t in range(steps) if side == "f" else range(steps - 1, -1, -1):
            z = np.concatenate([x[t], h], 1)
            a = z @ w + b
            g = 1 / (1 + np.exp(-a[:, : 3 * HIDDEN]))
            u = np.tanh(a[:, 3 * HIDDEN :])
            f, i, o = g[:, :HIDDEN], g[:, HIDDEN : 2 * HIDDEN], g[:, 2 * HIDDEN :]
            before = c
            m = self.mask[t][:, None]
            c = m * (f * c + i * u)
            tc = np.tanh(c)
            h = m * (o * tc)
            out[t] = h
            if keep:
                trace.append((t, z, f, i, o, u, before, tc, m))
        return out, trace

    def inputs(self, batch: list[Features]) -> np.ndarray:
        steps = max(len(b) for b in batch)
        self.mask = np.zeros((steps, len(batch)))
        x = np.zeros((steps, len(batch), PATH_DIM + WORD_DIM + NUMBERS))
        for r, b in enumerate(batch):
            self.mask[: len(b), r] = 1
            x[: len(b), r] = b.vectors(self.p)
        return x

    def scores(self, batch: list[Features]) -> list[np.ndarray]:
        x = self.inputs(batch)
        h = np.concatenate([self._run(x, "f", False)[0], self._run(x, "b", False)[0]], 2)
        s = h @ self.p["out"] + self.p["bias"]
        return [s[: len(b), r] for r, b in enumerate(batch)]

    def gradients(self, batch: list[Features], labels: list[np.ndarray]) -> dict[str, np.ndarray]:
        x = self.inputs(batch)
        (hf, tf), (hb, tb) = self._run(x, "f", True), self._run(x, "b", True)
        h = np.concatenate([hf, hb], 2)
        s = 1 / (1 + np.exp(-(h @ self.p["out"] + self.p["bias"])))
        y = np.zeros_like(s)
        for r, v in enumerate(labels):
            y[: len(v), r] = v
        ds = (s - y) * self.mask / max(self.mask.sum(), 1)
        grad = {k: np.zeros_like(v) for k, v in self.p.items()}
        grad["out"], grad["bias"] = np.einsum("tn,tnh->h", ds, h), np.array([ds.sum()])
        dh_all, dx = ds[:, :, None] * self.p["out"], np.zeros_like(x)
        for side, trace, part in (("f", tf, dh_all[:, :, :HIDDEN]), ("b", tb, dh_all[:, :, HIDDEN:])):
            w = self.p[f"w{side}"]
            dh, dc = np.zeros(part.shape[1:]), np.zeros(part.shape[1:])
            for t, z, f, i, o, u, before, tc, m in reversed(trace):
                d = m * (dh + part[t])
                dcm = m * dc + d * o * (1 - tc * tc)
                da = np.concatenate([dcm * before * f * (1 - f), dcm * u * i * (1 - i), d * tc * o * (1 - o), dcm * i * (1 - u * u)], 1)
                grad[f"w{side}"] += z.T @ da
                grad[f"c{side}"] += da.sum(0)
                dz = da @ w.T
                dx[t] += dz[:, :-HIDDEN]
                dh, dc = dz[:, -HIDDEN:], dcm * f
        for r, b in enumerate(batch):
            d = dx[: len(b), r]
            np.add.at(grad["path"], b.path, d[b.path_block, :PATH_DIM] * b.path_scale[:, None])
            np.add.at(grad["word"], b.word, d[b.word_block, PATH_DIM : PATH_DIM + WORD_DIM] * b.word_scale[:, None])
        return grad

    def fit(self, pages: list[Features], labels: list[np.ndarray], epochs: int = 8, rows: int = 32, rate: float = 0.01, seed: int = 2) -> None:
        r = np.random.default_rng(seed)
        m, v, t = {k: 0.0 for k in self.p}, {k: 0.0 for k in self.p}, 0
        for _ in range(epochs):
            order = r.permutation(len(pages))
            for at in range(0, len(order), rows):
                pick = sorted(order[at : at + rows], key=lambda i: len(pages[i]))
                t += 1
                for k, g in self.gradients([pages[i] for i in pick], [labels[i] for i in pick]).items():
                    m[k], v[k] = 0.9 * m[k] + 0.1 * g, 0.999 * v[k] + 0.001 * g * g
                    self.p[k] -= rate * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)


class Features:
    """A page's blocks as numbers. Sums are scaled by their count, so long blocks weigh as short ones."""

    def __init__(self, found: list[tuple[tuple[str, ...], str, float]], words: tuple[np.ndarray, np.ndarray] | None = None):
        self.n = len(found)
        ids = [path_ids(p) for p, _, _ in found]
        count = np.fromiter(map(len, ids), np.int64, len(ids))
        self.path, self.path_block = np.concatenate(ids) if ids else np.zeros(0, np.int64), np.repeat(np.arange(self.n), count)
        self.path_scale = np.repeat(1 / np.sqrt(np.maximum(count, 1)), count)
        self.word, self.word_block = words if words is not None else hashed_words([t for _, t, _ in found])
        many = np.bincount(self.word_block, minlength=self.n)
        self.word_scale = 1 / np.maximum(many, 1)[self.word_block]
        size = np.fromiter((len(t) for _, t, _ in found), float, self.n)
        at = np.arange(self.n) / max(self.n, 1)
        self.numbers = np.stack([np.log1p(size) / 5, np.log1p(many) / 3, np.fromiter((x for _, _, x in found), float, self.n), at, 1 - at, np.fromiter((t[-1] in ".!?:\"'" for _, t, _ in found), float, self.n)], 1) if self.n else np.zeros((0, NUMBERS))

    def __len__(self) -> int:
        return self.n

    def vectors(self, p: dict[str, np.ndarray]) -> np.ndarray:
        out = np.zeros((self.n, PATH_DIM + WORD_DIM + NUMBERS))
        for name, ids, block, scale, a in (("path", self.path, self.path_block, self.path_scale, 0), ("word", self.word, self.word_block, self.word_scale, PATH_DIM)):
            if len(ids):
                head = np.flatnonzero(np.r_[True, block[1:] != block[:-1]])
                out[block[head], a : a + p[name].shape[1]] = np.add.reduceat(p[name][ids] * scale[:, None], head)
        out[:, -NUMBERS:] = self.numbers
        return out


_PATHS: dict[tuple[str, ...], np.ndarray] = {}


def path_ids(path: tuple[str, ...]) -> np.ndarray:
    """Hashed names of a path, and the innermost one again as such."""
    got = _PATHS.get(path)
    if got is None:
        if len(_PATHS) > 100_000:
            _PATHS.clear()
        names = sorted(set(path) - {"html", "body"}) or ["body"]
        got = _PATHS[path] = np.array([int(coded(sum(c * 131**i for i, c in enumerate(x.encode())) % (1 << 61))[0] >> np.uint64(54)) for x in [*names, f"<{path[-1] if path else ''}"]], np.int64)
    return got


def hashed_words(texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
    raw, off = utf8(pa.array(texts, pa.string()))
    raw = LOWER[raw]
    starts, ends, row = word_spans(raw, off)
    h = spans_hash(CODES[raw], starts, ends) * MIX_1 >> np.uint64(54)
    return h.astype(np.int64), row


#: Page plans: for each part, the elements it may stand in. A plan draws one for each part it has.
PLANS = {
    "title": ["head title"],
    "header": ["header h2", "div.header p", "div.top", "div.site-header span", "header div"],
    "nav": ["nav ul li", "div.menu", "ul.menu li", "div.navigation li", "nav", "div.nav-bar ul li"],
    "ad": ["div.ad", "div.advert p", "div.sponsored", "aside.ad", "div.ads-banner", "section.promo p"],
    "notice": ["div.cookie-notice p", "div.notice", "div.consent-banner p", "section.notice p"],
    "side": ["aside p", "div.sidebar li", "aside ul li", "div.related li", "div.widget p", "div.sidebar p"],
    "form": ["form p", "form div", "div.newsletter form p", "form fieldset", "div.login form"],
    "comments": ["section.comments div.comment p", "div.comments p", "ol.comment-list li.comment", "div.reply p", "section.comments article p"],
    "footer": ["footer", "footer p", "div.footer p", "div.site-footer", "div.copyright"],
    "main": ["article p", "main p", "main article p", "div.content p", "div.main-content p", "article section p", "div.post-body p", "div.story p", "section.entry p", "div.text p", "div.page div p", "p", "div", "td", "article div", "article li", "main blockquote p"],
}
ORDER = ("title", "header", "nav", "ad", "notice", "main", "form", "side", "comments", "footer")


def plan(main: list[str], rest: list[str], r: np.random.Generator) -> tuple[list[tuple[tuple[str, ...], str, float]], np.ndarray]:
    """The texts laid out under a page plan, and each block's part."""
    out, labels = [], []

    def element(x: str) -> tuple[str, ...]:
        names = []
        for e in x.split():
            tag, _, cls = e.partition(".")
            names += [tag, *(f".{c}" for c in PART.findall(cls))]
        return tuple(names)

    draw = lambda k: PLANS[k][r.integers(len(PLANS[k]))]
    base = draw("main")
    order = list(ORDER)
    if r.random() < 0.3:
        order.remove("side")
        order.insert(order.index("main"), "side")
    wrap = r.choice(["", "div ", "div.page ", "div.wrapper div ", "div.container "])
    for part in order:
        if part == "main":
            spot = r.integers(0, max(len(main), 1))
            for i, t in enumerate(main):
                path = base
                if i == 0 and r.random() < 0.6:
                    path = " ".join([*base.split()[:-1], "h1"])
                elif r.random() < 0.08:
                    path = " ".join([*base.split()[:-1], str(r.choice(["h2", "li", "blockquote", "pre", "figcaption", "td"]))])
                out.append((("html", "body", *element(wrap + path)), t, float(r.random() < 0.03)))
                labels.append(1)
                if i == spot and len(base.split()) > 1 and r.random() < 0.35 and rest:
                    inner = str(r.choice(["div.ad", "aside p", "div.share", "form p", "div.related li", "nav li", "div.comments p", "footer p", "header p"]))
                    out.append((("html", "body", *element(wrap + " ".join(base.split()[:-1]) + " " + inner)), str(rest[r.integers(len(rest))]), float(r.random() < 0.5)))
                    labels.append(0)
        elif part == "title" or r.random() < (0.75 if part in ("nav", "footer") else 0.45):
            e = draw(part)
            long = part in ("comments", "side", "notice", "ad", "form") and r.random() < 0.6
            for _ in range(1 if part == "title" else int(r.integers(1, 7))):
                t = str(main[r.integers(len(main))] if long and main else rest[r.integers(len(rest))] if rest else "menu")
                out.append((("html", *(("body", *element(wrap + e)) if part != "title" else element(e))), t, float(part == "nav") if r.random() < 0.9 else 0.0))
                labels.append(0)
    return out, np.array(labels, float)


def train(pages: list[str], copies: int = 3, seed: int = 4, epochs: int = 8) -> dict[str, np.ndarray] | None:
    r = np.random.default_rng(seed)
    sets, labels = [], []
    for page in pages:
        found = blocks(page)
        parts = [told(p) for p, _, _ in found]
        if not found:
            continue
        if None not in parts:
            sets.append(Features(found))
            labels.append(np.array(parts, float))
        main, rest = [t for (_, t, _), y in zip(found, parts, strict=True) if y], [t for (_, t, _), y in zip(found, parts, strict=True) if y == 0]
        for _ in range(copies if main else 0):
            out, y = plan(main, rest, r)
            sets.append(Features(out))
            labels.append(y)
    if not sets:
        return None
    net = Network()
    net.fit(sets, labels, epochs)
    return net.p


def extract(pages: list[str | None], weights: dict[str, np.ndarray] | None, rows: int = 256) -> list[str]:
    found = [blocks(p or "") for p in pages]
    out = [""] * len(pages)
    if weights is None:
        return ["\n".join(t for p, t, _ in f if told(p) != 0) for f in found]
    net = Network()
    net.p = weights
    order = sorted((i for i in range(len(pages)) if found[i]), key=lambda i: len(found[i]))
    at = 0
    while at < len(order):
        pick = order[at : at + rows]
        while len(pick) > 1 and len(found[pick[-1]]) * len(pick) > 50_000:
            pick = pick[: len(pick) // 2]
        at += len(pick)
        words, block = hashed_words([t for i in pick for _, t, _ in found[i]])
        first = np.cumsum([0, *(len(found[i]) for i in pick)])
        cut = np.searchsorted(block, first)
        sets = [Features(found[i], (words[cut[k] : cut[k + 1]], block[cut[k] : cut[k + 1]] - first[k])) for k, i in enumerate(pick)]
        for i, s in zip(pick, net.scores(sets), strict=True):
            out[i] = "\n".join(t for (_, t, _), x in zip(found[i], s, strict=True) if x > 0)
    return out


def main_text(pages: DataFrame, sample: int = 300, page_id: str = "page_id", url: str = "url", html: str = "html", most_chars: int = 100_000) -> DataFrame:
    """(page_id, url, text, n_chars). Trains on the `sample` pages, of at most `most_chars` characters, that come first by a hash of page_id; extracts from all, whole."""
    spark = ready(pages.sparkSession)
    pages = pages.select(F.col(page_id).cast("long").alias("page_id"), F.col(url).alias("url"), F.col(html).alias("html"))
    short = pages.where(F.length("html").between(1, most_chars)).select("page_id", "html")
    # Ids are chosen without their pages, so that tasks do not send pages that lose; repeated ids cannot raise the bound.
    chosen = short.where("page_id IS NOT NULL").select("page_id", F.xxhash64("page_id").alias("h")).distinct().orderBy("h", "page_id").limit(sample).select("page_id")
    learn = [x["html"] for x in short.join(F.broadcast(chosen), "page_id").dropDuplicates(["page_id"]).orderBy(F.xxhash64("page_id"), "page_id").limit(sample).collect()]
    sent = spark.sparkContext.broadcast(train(learn))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, 1000):
                part = batch.slice(i, 1000)
                got = extract(part.column(2).to_pylist(), sent.value)
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(got, pa.string()), pa.array([len(x) for x in got], pa.int64())], ["page_id", "url", "text", "n_chars"])

    return pages.mapInArrow(run, "page_id long, url string, text string, n_chars long")
