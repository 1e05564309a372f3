"""Operator 9: main text of web pages by a recurrent block labeller.

A page is read into leaf blocks (runs of text between block-level tags) with their tag paths. Each block is a vector of hashed path
parts (tags, classes, ids), hashed words and a few numbers. A bidirectional LSTM in numpy reads the whole sequence of a page and
decides for every block whether it belongs to the article, using the context of the entire document.

Training is weakly supervised: the blocks of a bounded sample of whole pages (``sample`` rows, ``sample_bytes`` together) are labelled by their semantic tags,
and each page is varied with parts that the sample may lack (comments, sidebars, notices, forms, other containers for the article), so that
the network learns path vocabulary and order rather than one template.

A map over the scan; memory is one batch of pages. Scripts, styles, comments and tags never become text. Dropped elements
(svg, iframe, template and the like) that are empty or never closed lose their tag only; elements of any depth are closed in order. Edge cases: null and empty pages
give an empty text; unclosed or cut tags end with the page; a page of one enormous block is one step; repeated rows are labelled alike;
other columns are not read.
"""

from __future__ import annotations

import html as entities
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, chunks, table
from .decontam import LOWER, word_hashes, word_spans

#: Hold text only and run to the end of the page where they are not closed.
RAW = "script|style|textarea|title"
#: Dropped up to their closing tag; without one, or closed in itself, only the tag goes.
DROPPED = frozenset("noscript template svg iframe object canvas select".split())
CLOSING = {tag: re.compile(rf"</{tag}\s*>", re.I) for tag in DROPPED}
EMPTY = frozenset("svg object iframe canvas".split())
DEEPEST = 256  # path parts are read from so many outer elements
MARKUP = re.compile(r"<!--.*?(?:-->|\Z)|<(?P<raw>" + RAW + r")(?=[\s/>])[^>]*>.*?(?:</(?P=raw)\s*>|\Z)|<(?P<end>/?)(?P<tag>[a-zA-Z][^\s/>]*)(?P<attrs>(?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)>|<[!/?a-zA-Z][^>]*(?:>|\Z)", re.S | re.I)
ATTRIBUTE = re.compile(r"\b(class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s>]+))", re.I)
BLOCK = frozenset("address article aside blockquote body center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html li main menu nav ol p pre section summary table tbody td tfoot th thead tr ul".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
PART = re.compile(r"[^a-z0-9]+")
SPACE = re.compile(r"\s+")
PATHS, WORDS, NUMBERS = 160, 32, 5
WIDTH = PATHS + WORDS + NUMBERS


def blocks_of(page: str) -> list[tuple[tuple[str, ...], str, int]]:
    """(path parts, text, characters inside links) of each non-empty block in page order."""
    stack: list[tuple[str, tuple[str, ...]]] = []
    opened: Counter = Counter()  # of the tags in the stack
    unclosed: set[str] = set()  # dropped elements without a closing tag further on
    out, held, linked, done = [], [], 0, 0

    def flush():
        nonlocal held, linked
        if held:
            text = SPACE.sub(" ", "".join(held)).strip()
            if text:
                out.append((tuple(p for _, parts in stack[:DEEPEST] for p in parts), text, linked))
        held, linked = [], 0

    def take(raw: str):
        nonlocal linked
        if raw:
            text = entities.unescape(raw) if "&" in raw else raw
            held.append(text)
            if any(t == "a" for t, _ in stack[-4:]):
                linked += len(text)

    def cut(k: int):
        for t, _ in stack[k:]:
            opened[t] -= 1
        del stack[k:]

    while m := MARKUP.search(page, done):
        take(page[done : m.start()])
        done = m.end()
        tag = m.group("tag")
        if not tag:
            continue
        tag = tag.lower()
        if tag == "br":
            held.append(" ")
            continue
        attrs = m.group("attrs") or ""
        if tag in DROPPED and not m.group("end"):
            if tag in EMPTY and attrs.endswith("/"):
                continue
            close = None if tag in unclosed else CLOSING[tag].search(page, done)
            if close:
                done = close.end()
            else:
                unclosed.add(tag)
            continue
        block = tag in BLOCK
        if block:
            flush()
        if m.group("end"):
            for k in range(len(stack) - 1 if opened[tag] else -1, -1, -1):
                if stack[k][0] == tag:
                    cut(k)
                    break
                if stack[k][0] in ("article", "main", "body") and tag not in ("article", "main", "body", "html"):
                    break
            continue
        if tag in VOID:
            continue
        if block:
            # a new block ends open inline tags and an open paragraph
            while stack and (stack[-1][0] not in BLOCK or stack[-1][0] == "p" or stack[-1][0] == tag == "li"):
                cut(len(stack) - 1)
        parts = [tag]
        if attrs:
            for name, a, b, c in ATTRIBUTE.findall(attrs):
                parts += [f"{name.lower()}:{p}" for p in PART.split((a or b or c).lower()) if p]
        stack.append((tag, tuple(parts)))
        opened[tag] += 1
    take(page[done:])
    flush()
    return out


_SLOTS: dict[str, tuple[tuple[int, float], ...]] = {}


def slots(part: str) -> tuple[tuple[int, float], ...]:
    """Two places of a path part with their signs, so that hardly any two parts are alike."""
    found = _SLOTS.get(part)
    if found is None:
        h = zlib.crc32(part.encode())
        found = tuple((v % PATHS, 1.0 if v & 0x8000 else -1.0) for v in (h & 0xFFFF, h >> 16))
        if len(_SLOTS) < 100_000:
            _SLOTS[part] = found
    return found


def vectors(pages: list[list[tuple]]) -> np.ndarray:
    """One row for each block of the pages."""
    blocks = [(k, n, b) for page in pages for n in (len(page),) for k, b in enumerate(page)]
    x = np.zeros((len(blocks), WIDTH), np.float32)
    if not blocks:
        return x
    raw = [b[2][1].encode("utf-8", "replace") for b in blocks]
    data = LOWER[np.frombuffer(b"".join(raw), np.uint8)]
    bounds = np.concatenate([[0], np.cumsum([len(r) for r in raw])])
    starts, ends, first = word_spans(data, bounds)
    if len(starts):
        h = word_hashes(data, starts, ends)
        owner = np.repeat(np.arange(len(blocks)), np.diff(first))
        found = np.bincount(owner * WORDS + (h % np.uint64(WORDS)).astype(np.int64), minlength=len(blocks) * WORDS).reshape(-1, WORDS)
        x[:, PATHS : PATHS + WORDS] = found / np.maximum(1, found.sum(1, keepdims=True))
    known: dict[tuple, np.ndarray] = {}
    for i, (k, n, (path, text, linked)) in enumerate(blocks):
        row = known.get(path)
        if row is None:
            row = known[path] = np.zeros(PATHS, np.float32)
            for p in path:
                for at, sign in slots(p):
                    row[at] += sign
        x[i, :PATHS] = row
        size = len(text)
        x[i, PATHS + WORDS :] = (min(np.log1p(size) / 8, 1.5), min(1.0, linked / size), (k + 1) / n, text[-1] in ".!?", 1.0)
    np.clip(x, -3, 3, out=x)
    return x


class BiLstm:
    """Two LSTM layers over the block sequence, one for each direction, and a logistic output."""

    def __init__(self, hidden: int = 16, seed: int = 5):
        rng = np.random.default_rng(seed)
        self.h = hidden
        self.p = {}
        for d in "fb":
            self.p[f"x{d}"] = rng.normal(0, WIDTH**-0.5, (WIDTH, 4 * hidden))
            self.p[f"h{d}"] = rng.normal(0, hidden**-0.5, (hidden, 4 * hidden))
            self.p[f"c{d}"] = np.concatenate([np.zeros(hidden), np.ones(hidden), np.zeros(2 * hidden)])
        self.p |= {"o": rng.normal(0, 0.3, 2 * hidden), "d": np.zeros(1)}
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}

    def _run(self, z: np.ndarray, mask: np.ndarray, way: str, keep: bool):
        """z: time, batch, 4h inputs. States of the masked steps carry over."""
        t_max, n, _ = z.shape
        h, c = np.zeros((n, self.h), np.float32), np.zeros((n, self.h), np.float32)
        out, tape = np.zeros((t_max, n, self.h), np.float32), {}
        k = self.h
        for t in range(t_max) if way == "f" else range(t_max - 1, -1, -1):
            g = z[t] + h @ self.p[f"h{way}"]
            gates = 1 / (1 + np.exp(-g[:, : 3 * k]))
            new = np.tanh(g[:, 3 * k :])
            i, f, o = gates[:, :k], gates[:, k : 2 * k], gates[:, 2 * k :]
            c2 = f * c + i * new
            tc = np.tanh(c2)
            h2 = o * tc
            m = mask[t][:, None]
            if keep:
                tape[t] = (h, c, i, f, o, new, tc, m)
            h, c = np.where(m, h2, h), np.where(m, c2, c)
            out[t] = h
        return out, tape

    def forward(self, x: np.ndarray, mask: np.ndarray, keep: bool = False):
        runs = {w: self._run(x @ self.p[f"x{w}"] + self.p[f"c{w}"], mask, w, keep) for w in "fb"}
        h = np.concatenate([runs["f"][0], runs["b"][0]], 2)
        return 1 / (1 + np.exp(-(h @ self.p["o"] + self.p["d"]))), h, runs

    def step(self, x, mask, y):
        q, h, runs = self.forward(x, mask, True)
        dz = (q - y) * mask / max(1, mask.sum())
        loss = -(np.log(np.where(y > 0, q, 1 - q) + 1e-9) * mask).sum() / max(1, mask.sum())
        g = {"o": np.einsum("tb,tbh->h", dz, h), "d": np.array([dz.sum()])}
        dh_all = dz[:, :, None] * self.p["o"]
        k, t_max = self.h, len(x)
        for w, part in (("f", dh_all[:, :, :k]), ("b", dh_all[:, :, k:])):
            tape = runs[w][1]
            g[f"x{w}"], g[f"h{w}"], g[f"c{w}"] = (np.zeros_like(self.p[f"{n}{w}"]) for n in "xhc")
            dh, dc = np.zeros_like(part[0]), np.zeros_like(part[0])
            for t in range(t_max - 1, -1, -1) if w == "f" else range(t_max):
                h0, c0, i, f, o, new, tc, m = tape[t]
                dh = dh + part[t]
                own, dcm = dh * m, dc * m
                dct = dcm + own * o * (1 - tc**2)
                dg = np.concatenate([dct * new * i * (1 - i), dct * c0 * f * (1 - f), own * tc * o * (1 - o), dct * i * (1 - new**2)], 1)
                g[f"x{w}"] += x[t].T @ dg
                g[f"h{w}"] += h0.T @ dg
                g[f"c{w}"] += dg.sum(0)
                dh = dg @ self.p[f"h{w}"].T + dh * ~m
                dc = dct * f + dc * ~m
        return float(loss), g

    def fit(self, pages, labels, epochs: int = 8, batch: int = 16, rate: float = 0.01, seed: int = 5) -> "BiLstm":
        rng = np.random.default_rng(seed)
        order = [k for k in range(len(pages)) if pages[k]]
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v = {k: np.zeros_like(w) for k, w in self.p.items()}
        t = 0
        for epoch in range(epochs):
            order = sorted(rng.permutation(order).tolist(), key=lambda k: len(pages[k]) // 8)
            groups = [order[a : a + batch] for a in range(0, len(order), batch)]
            for g_at in rng.permutation(len(groups)):
                own = groups[g_at]
                x, mask, _ = padded([pages[k] for k in own])
                y = np.zeros(mask.shape, np.float32)
                for b, k in enumerate(own):
                    y[: len(labels[k]), b] = labels[k]
                _, g = self.step(x, mask, y)
                norm = np.sqrt(sum((w**2).sum() for w in g.values()))
                t += 1
                for k, w in self.p.items():
                    d = g[k] * min(1.0, 5 / (norm + 1e-9))
                    m[k] = 0.9 * m[k] + 0.1 * d
                    v[k] = 0.999 * v[k] + 0.001 * d**2
                    self.p[k] = (w - rate * 0.75**epoch * m[k] / (1 - 0.9**t) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
        return self

    def label(self, pages) -> list[np.ndarray]:
        """Article probability of each block of each page."""
        out: list[np.ndarray] = [np.zeros(0)] * len(pages)
        order = sorted((k for k in range(len(pages)) if pages[k]), key=lambda k: len(pages[k]))
        at = 0
        while at < len(order):
            to = at + 1
            while to < len(order) and to - at < 256 and (to - at + 1) * len(pages[order[to]]) <= 8192:
                to += 1
            own = order[at:to]
            x, mask, _ = padded([pages[k] for k in own])
            q = self.forward(x, mask)[0]
            for b, k in enumerate(own):
                out[k] = q[: len(pages[k]), b]
            at = to
        return out


def padded(pages):
    flat = vectors(pages)
    sizes = [len(p) for p in pages]
    x = np.zeros((max(sizes), len(pages), WIDTH), np.float32)
    mask = np.zeros(x.shape[:2], bool)
    at = 0
    for b, n in enumerate(sizes):
        x[:n, b], mask[:n, b] = flat[at : at + n], True
        at += n
    return x, mask, sizes


# ---- weak labels and variations of training pages ----

OUTSIDE = frozenset("nav footer aside header form button dialog menu head label".split())
BOILER = frozenset("ad ads advert advertisement sponsored promo banner comment comments reply replies respond disqus sidebar related recommended share social cookie consent notice alert popup modal newsletter subscribe menu nav navigation breadcrumb breadcrumbs footer header masthead copyright login signup search toolbar widget".split())


def weak_label(path: tuple[str, ...], has_container: bool) -> bool:
    inside = not has_container
    for p in path:
        if p in ("article", "main") or p in ("role:main", "id:main", "id:content", "class:content", "class:post", "class:entry"):
            inside = True
        name, _, value = p.rpartition(":")
        if p in OUTSIDE and not (p == "header" and inside) or name and value in BOILER:
            return False
    return inside


CONTAINERS = (("article",), ("main",), ("div", "class:content"), ("main", "article"), ("div", "class:post"), ("div", "id:content"), ("section", "class:article", "class:body"), ("article", "class:post"))
EXTRAS = (
    (("section", "class:comments"), ("div", "class:comment")), (("div", "id:comments"), ("ol", "class:comment", "class:list", "li")), (("aside", "class:sidebar"), ("ul", "li", "a")), (("aside",), ("p",)),
    (("div", "class:cookie", "class:notice"), ("p",)), (("div", "class:notice"), ("p",)), (("form", "class:newsletter"), ("p",)), (("form",), ("label",)), (("header",), ("p",)), (("header", "class:site", "class:header"), ("h1",)),
    (("div", "class:related"), ("ul", "li", "a")), (("div", "class:share"), ("a",)), (("div", "class:ad"), ()), (("div", "class:advert"), ("p",)), (("div", "class:sponsored"), ("p",)), (("div", "class:sidebar"), ("p",)), (("div", "class:menu"), ("ul", "li", "a")),
    (("div", "class:comment", "class:body"), ("p",)), (("div", "class:popup"), ("p",)), (("nav", "class:breadcrumb"), ("a",)), (("div", "role:complementary"), ("p",)), (("ul", "class:menu"), ("li", "a")),
)


INNERS = (("p",), ("div",), *(("ul", "li"), ("ol", "li")) * 6, ("blockquote",), ("blockquote", "p"), ("pre",), ("table", "tbody", "tr", "td"), ("table", "tr", "th"), ("section", "p"), ("h2",), ("h3",), ("dl", "dd"), ("figure", "figcaption"), ("div", "class:text", "p"))
VARIATIONS = 8  # of each training page
WRAPPED = (0, 0, 0, 1, 2, 4, 12, 60)


def varied(page: list[tuple], label: list[bool], pool: list[str], rng) -> tuple[list[tuple], list[bool]]:
    """Another container for the article, other elements for some of its paragraphs, some blocks left out and some extra parts before, inside and after it."""
    container = CONTAINERS[rng.integers(len(CONTAINERS))]
    wrapper = ("div",) * WRAPPED[rng.integers(len(WRAPPED))]
    restyled, left_out = rng.choice((0.0, 0.2, 0.6)), rng.choice((0.0, 0.0, 0.4))
    out = []
    for (path, text, linked), y in zip(page, label):
        if rng.random() < left_out:  # pages without a heading, a menu, a footer
            continue
        if y:
            if path[-1] == "p" and rng.random() < restyled:
                path = path[:-1] + INNERS[rng.integers(len(INNERS))]
                if rng.random() < 0.4:  # a few words of any block: it is the place that counts
                    words = pool[rng.integers(len(pool))].split()
                    text = " ".join(words[: 1 + int(rng.integers(4))]) or text
                    linked = 0
            path = tuple(q for p in path for q in ((*container, *wrapper) if p == "article" else (p,)))
        out.append((path, text, linked, y))
    root = ("html", "body")
    for _ in range(rng.integers(0, 5)):
        outer, inner = EXTRAS[rng.integers(len(EXTRAS))]
        nested = rng.random() < 0.55
        own = [k for k, b in enumerate(out) if b[3]]
        if nested and own:  # inside the article
            at = int(rng.integers(own[0], own[-1] + 2))
        else:  # between top-level parts
            nested = False
            edges = [k for k in range(len(out) + 1) if k in (0, len(out)) or out[k - 1][3] != out[k][3]]
            at = int(rng.choice(edges))
        path = (*root, *((*container, *wrapper) if nested else ()), *outer, *inner)
        new = []
        for _ in range(rng.integers(1, 5)):
            words = pool[rng.integers(len(pool))]
            new.append((path, words, len(words) if "a" in inner else 0, False))
        out[at:at] = new
    return [b[:3] for b in out], [bool(b[3]) for b in out]


def train(pages: DataFrame, sample: int = 240, sample_bytes: int = 4 << 20, stretch: int = 256, seed: int = 5) -> BiLstm:
    """Learns from whole pages, at most `sample` of at most `sample_bytes` together.

    All their blocks train; a page of more than `stretch` blocks is several sequences in training (never in labelling).
    """
    rows = bounded_sample(pages.select(F.col("html").cast("string").alias("html")).filter("length(html) > 0"), "html", sample, sample_bytes)
    rng = np.random.default_rng(seed)
    xs, ys = [], []
    parsed = [blocks_of(p) for p in rows.column(0).to_pylist()]
    pool = [b[1] for page in parsed for b in page] or ["text"]
    for page in parsed:
        has = any(p in ("article", "main") for b in page for p in b[0])
        y = [weak_label(b[0], has) for b in page]
        xs.append(page)
        ys.append(y)
        for _ in range(VARIATIONS):
            x, z = varied(page, y, pool, rng)
            xs.append(x)
            ys.append(z)
    cut = lambda rows: [row[at : at + stretch] for row in rows for at in range(0, len(row), stretch)]
    xs, ys = cut(xs), cut(ys)
    return BiLstm(seed=seed).fit(xs, ys, seed=seed)


def extractor(net: BiLstm, least: float):
    def run(batches):
        for batch in chunks(batches, "html", 2 << 20):
            pages = [blocks_of(p) if p else [] for p in batch.column("html").to_pylist()]
            texts = ["\n\n".join(b[1] for b, q in zip(page, score) if q >= least) for page, score in zip(pages, net.label(pages))]
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64())], names=["page_id", "url", "text", "n_chars"])

    return run


def main_text(pages: DataFrame, net: BiLstm, least: float = 0.5) -> DataFrame:
    slim = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.col("html").cast("string").alias("html"))
    return slim.mapInArrow(extractor(net, least), "page_id long, url string, text string, n_chars long")


def op9_recurrent_blocks(spark, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return main_text(pages, train(pages))
