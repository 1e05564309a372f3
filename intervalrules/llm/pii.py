"""Operator 6: personal data by fixed patterns plus a skip-chain conditional random field.

The patterns give the base spans. The field labels candidate tokens: those with a digit or an at sign, values behind a secret's keyword
(``password:``, ``api_key=`` ...) and repeats of such values; all other tokens are outside by definition, so inference over the candidates is exact.
Neighbouring tokens share chain potentials; a token that repeats, or has the same core as, an earlier one of the same document shares a
skip potential with its last and with its first mention, however far away, so that one document labels its entities consistently. Marginals come from
loopy sum-product, run over all documents of a batch as one graph until the messages settle. Tokens inside base spans enter as evidence.
Added spans are tokens whose marginal reaches ``least``; base spans stay.

Weights are learned by gradient ascent on the likelihood that the same message passing approximates, from whole texts: at most ``sample`` of those
that hold a candidate, of at most ``sample_bytes`` together, labelled by the base patterns and by seed patterns for secrets.

A map over the scan; texts without a candidate are skipped after a byte test. Edge cases: null and empty texts have no spans; very long texts
are read whole and very long digit or letter runs take linear time; repeated rows, and rows that share or lack a doc_id, are judged alike; an
empty table gives no rows (and a field that adds nothing); other columns are not read by ``find`` and passed on by a redacting ``finder``.
"""

from __future__ import annotations

import hashlib
import re
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_sample, chunks, table, utf8

KINDS = ("email", "ip", "card", "phone", "secret")
# The base patterns of the contract, written so that each place is tried once.
DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
ADDRESS = re.compile(r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++")
CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
# Seeds of the added kind.
KEYWORD = r"(?:password|passwd|secret|token|api[_-]?key)\s*[=:]"
SECRET = re.compile(r"(?:" + KEYWORD + r"\s*[\"']?)([A-Za-z0-9/+_-]{8,})|\b(AKIA[0-9A-Z]{12,})\b", re.I)
NAMED = re.compile(KEYWORD, re.I)
TOKEN = re.compile(r"\S*[0-9@]\S*")
WORD = re.compile(r"\S+")
NOT_DIGIT = re.compile(r"[^0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if k % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def emails(text: str):
    done, at = 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > done and text[begin - 1] in LOCAL:
            begin -= 1
        found = DOMAIN.match(text, at) if begin < at else None
        if found:
            yield begin, found.end()
            done = found.end()
        else:
            done = max(done, at)  # the sign itself ends every later local part
        at = text.find("@", max(at + 1, done))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the base patterns, in order."""
    out = [(a, 0, b) for a, b in emails(text)] if "@" in text else []
    for m in ADDRESS.finditer(text):
        if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split(".")):
            out.append((m.start(), 1, m.end()))
    for m in CARD.finditer(text):
        if m.end() - m.start() >= 12:
            digits = NOT_DIGIT.sub("", m.group())
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append((m.start(), 2, m.end()))
    if "+" in text:
        for m in PHONE.finditer(text):
            if 9 <= len(NOT_DIGIT.sub("", m.group())) <= 15:
                out.append((m.start(), 3, m.end()))
    return sorted(out)


# ---- the field ----

O = len(KINDS)
LABELS = O + 1
WIDTH = 1 << 12
EVIDENCE = 6.0
TRIM = "\"'()[]{}<>,;:!?.#*%&$|~^`"


def shape(word: str) -> str:
    out = []
    for c in word:
        s = "9" if c.isdigit() else "A" if c.isupper() else "a" if c.isalpha() else c
        if not out or out[-1] != s:
            out.append(s)
    return "".join(out)[:12]


def candidates(text: str) -> list[tuple[int, int]]:
    """Tokens that may get a label: those with a digit or an at sign, values that follow a secret's keyword, and repeats of such values."""
    out = [m.span() for m in TOKEN.finditer(text)]
    values = {m.group(1).lower() for m in SECRET.finditer(text) if m.group(1)} if NAMED.search(text) else set()
    values = {v for v in values if not any(c.isdigit() for c in v)}
    if values:
        named = lambda word: value_of(word.strip(TRIM)).lower() in values
        out = sorted({*out, *(m.span() for m in WORD.finditer(text) if named(m.group()))})
    return out


def value_of(core: str) -> str:
    """What follows the last equals sign or, behind a name, the last colon."""
    at = max(core.rfind("="), core.rfind(":") if NAMED.match(core) else -1) + 1
    return core[at:].strip(TRIM) if 0 < at < len(core) else core


class Graph:
    """Candidate tokens of several documents with their features and edges."""

    def __init__(self):
        self.text, self.span, self.core = [], [], []
        self.feature, self.per = [], []
        self.edges: tuple[list, list] = ([], [])  # chain, skip
        self.known: list[int] = []  # evidence or training label, -1: none

    def add(self, number: int, text: str, known) -> None:
        """known: sorted (start, kind, end) of labelled spans."""
        last_at, seen, first, k = -10, {}, {}, 0
        for begin, end in candidates(text):
            word = text[begin:end]
            left = text[max(0, begin - 24) : begin].split()
            before = left[-1].lower() if left else ""
            right = text[end : end + 16].split()
            after = right[0] if right else ""
            core = word.strip(TRIM)
            lead = len(word) - len(word.lstrip(TRIM))
            value = value_of(core)
            start = begin + lead + (core.rfind(value) if value else 0)
            name = core[: len(core) - len(value)].lower()
            digits = sum(c.isdigit() for c in value)
            node = len(self.span)
            here = []
            for f in ("s:" + shape(value), "n:" + name, "b:" + (shape(before) if any(c.isdigit() for c in before) else before), "a:" + shape(after), f"l:{min(len(value), 40) // 3}", f"d:{min(digits, 20)}", f"r:{int(8 * digits / max(1, len(value)))}", "p:" + value[:4].upper() if value[:4].isalpha() else "p:", "1"):
                here.append(zlib.crc32(f.encode()) % WIDTH)
            self.feature += here
            self.per.append(len(here))
            self.text.append(number)
            self.span.append((start, start + len(value)))
            while k < len(known) and known[k][2] <= start:
                k += 1
            label = -1
            for a, kind, b in known[k : k + 4]:
                if a < start + len(value) and b > start:
                    label = kind
                    break
            self.known.append(label)
            if begin - last_at <= 1:
                self.edges[0].append((node - 1, node))
            last_at = end
            for key in {value.lower(), "#" + NOT_DIGIT.sub("", value) if digits >= 5 else value.lower()}:
                if len(key) >= 4:
                    # to the last mention and to the first one, so that none is more than two edges from another
                    for other in {seen[key], first[key]} - {node} if key in seen else ():
                        self.edges[1].append((other, node))
                    seen[key] = node
                    first.setdefault(key, node)

    def arrays(self):
        edges = [np.array(e, np.int64).reshape(-1, 2) for e in self.edges]
        return np.array(self.feature, np.int64), np.repeat(np.arange(len(self.per)), self.per), edges


class Field:
    def __init__(self):
        self.unary = np.zeros((WIDTH, LABELS))
        self.pair = [np.zeros((LABELS, LABELS)), np.eye(LABELS)]

    def beliefs(self, scores: np.ndarray, edges, settle: float = 1e-3, rounds: int = 100):
        """Node and edge marginals by loopy sum-product, until no message moves by more than `settle` (`rounds` ends a graph that oscillates)."""
        n = len(scores)
        a = np.concatenate([e[:, 0] for e in edges])
        b = np.concatenate([e[:, 1] for e in edges])
        kind = np.repeat(np.arange(len(edges)), [len(e) for e in edges])
        psi = np.stack(self.pair)[kind] if len(a) else np.zeros((0, LABELS, LABELS))
        source, target = np.concatenate([a, b]), np.concatenate([b, a])
        both = np.concatenate([psi, psi.transpose(0, 2, 1)])
        m = len(a)
        back = np.concatenate([np.arange(m, 2 * m), np.arange(m)])
        message = np.zeros((2 * m, LABELS))
        for _ in range(rounds if m else 0):
            total = scores.copy()
            np.add.at(total, target, message)
            out = (total[source] - message[back])[:, :, None] + both
            top = out.max(1, keepdims=True)
            new = (top + np.log(np.exp(out - top).sum(1, keepdims=True)))[:, 0]
            move = 0.5 * (new - new.mean(1, keepdims=True) - message)
            message += move
            if np.abs(move).max() < settle:
                break
        total = scores.copy()
        if m:
            np.add.at(total, target, message)
        node = np.exp(total - total.max(1, keepdims=True))
        node /= node.sum(1, keepdims=True)
        if not m:
            return node, np.zeros((0, LABELS, LABELS)), kind
        joint = (total[a] - message[m:])[:, :, None] + (total[b] - message[:m])[:, None, :] + psi
        joint = np.exp(joint - joint.max((1, 2), keepdims=True))
        return node, joint / joint.sum((1, 2), keepdims=True), kind

    def scores(self, feature: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
        out = np.zeros((n, LABELS))
        np.add.at(out, owner, self.unary[feature])
        return out

    def fit(self, graph: Graph, steps: int = 120, rate: float = 0.3, decay: float = 1e-3) -> "Field":
        feature, owner, edges = graph.arrays()
        n = len(graph.known)
        if not n:
            return self
        y = np.array([O if k < 0 else k for k in graph.known])
        gold = np.eye(LABELS)[y]
        weights = [self.unary, *self.pair]
        sums = [np.full_like(w, 1e-6) for w in weights]
        for _ in range(steps):
            node, joint, kind = self.beliefs(self.scores(feature, owner, n), edges, 0.03)
            grad = np.zeros_like(self.unary)
            np.add.at(grad, feature, (gold - node)[owner])
            grads = [grad]
            for t, e in enumerate(edges):
                seen = np.zeros((LABELS, LABELS))
                np.add.at(seen, (y[e[:, 0]], y[e[:, 1]]), 1)
                g = seen - joint[kind == t].sum(0)
                grads.append((g + g.T) / 2 if t else g)
            for w, g, s in zip(weights, grads, sums):  # AdaGrad, in place
                g = g / n**0.5 - decay * w
                s += g * g
                w += rate * g / np.sqrt(s)
        return self

    def added(self, graph: Graph, least: float) -> list[tuple[int, int, int, int]]:
        """(document, start, kind, end) of tokens without evidence that get a label."""
        feature, owner, edges = graph.arrays()
        if not len(graph.known):
            return []
        scores = self.scores(feature, owner, len(graph.known))
        known = np.array(graph.known)
        fixed = np.flatnonzero(known >= 0)
        scores[fixed, known[fixed]] += EVIDENCE + np.abs(scores[fixed]).max(1)
        node, _, _ = self.beliefs(scores, edges)
        best = node.argmax(1)
        take = np.flatnonzero((best != O) & (known < 0) & (node.max(1) >= least))
        return [(graph.text[i], graph.span[i][0], int(best[i]), graph.span[i][1]) for i in take if graph.span[i][1] > graph.span[i][0]]


def join_spans(spans) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def spans_of(texts: list[str], field: Field, least: float = 0.9) -> list[tuple[list, list]]:
    """(base, all) spans of each text."""
    graph = Graph()
    base = []
    for n, text in enumerate(texts):
        found = base_spans(text)
        base.append(found)
        graph.add(n, text, found)
    full = [list(b) for b in base]
    for n, a, kind, b in field.added(graph, least):
        full[n].append((a, kind, b))
    return [(b, sorted(set(f))) for b, f in zip(base, full)]


TRIGGER = np.zeros(256, bool)
TRIGGER[48:58] = TRIGGER[64] = True


SIGN = np.zeros(256, bool)
SIGN[58] = SIGN[61] = True  # ends a keyword


def triggered(data: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Texts that can hold a candidate: with a digit, an at sign or a secret's keyword."""
    has = lambda kind: np.diff(np.concatenate([[0], np.cumsum(kind[data])])[bounds]) > 0
    out = has(TRIGGER)
    for k in np.flatnonzero(~out & has(SIGN)):
        out[k] = NAMED.search(data[bounds[k] : bounds[k + 1]].tobytes().decode()) is not None
    return np.flatnonzero(out)


def redact(text: str, spans) -> str:
    """Spans (overlaps merged under the first one's kind) replaced by [KIND]."""
    out, done = [], 0
    for a, kind, b in sorted(spans):
        if a >= done:
            out += [text[done:a], f"[{KINDS[kind].upper()}]"]
        done = max(done, b)
    return "".join(out) + text[done:]


def finder(field: Field, least: float, redacting: bool):
    def run(batches):
        for batch in chunks(batches, "text", 4 << 20):
            data, bounds = utf8(batch.column("text"))
            some = triggered(data, bounds)
            texts = [data[bounds[k] : bounds[k + 1]].tobytes().decode() for k in some.tolist()]
            found = dict(zip(some.tolist(), spans_of(texts, field, least)))
            cols, names = [batch.column(c) for c in batch.schema.names if c != "text"], [c for c in batch.schema.names if c != "text"]
            if redacting:
                new = batch.column("text").to_pylist()
                for (k, (_, full)), text in zip(found.items(), texts):
                    new[k] = redact(text, full)
                yield pa.RecordBatch.from_arrays([*cols, pa.array(new, pa.string())], names=[*names, "text"])
                continue
            none = hashlib.sha256(b"").hexdigest()
            count = np.zeros((4, batch.num_rows), np.int64)
            digest, spans = [none] * batch.num_rows, [""] * batch.num_rows
            for k, (base, full) in found.items():
                for _, kind, _ in base:
                    count[kind, k] += 1
                digest[k] = hashlib.sha256(join_spans(base).encode()).hexdigest()
                spans[k] = join_spans(full)
            yield pa.RecordBatch.from_arrays([*cols, *(pa.array(c, pa.int64()) for c in count), pa.array(digest, pa.string()), pa.array(spans, pa.string())], names=[*names, "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "spans"])

    return run


def train(docs: DataFrame, sample: int = 2000, sample_bytes: int = 16 << 20) -> Field:
    """Learns from whole texts: at most `sample` of those with a candidate, of at most `sample_bytes` together."""
    named = F.col("text").rlike("[=:]") & F.col("text").rlike(f"(?i){KEYWORD}")  # a keyword ends with one of the signs
    rows = docs.select(F.col("text").cast("string").alias("text")).filter(F.col("text").rlike("[0-9@]") | named)
    rows = bounded_sample(rows, "text", sample, sample_bytes)
    graph = Graph()
    for n, text in enumerate(rows.column(0).to_pylist()):
        values = {m.group(g) for m in SECRET.finditer(text) for g in (1, 2) if m.group(g)}
        # a secret is one wherever it stands
        seeds = [(m.start(), 4, m.end()) for v in values for m in re.finditer(rf"(?<![A-Za-z0-9]){re.escape(v)}(?![A-Za-z0-9])", text)]
        base = base_spans(text)
        seeds = [s for s in seeds if not any(a < s[2] and b > s[0] for a, _, b in base)]
        graph.add(n, text, sorted(base + seeds))
    return Field().fit(graph)


def find(docs: DataFrame, field: Field, least: float = 0.9) -> DataFrame:
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return slim.mapInArrow(finder(field, least, False), "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string")


def op6_skip_chain(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return find(docs, train(docs))

