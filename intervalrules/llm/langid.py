"""Operator 3: language identification by a byte convolutional network, trained and applied in numpy.

Bytes (A-Z lower-cased) are embedded, convolved by filters of several widths, rectified, max-pooled over a fixed-length window and classified by a
softmax layer. A text is cut into consecutive windows of ``length`` bytes (each starts ``overlap`` bytes early so that no
filter misses a border); all of them are read, and the window probabilities are averaged by their number of bytes.

Training uses a bounded sample: at most ``texts`` labelled rows, the same number from each language that occurs (all of them are learned),
``windows`` random windows of each. Everything else covers all rows. The model is a few kilobytes and travels with the
task; prediction is a map over the scan without a shuffle.

Edge cases: a null, empty or letterless text is ``und`` with score 0; a text shorter than a window is padded with spaces, a very long one is read
whole; without any labelled row all texts are ``und``; an empty table gives no rows; rows are judged one by one, so repeats, rows that share or lack a
doc_id and other columns do not matter (a null doc_id is not held out).
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import chunks, table, utf8
from .decontam import LOWER

UNKNOWN = "und"
LENGTH, PAD = 256, 32
WIDTHS, FILTERS, EMBED = (2, 3, 4), 8, 8


def held_out(key: str = "doc_id"):
    return F.coalesce(F.crc32(F.col(key).cast("string")) % 4 == 2, F.lit(False))


class ByteNet:
    """Multi-width filters over byte embeddings, max pooling and softmax."""

    def __init__(self, labels: list[str], seed: int = 7):
        rng = np.random.default_rng(seed)
        self.labels = labels
        n = len(WIDTHS) * FILTERS
        self.p = {"e": rng.normal(0, 0.5, (256, EMBED)), "o": rng.normal(0, 0.3, (n, len(labels))), "c": np.zeros(len(labels))}
        for w in WIDTHS:
            self.p[f"w{w}"] = rng.normal(0, (2 / (w * EMBED)) ** 0.5, (w, EMBED, FILTERS))
            self.p[f"b{w}"] = np.zeros(FILTERS)
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}

    def _pooled(self, x: np.ndarray):
        e = self.p["e"][x]
        out = []
        for w in WIDTHS:
            n = x.shape[1] - w + 1
            z = sum(e[:, j : j + n] @ self.p[f"w{w}"][j] for j in range(w)) + self.p[f"b{w}"]
            at = z.argmax(1)
            out.append((np.maximum(np.take_along_axis(z, at[:, None], 1)[:, 0], 0), at))
        return e, out

    def step(self, x: np.ndarray, y: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
        """Mean loss and gradients of a batch of windows."""
        p, n = self.p, len(x)
        e, pooled = self._pooled(x)
        h = np.concatenate([v for v, _ in pooled], 1)
        z = h @ p["o"] + p["c"]
        q = np.exp(z - z.max(1, keepdims=True))
        q /= q.sum(1, keepdims=True)
        loss = -np.log(q[np.arange(n), y] + 1e-9).mean()
        dz = q.copy()
        dz[np.arange(n), y] -= 1
        dz /= n
        g = {"o": h.T @ dz, "c": dz.sum(0), "e": np.zeros_like(p["e"])}
        dh = (dz @ p["o"].T) * (h > 0)
        for k, w in enumerate(WIDTHS):
            d, at = dh[:, k * FILTERS : (k + 1) * FILTERS], pooled[k][1]
            g[f"b{w}"], g[f"w{w}"] = d.sum(0), np.zeros_like(p[f"w{w}"])
            rows = np.arange(n)[:, None]
            for j in range(w):
                seen = e[rows, at + j]  # n, FILTERS, EMBED
                g[f"w{w}"][j] = np.einsum("nf,nfe->ef", d, seen)
                np.add.at(g["e"], x[rows, at + j], d[:, :, None] * p[f"w{w}"][j].T[None])
        return float(loss), g

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int, batch: int = 128, rate: float = 0.01, seed: int = 7) -> "ByteNet":
        rng = np.random.default_rng(seed)
        m = {k: np.zeros_like(v) for k, v in self.p.items()}
        v = {k: np.zeros_like(w) for k, w in self.p.items()}
        t = 0
        for epoch in range(epochs):
            order = rng.permutation(len(x))
            for at in range(0, len(x), batch):
                part = order[at : at + batch]
                _, g = self.step(x[part], y[part])
                t += 1
                for k in self.p:  # Adam
                    m[k] = 0.9 * m[k] + 0.1 * g[k]
                    v[k] = 0.999 * v[k] + 0.001 * g[k] ** 2
                    self.p[k] -= (rate * 0.7**epoch * m[k] / (1 - 0.9**t) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
        return self

    def tables(self) -> "ByteNet":
        """Filter responses of byte pairs, so that a filter of width w costs w / 2 look-ups a place."""
        for w in WIDTHS:
            one = [self.p["e"] @ self.p[f"w{w}"][j] for j in range(w)]
            pairs = [np.ascontiguousarray((one[j][:, None] + one[j + 1][None]).reshape(65536, FILTERS), np.float32) for j in range(0, w - 1, 2)]
            setattr(self, f"t{w}", (pairs, one[-1].astype(np.float32) if w % 2 else None))
        return self

    def predict(self, x: np.ndarray) -> np.ndarray:
        """Label probabilities of windows; call tables() first."""
        pair = x[:, :-1].astype(np.int32) * 256 + x[:, 1:]
        out = []
        for w in WIDTHS:
            pairs, single = getattr(self, f"t{w}")
            n = x.shape[1] - w + 1
            z = pairs[0].take(pair[:, :n], axis=0)
            for k, t in enumerate(pairs[1:], 1):
                z += t.take(pair[:, 2 * k : 2 * k + n], axis=0)
            if single is not None:
                z += single.take(x[:, w - 1 : w - 1 + n], axis=0)
            while n > 1:  # fold halves: a maximum over places in long runs
                half = (n + 1) // 2
                z = np.maximum(z[:, :half], z[:, n - half : n])
                n = half
            out.append(np.maximum(z[:, 0] + self.p[f"b{w}"], 0))
        z = np.concatenate(out, 1) @ self.p["o"] + self.p["c"]
        q = np.exp(z - z.max(1, keepdims=True))
        return q / q.sum(1, keepdims=True)


def windows_of(data: np.ndarray, bounds: np.ndarray, length: int = LENGTH, overlap: int = max(WIDTHS) - 1):
    """(windows, owner text, bytes new in each) of texts; short ones are padded with spaces."""
    sizes = np.diff(bounds)
    step = length - overlap
    counts = np.maximum(1, -(-(sizes - overlap) // step)) * (sizes > 0)
    owner = np.repeat(np.arange(len(sizes)), counts)
    nth = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts)
    begin = bounds[:-1][owner] + nth * step
    end = np.minimum(begin + length, bounds[1:][owner])
    padded = np.concatenate([data, np.full(length, PAD, np.uint8)])
    x = np.lib.stride_tricks.sliding_window_view(padded, length)[begin].copy()
    short = end - begin < length
    if short.any():
        rows = np.flatnonzero(short)
        x[rows] = np.where(np.arange(length)[None] < (end - begin)[rows, None], x[rows], PAD)
    return x, owner, np.minimum(end - begin, step)


ASCII_LETTER = np.zeros(256, bool)
ASCII_LETTER[65:91] = ASCII_LETTER[97:123] = True


def has_letters(data: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    count = np.concatenate([[0], np.cumsum(ASCII_LETTER[data])])
    out = count[bounds[1:]] > count[bounds[:-1]]
    wide = np.concatenate([[0], np.cumsum(data >= 128)])
    for k in np.flatnonzero(~out & (wide[bounds[1:]] > wide[bounds[:-1]])):
        out[k] = any(c.isalpha() for c in data[bounds[k] : bounds[k + 1]].tobytes().decode("utf-8", "replace"))
    return out


def predictor(net: ByteNet | None):
    def run(batches):
        ready = net.tables() if net else None
        for batch in chunks(batches, "text", 2 << 20):
            data, bounds = utf8(batch.column("text"))
            n = batch.num_rows
            label, score = np.full(n, UNKNOWN, object), np.zeros(n)
            known = has_letters(data, bounds)
            if ready and known.any():
                x, owner, new = windows_of(LOWER[data], bounds)
                total = np.zeros((n, len(ready.labels)))
                for at in range(0, len(x), 512):
                    np.add.at(total, owner[at : at + 512], ready.predict(x[at : at + 512]) * new[at : at + 512, None])
                total /= np.maximum(total.sum(1, keepdims=True), 1e-12)
                best = total.argmax(1)
                label = np.where(known, np.array(ready.labels, object)[best], UNKNOWN)
                score = np.where(known, np.clip(total[np.arange(n), best], 0, 1), 0.0)
            yield pa.RecordBatch.from_arrays([batch.column(c) for c in batch.schema.names if c != "text"] + [pa.array(label.tolist(), pa.string()), pa.array(score, pa.float64())], names=[*(c for c in batch.schema.names if c != "text"), "lang_pred", "score"])

    return run


def known_only(net: ByteNet | None, least: float):
    """Passes on the rows of texts whose language is known with at least this score; a missing label is filled in."""
    predict = predictor(net)

    def run(batches):
        for batch in batches:
            for part in chunks([batch], "text"):
                got = pa.Table.from_batches(list(predict([part.select(["text"])])))
                label, score = got["lang_pred"].to_pylist(), got["score"].to_pylist()
                keep = pa.array([v != UNKNOWN and s >= least for v, s in zip(label, score)])
                cols = [pc.coalesce(part.column(c), pa.array(label, pa.string())) if c == "lang" else part.column(c) for c in part.schema.names]
                yield pa.RecordBatch.from_arrays(cols, names=part.schema.names).filter(keep)

    return run


def train(docs: DataFrame, texts: int = 2000, windows: int = 4, epochs: int = 5, seed: int = 7) -> ByteNet | None:
    """Fits on rows that are not held out: at most `texts` of them, dealt evenly over all their languages (one a language at least)."""
    rows = docs.select(F.col("doc_id").alias("id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang")).filter(F.col("lang").isNotNull() & ~held_out("id") & F.col("text").rlike(r"\p{L}"))
    # the row's place in the scan tells copies, and rows that share or lack an id, apart
    rows = rows.withColumn("draw", F.pmod(F.xxhash64("id", F.monotonically_increasing_id(), F.lit(seed)), F.lit(1 << 30)))
    counts = rows.groupBy("lang").count().orderBy("lang").collect()  # one row a language
    if not counts:
        return None
    names, each = [r["lang"] for r in counts], max(1, texts // len(counts))
    bar = F.create_map(*[v for r in counts for v in (F.lit(r["lang"]), F.lit(min(1 << 30, math.ceil((1.5 * each + 20) / r["count"] * (1 << 30)))))])
    drawn = rows.filter(F.col("draw") < bar[F.col("lang")])
    first = Window.partitionBy("lang").orderBy("draw", "id", "text")
    drawn = drawn.withColumn("nth", F.row_number().over(first)).filter(F.col("nth") <= each)
    cut = [F.substring("text", 1 + F.pmod(F.xxhash64("draw", F.lit(k)), F.greatest(F.lit(1), F.length("text") - LENGTH)).cast("int"), F.lit(LENGTH)) for k in range(windows)]
    sample = drawn.select("lang", F.explode(F.array(*cut)).alias("part")).orderBy("lang", "part").toArrow()  # texts * windows stretches at most
    y = np.array([names.index(v) for v in sample.column("lang").to_pylist()])
    data, bounds = utf8(sample.column("part"))
    x, owner, _ = windows_of(LOWER[data], bounds)
    keep = np.flatnonzero(np.diff(owner, prepend=-1) > 0)  # the first window of each part
    return ByteNet(names, seed).fit(x[keep], y[owner[keep]], epochs, seed=seed)


def identify(docs: DataFrame, net: ByteNet | None, keys: list[str]) -> DataFrame:
    """keys, lang_pred, score of each row; keys are not read by the model."""
    slim = docs.select(*keys, F.col("text").cast("string").alias("text"))
    kept = [f for f in slim.schema.fields if f.name in keys]
    kind = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept), "lang_pred string", "score double"])
    return slim.mapInArrow(predictor(net), kind)


def op3_byte_convolution(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    net = train(docs)
    return identify(docs, net, ["doc_id"]).select("doc_id", held_out().alias("held_out"), "lang_pred", "score")
