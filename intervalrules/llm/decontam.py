"""Operator 5: benchmark decontamination over a stored, document-partitioned positional inverted index.

``build_index`` turns every chunk of the corpus into one row of a table, an index shard: the lexicon of its words, and for each word the
sorted places where it stands (places count through the shard's documents; stored as differences). The index does not depend on the benchmark.
A shard holds whole documents, so no list of a frequent word ever grows beyond one chunk and phrases are intersected without a shuffle.

Queries are the benchmark's windows, compiled on the driver in blocks of at most ``block_bytes`` text, one pass over the index for each:

* phrases: the terms of a window are sorted from the rarest of the shard on; the rarest term's list, shifted by its place in the phrase,
  is intersected with the shifted lists of the next rarest terms by binary search;
* proximity: places of the rarest term are kept while every other term has a place near enough, again from the rarest on; of those, the
  first stretch of ``span`` words that holds all terms is returned.

Only documents with matches leave a pass; the blocks' matches are merged by shard and document. Terms are found by hash and compared in full.

Edge cases: null or empty texts have no words; an item without words has no window; an item with fewer words than the window is one window;
repeated items are one, items without an item_id make words hit but are not listed; repeated document rows, and rows that share or lack a doc_id,
each give their own row; a very long text is a shard of its own; an empty table gives no rows, an empty benchmark no hits; extra columns are not read.
"""

from __future__ import annotations

from typing import NamedTuple

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, chunks, mix64, ragged, table, utf8

WINDOW = 10
# Byte classes of words: ASCII digits and letters and every byte of a character beyond ASCII.
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
IS_WORD = np.zeros(256, bool)
IS_WORD[48:58] = IS_WORD[97:123] = IS_WORD[128:] = True
BASE = 0x9E3779B97F4A7C15  # odd
_POWERS: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def powers(n: int, base: int = BASE) -> tuple[np.ndarray, np.ndarray]:
    """base^i and base^-i modulo 2^64 for i <= n."""
    size = 1 << max(16, int(n).bit_length())
    if base not in _POWERS or len(_POWERS[base][0]) < size:
        up, down = np.full(size, base, np.uint64), np.full(size, pow(base, -1, 1 << 64), np.uint64)
        up[0] = down[0] = 1
        _POWERS[base] = np.multiply.accumulate(up), np.multiply.accumulate(down)
    return _POWERS[base]


def word_spans(data: np.ndarray, bounds: np.ndarray, member: np.ndarray = IS_WORD) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, offset of each text's first word) of the words in lower-cased bytes; words end with their text."""
    inside = np.zeros(len(data) + 2, bool)
    inside[1:-1] = member[data]
    rises = inside[1:-1] & ~inside[:-2]
    falls = inside[1:-1] & ~inside[2:]
    edges = bounds[1:-1]
    edges = edges[(edges > 0) & (edges < len(data))]
    rises[edges] |= inside[edges + 1]
    falls[edges - 1] |= inside[edges]
    starts, ends = np.flatnonzero(rises), np.flatnonzero(falls) + 1
    return starts, ends, np.searchsorted(starts, bounds)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each word, equal for equal bytes wherever they stand."""
    up, down = powers(len(data))
    sums = np.zeros(len(data) + 1, np.uint64)
    own = sums[1:]  # in place: this is the largest array of a task
    own += data
    own += np.uint64(1)
    own *= up[: len(data)]
    np.cumsum(own, out=own)
    raw = (sums[ends] - sums[starts]) * down[starts]
    return mix64(raw ^ ((ends - starts).astype(np.uint64) << np.uint64(56)))


def words_of(texts) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    data, bounds = utf8(texts)
    data = LOWER[data]
    starts, ends, first = word_spans(data, bounds)
    return data, starts, ends, first, word_hashes(data, starts, ends)


class Queries:
    """Windows of a block of items, as rows of term numbers; windows of equal terms stand once. Items without an id have number -1."""

    def __init__(self, ids: list[str | None], texts: list[str | None], window: int = WINDOW):
        data, starts, ends, first, hashes = words_of(pa.array(texts, pa.string()))
        self.terms, at, number = np.unique(hashes, return_index=True, return_inverse=True)
        self.words = [data[starts[i] : ends[i]].tobytes() for i in at]
        self.ids = sorted({i for i in ids if i is not None})
        known = {v: k for k, v in enumerate(self.ids)}
        item = np.array([known.get(i, -1) for i in ids], np.int64)
        sizes = np.diff(first)
        self.by_length: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for n in sorted(set(np.minimum(sizes[sizes > 0], window).tolist())):
            own = np.flatnonzero(np.minimum(sizes, window) == n)
            counts = sizes[own] - n + 1
            begin, owner = ragged(first[own], counts), np.repeat(item[own], counts)
            rows, of = np.unique(number[begin[:, None] + np.arange(n)], axis=0, return_inverse=True)
            pairs = np.unique(np.column_stack([of.ravel(), owner]), axis=0)
            self.by_length[n] = rows, np.searchsorted(pairs[:, 0], np.arange(len(rows) + 1)), pairs[:, 1]

    def items_of(self, n: int, rows: np.ndarray) -> set[str]:
        _, begin, owner = self.by_length[n]
        return {self.ids[i] for i in owner[ragged(begin[rows], begin[rows + 1] - begin[rows])].tolist() if i >= 0}


def query_blocks(benchmark: DataFrame, window: int, block_bytes: int):
    """Queries of items of at most block_bytes together (a longer item stands alone); the driver holds one block at a time."""
    ids, texts, size = [], [], 0
    for row in benchmark.select(F.col("item_id").cast("string"), F.col("text").cast("string")).filter("text IS NOT NULL").toLocalIterator():
        n = len(row[1].encode())
        if ids and size + n > block_bytes:
            yield Queries(ids, texts, window)
            ids, texts, size = [], [], 0
        ids.append(row[0])
        texts.append(row[1])
        size += n
    if ids:
        yield Queries(ids, texts, window)


class Postings(NamedTuple):
    """A shard's lists. Terms are sorted by hash; the list of term t is places[begin[t] : begin[t] + counts[t]]."""

    terms: np.ndarray
    counts: np.ndarray
    lexicon: bytes
    word_ends: np.ndarray
    places: np.ndarray
    first: np.ndarray  # the first place of each document, and the number of places


def postings(texts) -> Postings:
    data, starts, ends, first, hashes = words_of(texts)
    order = np.argsort(hashes, kind="stable")
    sorted_ = hashes[order]
    begin = np.flatnonzero(np.concatenate([[True], sorted_[1:] != sorted_[:-1]])) if len(order) else order
    one = order[begin]
    sizes = ends[one] - starts[one]
    return Postings(sorted_[begin], np.diff(np.append(begin, len(order))), data[ragged(starts[one], sizes)].tobytes(), np.cumsum(sizes), order, first)


INDEX = "doc_ids array<bigint>, n_words array<bigint>, terms binary, counts binary, lexicon binary, word_ends binary, places binary, first binary"


def indexer(batches):
    """One row for each chunk of texts."""
    for batch in chunks(batches, "text", 4 << 20):
        p = postings(batch.column("text"))
        begin = np.cumsum(p.counts) - p.counts
        steps = np.diff(p.places, prepend=0)
        steps[begin] = p.places[begin]
        blobs = (p.terms, p.counts.astype("<u4"), p.lexicon, p.word_ends.astype("<u4"), steps.astype("<u4"), p.first)
        lists = [pa.array([v], pa.list_(pa.int64())) for v in (batch.column("doc_id").to_pylist(), np.diff(p.first).tolist())]
        yield pa.RecordBatch.from_arrays([*lists, *(pa.array([v if isinstance(v, bytes) else v.tobytes()], pa.binary()) for v in blobs)], names=[c.split()[0] for c in INDEX.split(", ")])


def build_index(docs: DataFrame, scratch: Scratch) -> DataFrame:
    """The index as a table: one row for each shard, numbered."""
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return scratch.table("index", slim.mapInArrow(indexer, INDEX).withColumn("shard", F.monotonically_increasing_id()))


def loaded(batches):
    """(shard number, Postings) of the rows of the index."""
    for batch in batches:
        for row in zip(*(batch.column(c) for c in ("shard", "terms", "counts", "lexicon", "word_ends", "places", "first"))):
            shard, terms, counts, lexicon, word_ends, steps, first = (v.as_py() for v in row)
            counts = np.frombuffer(counts, "<u4").astype(np.int64)
            sums = np.cumsum(np.frombuffer(steps, "<u4").astype(np.int64))
            begin = np.cumsum(counts) - counts
            # each list starts anew
            before = np.concatenate([[0], sums])[begin] if len(begin) else begin
            yield shard, Postings(np.frombuffer(terms, np.uint64), counts, lexicon, np.frombuffer(word_ends, "<u4").astype(np.int64), sums - np.repeat(before, counts), np.frombuffer(first, np.int64))


class Shard:
    """The lists that a block of queries asks for, in one shard; terms are numbered as in the queries."""

    def __init__(self, p: Postings, queries: Queries):
        self.first, self.size = p.first, int(p.first[-1])
        n = len(queries.terms)
        at = np.searchsorted(p.terms, queries.terms)
        at[at == len(p.terms)] = 0
        found = np.flatnonzero(p.terms[at] == queries.terms) if len(p.terms) else np.zeros(0, np.int64)
        word_begin = np.concatenate([[0], p.word_ends])
        # equal hash, other word: not the term
        same = [p.lexicon[word_begin[at[t]] : word_begin[at[t] + 1]] == queries.words[t] for t in found.tolist()]
        found = found[np.array(same, bool)]
        self.counts = np.zeros(n, np.int64)
        self.counts[found] = p.counts[at[found]]
        list_begin = np.cumsum(p.counts) - p.counts
        self.places = p.places[ragged(list_begin[at[found]], self.counts[found])]
        self.begin = np.cumsum(self.counts) - self.counts
        # key = term * width + place is sorted as a whole
        self.width = self.size + 64
        self.keys = np.repeat(np.arange(n), self.counts) * self.width + self.places
        self.doc = np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))

    def has(self, term: np.ndarray, place: np.ndarray) -> np.ndarray:
        key = term * self.width + place
        at = np.searchsorted(self.keys, key)
        at[at == len(self.keys)] = 0
        return (self.keys[at] == key) & (place >= 0) if len(self.keys) else np.zeros(len(key), bool)

    def between(self, term: np.ndarray, low: np.ndarray, high: np.ndarray) -> np.ndarray:
        """Whether a term has a place in [low, high]."""
        return np.searchsorted(self.keys, term * self.width + high, "right") > np.searchsorted(self.keys, term * self.width + low, "left")

    def _rarest(self, windows: np.ndarray):
        """(window row, place of its rarest term, terms of each window from the rarest on) of windows whose terms all occur."""
        alive = np.flatnonzero((self.counts[windows] > 0).all(1))
        rarity = np.argsort(self.counts[windows], axis=1, kind="stable")
        rarest = windows[alive, rarity[alive, 0]]
        row = np.repeat(alive, self.counts[rarest])
        return row, self.places[ragged(self.begin[rarest], self.counts[rarest])], rarity

    def phrases(self, windows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(window row, first place) of every occurrence inside one document."""
        n = windows.shape[1]
        row, place, rarity = self._rarest(windows)
        begin = place - rarity[row, 0]
        for j in range(1, n):
            if not len(row):
                break
            offset = rarity[row, j]
            alive = self.has(windows[row, offset], begin + offset)
            row, begin = row[alive], begin[alive]
        inside = (begin >= 0) & (begin + n <= self.size)
        row, begin = row[inside], begin[inside]
        inside = self.doc[begin] == self.doc[begin + n - 1] if len(begin) else np.zeros(0, bool)
        return row[inside], begin[inside]

    def near(self, windows: np.ndarray, span: int) -> tuple[np.ndarray, np.ndarray]:
        """(window row, first place) of stretches of `span` words of one document that hold all terms of a window, in any order.

        One for each place of the window's rarest term that lies in such a stretch: the first that holds this place.
        """
        row, place, rarity = self._rarest(windows)
        for j in range(1, windows.shape[1]):
            low = np.maximum(place - span + 1, self.first[self.doc[place]])
            high = np.minimum(place + span, self.first[self.doc[place] + 1]) - 1
            alive = self.between(windows[row, rarity[row, j]], low, high)
            row, place = row[alive], place[alive]
        begin = np.full(len(row), -1, np.int64)
        for offset in range(span - 1, -1, -1):
            todo = np.flatnonzero((begin < 0) & (place - offset >= self.first[self.doc[place]])) if len(row) else row
            low = place[todo] - offset
            high = np.minimum(low + span, self.first[self.doc[place[todo]] + 1]) - 1
            for j in range(1, windows.shape[1]):
                alive = self.between(windows[row[todo], j], low, high) & self.between(windows[row[todo], 0], low, high)
                todo, low, high = todo[alive], low[alive], high[alive]
            begin[todo] = low
        return row[begin >= 0], begin[begin >= 0]


def covered(shard: Shard, queries: Queries) -> tuple[np.ndarray, dict[int, set[str]]]:
    """Hit places, and the items of each document with hits."""
    depth = np.zeros(shard.size + 1, np.int64)
    items: dict[int, set[str]] = {}
    for n, (windows, _, _) in queries.by_length.items():
        row, begin = shard.phrases(windows)
        if not len(row):
            continue
        np.add.at(depth, begin, 1)
        np.add.at(depth, begin + n, -1)
        pairs = np.unique(np.column_stack([shard.doc[begin], row]), axis=0)
        cuts = np.flatnonzero(np.diff(pairs[:, 0], prepend=-1))
        for part in np.split(pairs, cuts[1:]):
            items.setdefault(int(part[0, 0]), set()).update(queries.items_of(n, part[:, 1]))
    return np.flatnonzero(np.cumsum(depth)[:-1] > 0), items


def phrase_matcher(queries: Queries):
    """Hit words (counted in their document) and items of the documents with hits."""

    def run(batches):
        for number, p in loaded(batches):
            shard = Shard(p, queries)
            hit, items = covered(shard, queries)
            if not len(hit):
                continue
            docs = np.array(sorted(items), np.int64)
            cuts = np.searchsorted(shard.doc[hit], docs), np.searchsorted(shard.doc[hit], docs, "right")
            places = [(hit[a:b] - shard.first[d]).tolist() for d, a, b in zip(docs, *cuts)]
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(docs), number)), pa.array(docs), pa.array(places, pa.list_(pa.int64())), pa.array([sorted(items[d]) for d in docs.tolist()], pa.list_(pa.string()))], names=["shard", "doc", "places", "items"])

    return run


def near_matcher(queries: Queries, span: int):
    """(shard, document, item, first word of the first stretch) of proximity matches."""

    def run(batches):
        for number, p in loaded(batches):
            shard = Shard(p, queries)
            best: dict[tuple[int, str], int] = {}
            for n, (windows, _, _) in queries.by_length.items():
                row, begin = shard.near(windows, span)
                for r, at in zip(row.tolist(), begin.tolist()):
                    d = int(shard.doc[at])
                    for item in queries.items_of(n, np.array([r])):
                        best[d, item] = min(best.get((d, item), at), at)
            if best:
                rows = [(number, d, item, at - int(shard.first[d])) for (d, item), at in sorted(best.items())]
                cols = list(zip(*rows))
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int64()), pa.array(cols[2]), pa.array(cols[3], pa.int64())], names=["shard", "doc", "item_id", "place"])

    return run


LISTS = ("shard", "terms", "counts", "lexicon", "word_ends", "places", "first")


def _passes(index: DataFrame, benchmark: DataFrame, window: int, block_bytes: int, matcher, kind: str) -> DataFrame:
    """One pass over the index for each block of the benchmark."""
    out = None
    for queries in query_blocks(benchmark, window, block_bytes):
        got = index.select(*LISTS).mapInArrow(matcher(queries), kind)
        out = got if out is None else out.unionByName(got)
    return index.sparkSession.createDataFrame([], kind) if out is None else out


def indexed_rows(index: DataFrame) -> DataFrame:
    """shard, doc, doc_id, n_words of every document."""
    return index.select("shard", F.posexplode(F.arrays_zip("doc_ids", "n_words")).alias("doc", "d")).select("shard", F.col("doc").cast("long").alias("doc"), F.col("d.doc_ids").alias("doc_id"), F.col("d.n_words").alias("n_words"))


def contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = 4 << 20) -> DataFrame:
    """doc_id, n_words, n_hit, items of every document: exact matches of the benchmark's windows."""
    index = build_index(docs, Scratch(docs.sparkSession, "postings"))
    found = _passes(index, benchmark, window, block_bytes, phrase_matcher, "shard long, doc long, places array<bigint>, items array<string>")
    merged = found.groupBy("shard", "doc").agg(F.size(F.array_distinct(F.flatten(F.collect_list("places")))).alias("n_hit"), F.array_sort(F.array_distinct(F.flatten(F.collect_list("items")))).alias("items"))
    out = indexed_rows(index).join(merged, ["shard", "doc"], "left")
    return out.select("doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).cast("long").alias("n_hit"), F.coalesce("items", F.array().cast("array<string>")).alias("items"))


def proximity(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, span: int = 20, block_bytes: int = 4 << 20) -> DataFrame:
    """doc_id, item_id, place: documents that hold all words of a window of an item within `span` words, and where the first such stretch begins."""
    index = build_index(docs, Scratch(docs.sparkSession, "postings"))
    found = _passes(index, benchmark, window, block_bytes, lambda q: near_matcher(q, span), "shard long, doc long, item_id string, place long")
    found = found.groupBy("shard", "doc", "item_id").agg(F.min("place").alias("place"))
    return found.join(indexed_rows(index), ["shard", "doc"]).select("doc_id", "item_id", "place")


def cleaner(queries: Queries):
    """Passes on the rows of texts without a hit; a chunk's index is made in the task."""

    def run(batches):
        for batch in chunks(batches, "text", 4 << 20):
            shard = Shard(postings(batch.column("text")), queries)
            clean = np.ones(batch.num_rows, bool)
            clean[np.unique(shard.doc[covered(shard, queries)[0]])] = False
            yield batch.filter(pa.array(clean))

    return run


def without_benchmark(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, block_bytes: int = 4 << 20) -> DataFrame:
    """The rows whose text holds no benchmark window, one pass for each block of items."""
    for queries in query_blocks(benchmark, window, block_bytes):
        docs = docs.mapInArrow(cleaner(queries), docs.schema)
    return docs


def op5_benchmark_index(spark, sf_dir: str) -> DataFrame:
    found = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    digest = F.sha2(F.concat_ws(",", "items"), 256)
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), digest.alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def benchmark_proximity(spark, sf_dir: str) -> DataFrame:
    """Every document that holds the words of a window of an item close together, in any order."""
    return proximity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


OP5_SQL = r"""
WITH w AS (
  SELECT doc_id, unnest(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')) AS word,
         generate_subscripts(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), 1) AS pos
  FROM documents),
b AS (
  SELECT CAST(item_id AS VARCHAR) AS item, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS words
  FROM benchmark),
win AS (
  SELECT DISTINCT item, len(words[i:i+9]) AS n, array_to_string(words[i:i+9], ' ') AS phrase
  FROM (SELECT item, words, unnest(range(1, greatest(2, len(words) - 8))) AS i FROM b WHERE len(words) > 0)),
lens AS (SELECT DISTINCT n FROM win),
grams AS (
  SELECT doc_id, pos, n, CASE WHEN n = 10 THEN g10 ELSE array_to_string(l[1:n], ' ') END AS phrase
  FROM (SELECT doc_id, pos, list(word) OVER w10 AS l, string_agg(word, ' ') OVER w10 AS g10 FROM w
        WINDOW w10 AS (PARTITION BY doc_id ORDER BY pos ROWS BETWEEN CURRENT ROW AND 9 FOLLOWING)), lens
  WHERE len(l) >= n),
occ AS (SELECT g.doc_id, g.pos, g.n, win.item FROM grams g JOIN win USING (n, phrase)),
hit AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT DISTINCT doc_id, unnest(range(pos, pos + n)) AS p FROM occ) GROUP BY 1),
its AS (SELECT doc_id, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS items FROM (SELECT DISTINCT doc_id, item FROM occ WHERE item IS NOT NULL) GROUP BY 1),
cnt AS (SELECT doc_id, count(*) AS n_words FROM w GROUP BY 1)
SELECT d.doc_id, CAST(coalesce(n_words, 0) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
       sha256(coalesce(items, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM documents d LEFT JOIN cnt USING (doc_id) LEFT JOIN hit USING (doc_id) LEFT JOIN its USING (doc_id)
"""
