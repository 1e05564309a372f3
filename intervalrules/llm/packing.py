"""Operator 8: bounded-space online best-fit packing of token pieces.

Each task tokenises its texts and feeds the pieces, in the order in which they come, to a packer that keeps at most
``open_bins`` bins open. A bitset keyed by free space finds the fullest bin that still takes a piece; if none does and all bins
are open, the fullest one closes first. Bins left open at the end of a task are the items of a second round of the same packer
over all tasks' leftovers, so that the number of tasks costs next to nothing.

Memory of a task: one chunk of texts, the word cache and the open bins. Nothing is collected; what is shuffled is the leftover
bins alone. Results of a task depend on its input split only, so a lost task is redone alike.

Edge cases: a null or empty text is the end token alone (one piece of length 1); a text longer than a sequence is cut, its last
piece is packed like any other; repeated rows are packed each; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import os
import re
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, chunks, ragged, table, tidy

CAPACITY, END = 2048, 0
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long, bin long, offset long, open boolean"


SIMPLE = re.compile("[a-z\u00df-\u00f6\u00f8-\u00ff]+")


class WordTokenizer:
    """Ids of whole texts for a lower-casing tokenizer that drops white space: equal to encoding the text, since no token crosses it.

    Each distinct word is encoded once. Letters are lower-cased and sentence marks after a letter or digit are split off first, as the
    tokenizer itself does, so that there are fewer distinct words. Words of plain letters go to the merge model directly, others
    through the whole tokenizer; so do whole texts that might hold a special token. The cache is emptied when it holds ``limit`` words.
    """

    def __init__(self, path: str, limit: int = 500_000):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.tokenizer, self.limit = Tokenizer.from_file(path), limit
        self.model = self.tokenizer.model
        # the byte-level alphabet: printable bytes stand for themselves, the others follow from 256 on
        plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in set(plain)]
        self.alphabet = {b: chr(b) for b in plain} | {b: chr(256 + k) for k, b in enumerate(rest)}
        self.clear()

    def clear(self) -> None:
        self.known, self.ids, self.used = {}, np.zeros(1 << 16, np.uint32), 0
        self.first, self.count = np.zeros(1 << 14, np.int64), np.zeros(1 << 14, np.int64)

    def _coded(self, words: list[str]) -> list[list[int]]:
        out: list[list[int]] = []
        hard = []
        for word in words:
            if SIMPLE.fullmatch(word):
                if not word.isascii():
                    word = "".join(map(self.alphabet.__getitem__, word.encode()))
                out.append([t.id for t in self.model.tokenize(word)])
            else:
                hard.append(len(out))
                out.append([])
        for at in range(0, len(hard), 2000):
            own = hard[at : at + 2000]
            for k, e in zip(own, self.tokenizer.encode_batch_fast([words[k] for k in own], add_special_tokens=False)):
                out[k] = e.ids
        return out

    def _add(self, words: list[str]) -> None:
        base = len(self.known)
        need = base + len(words)
        if need > len(self.first):
            grow = max(need, 2 * len(self.first))
            self.first, self.count = np.resize(self.first, grow), np.resize(self.count, grow)
        coded = self._coded(words)
        counts = np.fromiter(map(len, coded), np.int64, len(coded))
        total = int(counts.sum())
        while self.used + total > len(self.ids):
            self.ids = np.resize(self.ids, 2 * len(self.ids))
        self.ids[self.used : self.used + total] = np.fromiter((i for c in coded for i in c), np.uint32, total)
        self.first[base:need], self.count[base:need] = self.used + np.cumsum(counts) - counts, counts
        self.used += total
        self.known.update(zip(words, range(base, need)))

    def __call__(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of each text; nulls are empty."""
        texts = pc.fill_null(texts, "")
        special = np.flatnonzero(pc.match_substring(texts, "<|").to_numpy(zero_copy_only=False))
        plain = pc.replace_substring_regex(pc.ascii_lower(texts), r"([a-z0-9])([.,;:!?]+)(\s|$)", r"\1 \2\3")
        split = pc.ascii_split_whitespace(plain)
        bounds = np.asarray(split.offsets, np.int64)
        words = split.flatten().dictionary_encode()
        names = words.dictionary.to_pylist()
        if len(self.known) + len(names) > self.limit:
            self.clear()
        new = [w for w in names if w not in self.known]
        if new:
            self._add(new)
        at = np.fromiter(map(self.known.__getitem__, names), np.int64, len(names))
        index = at[np.asarray(words.indices, np.int64)] if len(names) else np.zeros(0, np.int64)
        counts = self.count[index]
        cuts = np.concatenate([[0], np.cumsum(counts)])[bounds - bounds[0]]
        ids = self.ids[ragged(self.first[index], counts)]
        out = [ids[a:b] for a, b in zip(cuts, cuts[1:])]
        for k in special.tolist():
            out[k] = np.array(self.tokenizer.encode(texts[k].as_py(), add_special_tokens=False).ids, np.uint32)
        return out


class BestFit:
    """Bounded-space best-fit. bins: number -> fill; closed ones are forgotten."""

    def __init__(self, capacity: int, open_bins: int, base: int = 0):
        self.capacity, self.most, self.next = capacity, open_bins, base
        self.free, self.by_free, self.n_open = 0, {}, 0  # bit f of free: some open bin has f free tokens

    def _take(self, free: int) -> int:
        found = self.by_free[free]
        number = found.pop()
        if not found:
            del self.by_free[free]
            self.free &= ~(1 << free)
        self.n_open -= 1
        return number

    def _put(self, number: int, free: int) -> None:
        if free:
            self.by_free.setdefault(free, []).append(number)
            self.free |= 1 << free
            self.n_open += 1

    def add(self, length: int) -> tuple[int, int]:
        """(bin, offset in it) of the next piece."""
        fits = self.free >> length
        if fits:
            free = length + (fits & -fits).bit_length() - 1
            number = self._take(free)
        else:
            if self.n_open >= self.most:
                self._take((self.free & -self.free).bit_length() - 1)  # the fullest closes
            number, free = self.next, self.capacity
            self.next += 1
        self._put(number, free - length)
        return number, self.capacity - free

    def open_numbers(self) -> set[int]:
        return {n for found in self.by_free.values() for n in found}


def pieces_of(ids: np.ndarray, capacity: int = CAPACITY):
    """(piece, start, length, checksum) of a document's ids, the end token included."""
    for piece, start in enumerate(range(0, len(ids), capacity)):
        part = ids[start : start + capacity]
        yield piece, start, len(part), zlib.crc32(part.astype("<u4").tobytes())


def pack_texts(path: str, open_bins: int, capacity: int = CAPACITY):
    def run(batches):
        tokens, fit = WordTokenizer(path), BestFit(capacity, open_bins, TaskContext.get().partitionId() << 36)
        held: dict[int, list] = {}  # pieces of open bins
        done: list = []

        def emit(rows, still_open):
            cols = list(zip(*rows))
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64())
            names = ["doc_id", "piece", "start", "length", "ids_crc32", "bin", "offset"]
            return pa.RecordBatch.from_arrays([*(pa.array(c, k) for c, k in zip(cols, kinds)), pa.array([still_open] * len(rows))], names=[*names, "open"])

        for batch in chunks(batches, "text", 2 << 20):
            for doc, ids in zip(batch.column("doc_id").to_pylist(), tokens(batch.column("text"))):
                own = np.append(ids, np.uint32(END))
                for piece, start, length, crc in pieces_of(own, capacity):
                    number, offset = fit.add(length)
                    held.setdefault(number, []).append((doc, piece, start, length, crc, number, offset))
            live = fit.open_numbers()
            for number in [n for n in held if n not in live]:
                done += held.pop(number)
            if len(done) >= 5000:
                yield emit(done, False)
                done = []
        if done:
            yield emit(done, False)
        if left := [row for rows in held.values() for row in rows]:
            yield emit(left, True)

    return tidy(run)


def pack_bins(open_bins: int, capacity: int):
    def run(batches):
        fit = BestFit(capacity, open_bins, (1 << 62) + (TaskContext.get().partitionId() << 36))
        for batch in batches:
            fills = batch.column("fill").to_pylist()
            got = [fit.add(n) for n in fills]
            if got:
                yield pa.RecordBatch.from_arrays([batch.column("bin"), pa.array([g[0] for g in got], pa.int64()), pa.array([g[1] for g in got], pa.int64())], names=["bin", "sequence_id", "base"])

    return run


def best_fit(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, open_bins: int = 64, leftovers_per_task: int = 16_384) -> DataFrame:
    """One row for each piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    spark = docs.sparkSession
    packed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(pack_texts(tokenizer, open_bins, capacity), PIECES)
    packed = Scratch(spark, "packing").table("pieces", packed)
    bins = packed.filter("open").groupBy("bin").agg(F.sum("length").alias("fill"))
    n_bins = bins.count()
    tasks = max(1, -(-n_bins // leftovers_per_task))
    bins = bins.repartitionByRange(tasks, F.xxhash64("bin")).sortWithinPartitions(F.desc("fill"), "bin")
    moved = bins.mapInArrow(pack_bins(4 * open_bins, capacity), "bin long, sequence_id long, base long")
    cols = ["doc_id", "piece", "start", "length", "ids_crc32"]
    closed = packed.filter("NOT open").select(*cols, F.col("bin").alias("sequence_id"), "offset")
    left = packed.filter("open").join(moved, "bin").select(*cols, "sequence_id", (F.col("offset") + F.col("base")).alias("offset"))
    return closed.unionByName(left)


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def op8_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    return best_fit(table(spark, sf_dir, "documents"), tokenizer_path())
