"""Shared helpers: scratch tables in the cluster's shared folder and Arrow text access."""

from __future__ import annotations

import ctypes
from itertools import accumulate, takewhile

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.scratch import Tables


class Scratch(Tables):
    """Tables of one operator run."""

    def table(self, name: str, df: DataFrame) -> DataFrame:
        return self.put(name, df)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


NO_ID = -(1 << 63)  # stands for a null id inside an operator; it counts as the smallest id


def id_in(name: str):
    return F.coalesce(F.col(name).cast("long"), F.lit(NO_ID))


def id_out(name: str):
    return F.nullif(F.col(name), F.lit(NO_ID)).alias(name)


def bounded_sample(rows: DataFrame, text: str, most: int, most_bytes: int) -> pa.Table:
    """Whole rows, at most `most` and of at most `most_bytes` text together, drawn by a hash of each row; a longer text cannot be drawn.

    The hash covers the row's place in the scan, so that copies are drawn one by one. Sizes come first, texts only for the rows that are drawn.
    """
    own = F.xxhash64(text, F.monotonically_increasing_id())
    slim = rows.withColumns({"__h": own, "__n": F.octet_length(text)}).filter(F.col("__n") <= most_bytes)
    total = slim.count()
    bits = 1 << 40
    bar = min(bits, int(bits * (1.5 * most + 50) / max(total, 1)))
    near = slim.filter(F.shiftrightunsigned(F.col("__h"), 24) < F.lit(bar))
    sizes = near.select("__h", "__n").orderBy("__h", "__n").limit(most).collect()
    taken = list(takewhile(lambda s: s[0] <= most_bytes, zip(accumulate(r["__n"] for r in sizes), sizes)))
    last = taken[-1][1]["__h"] if taken else None
    drawn = near.filter(F.col("__h") <= F.lit(last)) if taken else near.limit(0)
    return drawn.orderBy("__h", "__n").limit(len(taken)).drop("__h", "__n").toArrow()


def utf8(column) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of an Arrow string column; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, "")
    column = column.cast(pa.large_binary())
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    data = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    if not len(offsets):
        offsets = np.zeros(1, np.int64)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def chunks(batches, text: str, limit: int = 8 << 20):
    """Slices of record batches whose texts have at most `limit` bytes together (a longer text stands alone)."""
    for batch in batches:
        if not batch.num_rows:
            continue
        _, offsets = utf8(batch.column(text))
        at = 0
        while at < batch.num_rows:
            to = int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1
            to = min(max(to, at + 1), batch.num_rows)
            yield batch.slice(at, to - at)
            at = to


def give_back() -> None:
    """Returns the free memory of this process to the system."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # glibc only
        trim(0)


def tidy(run):
    """The function of batches, followed by give_back: a Python worker lives on for other tasks and stages, whose memory adds to what it keeps."""

    def tidied(batches):
        yield from run(batches)
        give_back()

    return tidied


def ragged(starts: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Concatenated ranges start, start + 1, ... of the given lengths."""
    total = int(counts.sum())
    if not total:
        return np.zeros(0, np.int64)
    before = np.cumsum(counts) - counts
    return np.repeat(starts - before, counts) + np.arange(total)


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words."""
    x = x.astype(np.uint64, copy=True)
    for shift, factor in ((33, 0xFF51AFD7ED558CCD), (29, 0xC4CEB9FE1A85EC53)):
        x ^= x >> np.uint64(shift)
        x *= np.uint64(factor)
    return x ^ (x >> np.uint64(32))
