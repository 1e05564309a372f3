"""Operator 7: token counts of sections by offset-mapped attribution.

A whole text is encoded once by a lossless byte-level tokenizer. The running sum of the tokens' byte lengths gives each token's
span; sections are joined with the spans by binary search. Sections are the text's lines (with their line ends), stretches that a column
gives by their first characters, or the fields of a record that are encoded as one text. A token that crosses a border is allocated by an explicit rule:

* ``start`` - to the section that holds its first byte;
* ``most`` - to the section that holds most of its bytes, the earlier one on a tie;
* ``share`` - to every section by its share of the bytes (fractions add up to one).

A map over the scan without a shuffle; memory is one chunk of texts. Under each rule the sections' counts add up to the text's.

Edge cases: a null or empty text has no section and no token; an empty line is a section of one byte, an empty field a section of its separator (the last
one of nothing, without tokens); given sections that are null count as one, and those that begin at or behind the end of the text are left out; a very long
text is encoded whole; repeated rows, and rows that share or lack a doc_id, give their own results; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks, table, utf8

RULES = ("start", "most", "share")
NEWLINE = 10


def load(path: str, pattern: str):
    """A tiktoken encoding of a rank file and the byte length of each token."""
    import base64

    import tiktoken

    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    sizes = np.zeros(max(ranks.values()) + 1, np.int64)
    for token, number in ranks.items():
        sizes[number] = len(token)
    return tiktoken.Encoding("lossless", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}), sizes


def line_starts(data: np.ndarray) -> np.ndarray:
    """First byte of each line; a line keeps its line end."""
    if not len(data):
        return np.zeros(0, np.int64)
    after = np.flatnonzero(data == NEWLINE) + 1
    return np.concatenate([[0], after[after < len(data)]])


def allocate(ends: np.ndarray, starts: np.ndarray, size: int, rule: str) -> tuple[np.ndarray, int]:
    """Tokens of each section and the number of tokens that cross a border.

    ends: end byte of each token; starts: first byte of each section, the first at 0.
    """
    begin = np.concatenate([[0], ends[:-1]]) if len(ends) else ends
    first = np.searchsorted(starts, begin, "right") - 1
    last = np.searchsorted(starts, ends, "left") - 1
    crossing = np.flatnonzero(last > first)
    n = len(starts)
    if rule == "start":
        return np.bincount(first, minlength=n).astype(float), len(crossing)
    out = np.bincount(np.delete(first, crossing), minlength=n).astype(float)
    limits = np.append(starts, size)
    for t in crossing:  # few: a token holds a border only where a line end merges with its neighbours
        own = np.arange(first[t], last[t] + 1)
        share = np.minimum(limits[own + 1], ends[t]) - np.maximum(limits[own], begin[t])
        if rule == "most":
            out[own[share.argmax()]] += 1
        else:
            out[own] += share / share.sum()
    return out, len(crossing)


def byte_places(data: np.ndarray, characters: list[int]) -> np.ndarray:
    """First bytes of sections that begin at the given characters, the first of them at 0."""
    begins = np.flatnonzero((data & 0xC0) != 0x80)
    at = np.unique([0, *characters])
    return begins[at[at < len(begins)]]


def counter(path: str, pattern: str, rule: str):
    """Batches of doc_id, text and maybe starts, the first characters of the sections."""
    if rule not in RULES:
        raise ValueError(rule)

    def run(batches):
        encoding, sizes = load(path, pattern)
        for batch in chunks(batches, "text", 4 << 20):
            data, bounds = utf8(batch.column("text"))
            totals, crossed, sections, counts = [], [], [], []
            given = batch.column("starts").to_pylist() if "starts" in batch.schema.names else None
            for k in range(batch.num_rows):
                own = data[bounds[k] : bounds[k + 1]]
                ids = np.asarray(encoding.encode_to_numpy(own.tobytes().decode(), allowed_special="all"), np.int64) if len(own) else np.zeros(0, np.int64)
                starts = line_starts(own) if given is None else byte_places(own, given[k] or [])
                got, n_cross = allocate(np.cumsum(sizes[ids]), starts, len(own), rule) if len(own) else (np.zeros(0), 0)
                totals.append(len(ids))
                crossed.append(n_cross)
                sections.append(len(starts))
                counts.append(got)
            values = pa.array(np.concatenate(counts) if counts else [], pa.float64())
            lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(sections)]), pa.int32()), values)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(totals, pa.int64()), pa.array(sections, pa.int64()), pa.array(crossed, pa.int64()), lists], names=["doc_id", "n_tokens", "n_sections", "n_crossing", "section_tokens"])

    return run


COUNTS = "doc_id long, n_tokens long, n_sections long, n_crossing long, section_tokens array<double>"


def section_tokens(docs: DataFrame, path: str, pattern: str, rule: str = "most", starts: str | None = None) -> DataFrame:
    """doc_id, n_tokens, n_sections, n_crossing, section_tokens of every row; starts: column of the sections' first characters, else lines."""
    own = [] if starts is None else [F.col(starts).cast("array<int>").alias("starts")]
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), *own)
    return slim.mapInArrow(counter(path, pattern, rule), COUNTS)


def field_tokens(docs: DataFrame, fields: list[str], path: str, pattern: str, rule: str = "most") -> DataFrame:
    """doc_id, n_tokens, fields (a map) of every row: its fields are encoded as one text, one a line; a separator belongs to the field before it."""
    parts = [F.coalesce(F.col(f).cast("string"), F.lit("")) for f in fields]
    begin, starts = F.lit(0), []
    for part in parts:
        starts.append(begin)
        begin = begin + F.length(part) + 1
    whole = docs.select("doc_id", F.concat_ws("\n", *parts).alias("text"), F.array(*starts).alias("starts"))
    got = section_tokens(whole, path, pattern, rule, "starts")
    # an empty last field begins at the end of the text
    names = F.array(*map(F.lit, fields))
    return got.select("doc_id", "n_tokens", F.map_from_arrays(names, F.transform(names, lambda _, k: F.coalesce(F.get("section_tokens", k), F.lit(0.0)))).alias("fields"))


def op7_section_tokens(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers as public

    out = section_tokens(table(spark, sf_dir, "documents"), str(public.path("byte_bpe_50k.tiktoken")), public.PATTERN)
    return out.withColumn("section_tokens", F.col("section_tokens").cast("array<bigint>"))


def document_field_tokens(spark, sf_dir: str) -> DataFrame:
    """Tokens of source, language and text of every document, encoded as one record."""
    import public_tokenizers as public

    out = field_tokens(table(spark, sf_dir, "documents"), ["source", "lang", "text"], str(public.path("byte_bpe_50k.tiktoken")), public.PATTERN)
    return out.select("doc_id", "n_tokens", *[F.col("fields")[f].cast("long").alias(f) for f in ("source", "lang", "text")])
