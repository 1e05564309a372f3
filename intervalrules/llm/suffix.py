"""Operator 4: exact removal of repeated byte strings with per-shard suffix arrays.

A byte is removed if it lies in a string of ``length`` bytes that also starts elsewhere. Work goes by distinct text (equal texts are repeated as a whole):

1. Anchors. Each window of ``length`` bytes names the smallest hash of its short substrings as its anchor, so equal windows
   have equal anchors; runs of windows share one. Anchors that occur once in the corpus cannot repeat and go no further.
2. Shards. The stretches of text around repeated anchors are dealt by anchor, so equal windows meet in one shard. There equal stretches
   are folded, and what is left gets a suffix array (Larsson-Sadakane refinement from 8-byte ranks: only unresolved groups are
   sorted again, with doubled depth) and its common prefixes (Kasai's relation: a position whose predecessor moves along inherits its
   prefix less one, the others are compared).
3. Anchors that are too frequent for one shard are split over many; their sorted windows, named by two independent 64-bit digests, are dealt by
   range and merged by binary search, which finds the windows that repeat in other shards only.
4. Marked windows return to their texts, which are cut.

Texts are shuffled once, compressed, into a bucketed table below the shared folder; what is shuffled later is anchors, stretches of repeated
text and marks.

Edge cases: null and empty texts keep nothing and lose nothing; texts shorter than ``length`` lose nothing; long runs of one byte are
ordinary windows; repeated rows and doc_ids each get their row; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
import uuid

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, chunks, mix64, ragged, table, utf8
from .decontam import BASE, powers
from .neardup import runs

LENGTH, GRAM = 200, 24
OTHER_BASE = 0xD6E8FEB86659FD93  # of the second digest of a window
SPAN = 1 << 21  # places compared at once; their number fits the low 24 bits of a key
ENTRY = np.dtype([("h", "<u4"), ("t1", "<i8"), ("t2", "<i8"), ("lo", "<i4"), ("n", "<i4"), ("more", "<i4")])


def gram_hashes(data: np.ndarray, k: int, base: int = BASE) -> np.ndarray:
    up, down = powers(len(data), base)
    sums = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up[: len(data)], out=sums[1:])
    return mix64((sums[k:] - sums[:-k]) * down[: len(data) - k + 1])


def sliding_min(keys: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each w consecutive keys."""
    n = len(keys) - w + 1
    pad = -len(keys) % w
    full = np.concatenate([keys, np.full(pad, ~np.uint64(0))]).reshape(-1, w)
    ahead = np.minimum.accumulate(full, axis=1).ravel()
    back = np.minimum.accumulate(full[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[w - 1 : w - 1 + n])


def anchor_runs(data: np.ndarray, bounds: np.ndarray, length: int = LENGTH, gram: int = GRAM):
    """(anchor hash, text, first window, number of windows) of every run of windows with one anchor; places count from the text's start."""
    w = length - gram + 1
    hs, docs, los, ns = [], [], [], []
    for at in range(0, len(data) - length + 1, SPAN):
        part = data[at : min(len(data), at + SPAN + length - 1)]
        h = gram_hashes(part, gram)
        key = (h & ~np.uint64((1 << 24) - 1)) | np.arange(len(h), dtype=np.uint64)
        anchor = (sliding_min(key, w) & np.uint64((1 << 24) - 1)).astype(np.int64)
        place = np.arange(len(anchor)) + at
        doc = np.searchsorted(bounds, place, "right") - 1 if len(bounds) < 64 else np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))[place]
        valid = place + length <= bounds[doc + 1]
        head = valid.copy()
        head[1:] &= ~valid[:-1] | (anchor[1:] != anchor[:-1]) | (doc[1:] != doc[:-1])
        begin = np.flatnonzero(head)
        if not len(begin):
            continue
        ends = np.concatenate([[0], np.cumsum(valid)])
        count = np.diff(np.append(ends[begin], ends[-1]))
        hs.append(h[anchor[begin]])
        docs.append(doc[begin])
        los.append(place[begin] - bounds[doc[begin]])
        ns.append(count)
    if not hs:
        return np.zeros(0, np.uint64), *(np.zeros(0, np.int64),) * 3
    return tuple(np.concatenate(x) for x in (hs, docs, los, ns))


# ---- suffix arrays ----


def words8(data: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on as a number; the end is padded with zeros."""
    pad = np.concatenate([data, np.zeros(8, np.uint8)]).astype(np.uint64)
    out = np.zeros(len(data), np.uint64)
    for j in range(8):
        out |= pad[j : j + len(data)] << np.uint64(56 - 8 * j)
    return out


def suffix_array(data: np.ndarray, depth: int) -> np.ndarray:
    """Places sorted by their first `depth` bytes or more (a suffix that ends is smaller)."""
    n = len(data)
    key = words8(data)
    sa = np.argsort(key, kind="stable")
    same = key[sa[1:]] == key[sa[:-1]]
    head = np.concatenate([[True], ~same]) if n else np.zeros(0, bool)
    rank = np.zeros(n + 1, np.int64)
    rank[n] = -1
    rank[sa] = np.maximum.accumulate(np.where(head, np.arange(n), 0))
    # padding zeros equal real ones in the first ranks; the ranks past the end tell them apart below
    h = 8
    while h < depth:
        alone = head & np.append(head[1:], True)
        open_ = np.flatnonzero(~alone)
        if not len(open_):
            break
        at = sa[open_]
        pair = rank[at] * (n + 2) + rank[np.minimum(at + h, n)] + 1
        order = np.argsort(pair, kind="stable")
        sa[open_] = at[order]
        pair = pair[order]
        new = np.ones(len(open_), bool)
        new[1:] = pair[1:] != pair[:-1]
        head[open_] = new
        rank[sa[open_]] = np.maximum.accumulate(np.where(new, open_, 0))
        h *= 2
    return sa


def common_prefixes(data: np.ndarray, sa: np.ndarray, most: int) -> np.ndarray:
    """Length of the prefix that each suffix shares with the one before it in the array, exact below `most`, else at least that."""
    n = len(data)
    before = np.full(n, -1, np.int64)
    before[sa[1:]] = sa[:-1]
    follows = np.zeros(n, bool)
    # only after a prefix of one byte or more: after a prefix of 0 the next one can have any length
    shared = (before[:-1] >= 0) & (data[:-1] == data[before[:-1]])
    follows[1:] = (before[1:] == before[:-1] + 1) & shared & (np.arange(1, n) % most != 0)
    own = np.flatnonzero(~follows & (before >= 0))
    plain = np.zeros(n, np.int64)
    key = words8(data)
    alive, got = own, np.zeros(n, np.int64)
    step = 0
    while len(alive) and step < 2 * most + 8:
        a, b = alive + step, before[alive] + step
        ok = (a < n) & (b < n)
        alive, a, b = alive[ok], a[ok], b[ok]
        x = key[a] ^ key[b]
        same = x == 0
        ended = ~same
        if ended.any():
            zeros = (63 - np.floor(np.log2(x[ended].astype(np.float64)))).astype(np.int64)
            zeros -= (x[ended] >> np.minimum(63 - np.minimum(zeros, 63), 63).astype(np.uint64)) == 0  # rounding of the logarithm
            got[alive[ended]] = step + np.clip(zeros, 0, 63) // 8
        got[alive[same]] = step + 8
        alive = alive[same]
        step += 8
    limit = np.minimum(n - np.arange(n), np.where(before >= 0, n - before, 0))
    plain[own] = np.minimum(got[own], limit[own])
    # Kasai: along a chain of followers the value falls by one and stays above or at 0
    base = np.where(follows, -1, np.arange(n))
    base = np.maximum.accumulate(base)
    return np.where(follows, np.maximum(plain[base] - (np.arange(n) - base), 0), plain)[sa]


def repeated_windows(segments: list[bytes], counts: list[int], weights: list[int], length: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """(repeated?, group of equal windows) for the first counts[i] windows of each segment; weights: how often it stands in the shard."""
    data = np.frombuffer(b"".join(segments), np.uint8)
    begin = np.concatenate([[0], np.cumsum([len(s) for s in segments])])[:-1]
    sa = suffix_array(data, length)
    lcp = common_prefixes(data, sa, 3 * length)
    group = np.zeros(len(data), np.int64)
    group[sa] = np.cumsum(lcp < length)
    counts = np.asarray(counts)
    at = ragged(begin, counts)
    own = group[at]
    total = np.bincount(own, np.repeat(np.asarray(weights), counts), minlength=own.max() + 1 if len(own) else 0)
    cuts = np.cumsum(counts)[:-1]
    return np.split(total[own] >= 2, cuts), np.split(own, cuts)


# ---- stages ----


def text_key(text: bytes) -> tuple[int, int]:
    d = hashlib.blake2b(text, digest_size=16).digest()
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


def digester(with_text: bool):
    def run(batches):
        squeeze = zstandard.ZstdCompressor(level=1)
        for batch in chunks(batches, "text", 16 << 20):
            data, bounds = utf8(batch.column("text"))
            texts = [data[a:b].tobytes() for a, b in zip(bounds, bounds[1:])]
            keys = np.array([text_key(t) for t in texts], np.int64).reshape(-1, 2)
            cols = [pa.array(keys[:, 0].copy()), pa.array(keys[:, 1].copy())]
            if with_text:
                yield pa.RecordBatch.from_arrays([*cols, pa.array([squeeze.compress(t) for t in texts], pa.binary())], names=["t1", "t2", "z"])
            else:
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *cols], names=["doc_id", "t1", "t2"])

    return run


def expanded(batches, limit: int = 2 << 20):
    """(keys, bytes, bounds) of groups of texts."""
    expand = zstandard.ZstdDecompressor()
    keys, texts, size = [], [], 0
    for batch in batches:
        for row in zip(*(batch.column(c).to_pylist() for c in ("t1", "t2", "z"))):
            texts.append(expand.decompress(row[2]))
            keys.append(row[:2])
            size += len(texts[-1])
            if size >= limit:
                yield keys, texts
                keys, texts, size = [], [], 0
    if keys:
        yield keys, texts


def anchor_blocks(buckets: int, local_most: int, shard_most: int):
    """Blocks of anchors for buckets (kind 0), and anchors that are frequent within one task's chunk as finished candidates (kind 1)."""

    def run(batches):
        for keys, texts in expanded(batches):
            data = np.frombuffer(b"".join(texts), np.uint8)
            bounds = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
            if len(data) < LENGTH:
                continue
            h, doc, lo, n = anchor_runs(data, bounds)
            key = np.array(keys, np.int64)
            e = np.zeros(len(h), ENTRY)
            bucket = ((h >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)
            e["h"], e["t1"], e["t2"], e["lo"], e["n"] = h.astype(np.uint32), key[doc, 0], key[doc, 1], lo, n
            order = np.lexsort((e["h"], bucket))
            e, bucket = e[order], bucket[order]
            head = np.ones(len(e), bool)
            head[1:] = (bucket[1:] != bucket[:-1]) | (e["h"][1:] != e["h"][:-1])
            begin = np.flatnonzero(head)
            size = np.diff(np.append(begin, len(e)))
            frequent = np.repeat(size > local_most, size)
            e["more"][begin[size > local_most]] = 1
            kinds, bs, xs = [], [], []
            salt = int(key[0, 0]) & 0x3FFFFFFF
            rest = frequent & ~head
            if rest.any():
                own = e[rest]
                # no more than shard_most of them meet in one shard
                nth = np.arange(len(e)) - np.repeat(begin, size)
                own["more"] = (salt + nth[rest] // shard_most) & 0x3FFFFFFF
                for b in np.unique(bucket[rest]):
                    kinds.append(1)
                    bs.append(int(b))
                    xs.append(own[bucket[rest] == b].tobytes())
            go = ~rest
            e, bucket = e[go], bucket[go]
            cuts = np.searchsorted(bucket, np.arange(buckets + 1))
            for b in np.flatnonzero(np.diff(cuts)):
                kinds.append(0)
                bs.append(int(b))
                xs.append(e[cuts[b] : cuts[b + 1]].tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(kinds, pa.int32()), pa.array(bs, pa.int32()), pa.array(xs, pa.binary())], names=["kind", "bucket", "x"])

    return run


CANDIDATES = "t1 long, t2 long, lo int, n int, anchor long, salt int"


def candidate_rows(e: np.ndarray, bucket: int, salt: np.ndarray):
    """salt -1: the anchor stays in one shard."""
    anchor = e["h"].astype(np.int64) << 20 | bucket
    return pa.RecordBatch.from_arrays([pa.array(e["t1"].copy()), pa.array(e["t2"].copy()), pa.array(e["lo"].copy()), pa.array(e["n"].copy()), pa.array(anchor), pa.array(salt.astype(np.int32))], names=["t1", "t2", "lo", "n", "anchor", "salt"])


def repeated_anchors(most: int):
    """Entries of anchors that occur twice or more; frequent ones are salted."""

    def run(batches):
        for (bucket,), held in runs(batches, ("bucket",), ("x",)):
            e = np.frombuffer(b"".join(r[0] for r in held), ENTRY)
            e = e[np.argsort(e["h"], kind="stable")]
            begin = np.flatnonzero(np.concatenate([[True], e["h"][1:] != e["h"][:-1]]))
            size = np.diff(np.append(begin, len(e)))
            more = np.maximum.reduceat(e["more"], begin)
            keep = np.repeat((size > 1) | (more > 0), size)
            split = np.repeat((size > most) | (more > 0), size)
            nth = np.arange(len(e)) - np.repeat(begin, size)
            salt = np.where(split, nth // most, -1)
            if keep.any():
                yield candidate_rows(e[keep], bucket, salt[keep])

    return run


def local_candidates(batches):
    for batch in batches:
        for bucket, x in zip(batch.column("bucket").to_pylist(), batch.column("x").to_pylist()):
            e = np.frombuffer(x, ENTRY)
            yield candidate_rows(e, bucket, e["more"].astype(np.int64))


def cutter(length: int):
    """Stretches of text of the candidates of each text."""

    def run(batches):
        expand = zstandard.ZstdDecompressor()
        kinds = (pa.int64(), pa.int32(), pa.binary(), pa.int64(), pa.int64(), pa.int32(), pa.int32())
        pack = lambda rows: pa.RecordBatch.from_arrays([pa.array(r, k) for r, k in zip(rows, kinds)], names=["anchor", "salt", "seg", "t1", "t2", "lo", "n"])
        for batch in batches:
            rows = [[], [], [], [], [], [], []]
            for t1, t2, z, runs_ in zip(*(batch.column(c).to_pylist() for c in ("t1", "t2", "z", "runs"))):
                text = expand.decompress(z)
                for r in runs_:
                    for out, v in zip(rows, (r["anchor"], r["salt"], text[r["lo"] : r["lo"] + r["n"] - 1 + length], t1, t2, r["lo"], r["n"])):
                        out.append(v)
                if len(rows[0]) >= 20_000:
                    yield pack(rows)
                    rows = [[], [], [], [], [], [], []]
            yield pack(rows)

    return run


def stretches(flags: np.ndarray, lo: int, length: int) -> list[tuple[int, int]]:
    """Byte stretches covered by the flagged windows that start at lo, lo + 1, ..."""
    at = np.flatnonzero(flags)
    if not len(at):
        return []
    gap = np.flatnonzero(np.diff(at) > length)
    return [(lo + int(at[a]), lo + int(at[b]) + length) for a, b in zip([0, *(gap + 1)], [*gap, len(at) - 1])]


SHARDED = "t1 long, t2 long, s int, e int, part int, x binary"
HOT = np.dtype([("d", "<u8"), ("c", "<u8"), ("t1", "<i8"), ("t2", "<i8"), ("p", "<i4"), ("unique", "<i4")])


def sharder(length: int, merge_parts: int):
    """Marks found inside one shard; digests of the windows of split anchors for the merge."""

    def run(batches):
        for (shard,), held in runs(batches, ("shard",), ("anchor", "salt", "seg", "t1", "t2", "lo", "n")):
            folded: dict[tuple, list] = {}
            for row in held:
                folded.setdefault((row[0], row[1], row[2]), []).append(row)
            alike: dict[tuple, int] = {}
            for anchor, salt, _ in folded:
                alike[anchor, salt] = alike.get((anchor, salt), 0) + 1
            marks: list[tuple[int, int, int, int]] = []
            hard = []
            for key, rows in folded.items():
                if key[1] < 0 and alike[key[:2]] == 1:
                    if len(rows) > 1:  # the only stretch of its anchor, several times
                        marks += [(r[3], r[4], r[5], r[5] + r[6] - 1 + length) for r in rows]
                else:
                    hard.append((key, rows))
            hot = []
            if hard:
                # equal stretches have equal numbers of windows, for the anchor's run is decided by the content; take the widest to be safe
                counts = [max(r[6] for r in rows) for _, rows in hard]
                flags, groups = repeated_windows([k[2] for k, _ in hard], counts, [len(rows) for _, rows in hard], length)
                seen: set[int] = set()
                for (key, rows), flag, group in zip(hard, flags, groups):
                    for r in rows:
                        marks += [(r[3], r[4], a, b) for a, b in stretches(flag[: r[6]], r[5], length)]
                    if key[1] >= 0:
                        raw = np.frombuffer(key[2], np.uint8)
                        fresh = np.array([g not in seen for g in group.tolist()], bool)
                        seen.update(group.tolist())
                        at = np.flatnonzero(fresh)
                        if len(at):
                            e = np.zeros(len(at), HOT)
                            e["d"] = mix64(gram_hashes(raw, length)[at] ^ np.uint64(key[0] & 0x7FFFFFFFFFFFFFFF))
                            e["c"] = mix64(gram_hashes(raw, length, OTHER_BASE)[at])
                            e["t1"], e["t2"], e["p"], e["unique"] = rows[0][3], rows[0][4], rows[0][5] + at, ~flag[at]
                            hot.append(e)
            if marks:
                t1, t2, s, e = zip(*marks)
                yield pa.RecordBatch.from_arrays([pa.array(t1, pa.int64()), pa.array(t2, pa.int64()), pa.array(s, pa.int32()), pa.array(e, pa.int32()), pa.nulls(len(s), pa.int32()), pa.nulls(len(s), pa.binary())], names=["t1", "t2", "s", "e", "part", "x"])
            if hot:
                e = np.concatenate(hot)
                e = e[np.argsort(e["d"])]
                part = ((e["d"] >> np.uint64(32)) * np.uint64(merge_parts) >> np.uint64(32)).astype(np.int64)
                cuts = np.searchsorted(part, np.arange(merge_parts + 1))
                own = np.flatnonzero(np.diff(cuts))
                none = pa.nulls(len(own), pa.int64())
                yield pa.RecordBatch.from_arrays([none, none, pa.nulls(len(own), pa.int32()), pa.nulls(len(own), pa.int32()), pa.array(own, pa.int32()), pa.array([e[cuts[b] : cuts[b + 1]].tobytes() for b in own], pa.binary())], names=["t1", "t2", "s", "e", "part", "x"])

    return run


def digests(e: np.ndarray) -> np.ndarray:
    """Both digests of each window as 16 bytes that sort like the first one."""
    out = np.empty((len(e), 2), ">u8")
    out[:, 0], out[:, 1] = e["d"], e["c"]
    return out.view("S16").ravel()


def merger(length: int):
    """Windows that are single in their shard but found in another shard's sorted list."""

    def run(batches):
        for _, held in runs(batches, ("part",), ("x",)):
            lists = [np.frombuffer(r[0], HOT) for r in held]
            every = np.sort(np.concatenate([digests(e) for e in lists]))
            for e in lists:
                own = digests(e)
                found = np.searchsorted(every, own, "right") - np.searchsorted(every, own, "left") > 1
                take = e[found & (e["unique"] == 1)]
                if len(take):
                    yield pa.RecordBatch.from_arrays([pa.array(take["t1"].copy()), pa.array(take["t2"].copy()), pa.array(take["p"].copy()), pa.array((take["p"] + length).astype(np.int32))], names=["t1", "t2", "s", "e"])

    return run


def merged_spans(marks: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for a, b in sorted(marks):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [tuple(x) for x in out]


def remover(length: int, with_text: bool):
    def run(batches):
        expand, squeeze = zstandard.ZstdDecompressor(), zstandard.ZstdCompressor(level=1)
        for batch in batches:
            rows = []
            for t1, t2, z, copies, marks in zip(*(batch.column(c).to_pylist() for c in ("t1", "t2", "z", "copies", "marks"))):
                text = expand.decompress(z)
                spans = [(0, len(text))] if copies > 1 and len(text) >= length else merged_spans([(m["s"], m["e"]) for m in marks or []])
                kept, at = [], 0
                for a, b in spans:
                    kept.append(text[at:a])
                    at = b
                kept = b"".join([*kept, text[at:]])
                rows.append((t1, t2, len(text), sum(b - a for a, b in spans), len(spans), hashlib.sha256(kept).hexdigest(), squeeze.compress(kept) if with_text else None))
            cols = list(zip(*rows)) if rows else [[]] * 7
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
            names = ["t1", "t2", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names=names)

    return run


def _without_repeats(texts: DataFrame, copies: DataFrame, scratch: Scratch, parts: int, buckets: int, length: int, local_most: int, shard_most: int, with_text: bool) -> DataFrame:
    """t1, t2, n_bytes, n_removed, n_spans, kept_sha256, kept of every distinct text."""
    blocks = scratch.table("blocks", texts.mapInArrow(anchor_blocks(buckets, local_most, shard_most), "kind int, bucket int, x binary"))
    dealt = blocks.filter("kind = 0").select("bucket", "x").repartition(parts, "bucket").sortWithinPartitions("bucket")
    found = dealt.mapInArrow(repeated_anchors(shard_most), CANDIDATES).unionByName(blocks.filter("kind = 1").select("bucket", "x").mapInArrow(local_candidates, CANDIDATES))
    runs_of = found.groupBy("t1", "t2").agg(F.collect_list(F.struct("lo", "n", "anchor", "salt")).alias("runs"))
    cut = texts.join(runs_of, ["t1", "t2"]).select("t1", "t2", "z", "runs").mapInArrow(cutter(length), "anchor long, salt int, seg binary, t1 long, t2 long, lo int, n int")
    cut = cut.withColumn("shard", F.pmod(F.xxhash64("anchor", "salt"), F.lit(8 * parts)).cast("int"))
    cut = cut.repartition(parts, "shard").sortWithinPartitions("shard")
    sharded = scratch.table("sharded", cut.mapInArrow(sharder(length, parts), SHARDED))
    scratch.drop("blocks")
    hot = sharded.filter("part IS NOT NULL").select("part", "x").repartition(parts, "part").sortWithinPartitions("part")
    marks = sharded.filter("part IS NULL").select("t1", "t2", "s", "e").unionByName(hot.mapInArrow(merger(length), "t1 long, t2 long, s int, e int"))
    marks = marks.groupBy("t1", "t2").agg(F.collect_list(F.struct("s", "e")).alias("marks")).join(copies, ["t1", "t2"], "right")
    done = texts.join(marks, ["t1", "t2"]).select("t1", "t2", "z", "copies", "marks").mapInArrow(remover(length, with_text), "t1 long, t2 long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
    return scratch.table("done", done)


def remove_repeats(docs: DataFrame, length: int = LENGTH, local_most: int = 32, shard_most: int = 512, with_text: bool = False) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and the kept bytes, zstd) of every row."""
    if length != LENGTH:
        raise ValueError("the anchor scheme is laid out for one length")
    spark = docs.sparkSession
    scratch = Scratch(spark, "suffix")
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8)
    buckets = min(4 * parts, 1 << 20)
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    rows = scratch.table("rows", slim.mapInArrow(digester(False), "doc_id long, t1 long, t2 long"))
    copies = rows.groupBy("t1", "t2").agg(F.count(F.lit(1)).alias("copies"))
    name = f"texts_{uuid.uuid4().hex}"
    texts = slim.select("text").mapInArrow(digester(True), "t1 long, t2 long, z binary").dropDuplicates(["t1", "t2"])
    texts.repartition(parts, "t1", "t2").write.option("path", f"{scratch.root}/texts").option("compression", "uncompressed").format("parquet").bucketBy(parts, "t1", "t2").saveAsTable(name)
    try:
        done = _without_repeats(spark.table(name), copies, scratch, parts, buckets, length, local_most, shard_most, with_text)
    finally:
        spark.sql(f"DROP TABLE IF EXISTS {name}")
    scratch.drop("texts")
    scratch.drop("sharded")
    out = rows.join(done, ["t1", "t2"])
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", *(["kept"] if with_text else []))


def op4_suffix_shards(spark, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"))
