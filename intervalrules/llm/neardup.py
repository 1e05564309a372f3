"""Operator 2: near-duplicate vectors by neighbour descent.

1. Equal vectors become one representative with a count and a number of its own. Vectors that are null, zero or not finite take no part.
2. The neighbour graph starts from random projections: in each of several trees the vectors are sorted by their sign code, and
   each takes its nearest neighbours among the rows around it. The number of trees follows from the number of vectors, so that
   a pair at the threshold meets with the probability ``meet``.
3. Descent: the neighbours (both ways) of each vector are compared with each other, and lists keep the best ``k``. Rounds go on
   until at most ``settle`` of the entries change. Large neighbourhoods are compared in sub-groups, dealt anew in each round. A list
   (short ones too) is saturated when even its last entry reaches the threshold: it may lack links. Saturated lists are doubled, up to ``widest`` places,
   and descent goes on for them and their neighbours.
4. Edges at the threshold give components. What lists of any bounded length cannot hold follows exactly: vectors that are still saturated
   are put into balls (centre and radius) of at most ``block`` rows of one component; balls of different components that are near enough to hold a
   link are compared in full, and a link merges their components.
5. Every component of two or more is compared in full in blocks of ``block`` rows, in double precision. This makes the links of a
   component complete, and only counts leave a block pair, never pairs.
6. Audit: the links of a random sample of vectors are counted by brute force. While the share of them that was found is below ``meet``,
   twice as many further trees are added to the lists and steps 3 to 5 run again. The share is logged.

Memory: blocks of fixed size. Every step is written to the shared folder.

Edge cases: an empty table gives no rows; arrays of other lengths than the first valid one's group are compared only with those of equal length
(a missing dimension has no cosine); rows that share a vec_id, or have none, are judged by their own vectors (a null counts as the smallest
id); other columns, labels included, are not read.
"""

from __future__ import annotations

import logging
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Scratch, id_in, id_out, table
from .graph import components


def encoder(dtype: str):
    def run(batches):
        for batch in batches:
            lists = batch.column("embedding")
            out = []
            for k in range(batch.num_rows):
                v = lists[k].values if lists[k].is_valid else None
                if v is None or not len(v) or v.null_count:
                    out.append(None)
                    continue
                x = v.to_numpy(zero_copy_only=False).astype(dtype)
                out.append(x.tobytes() if np.isfinite(x).all() and np.any(x) else None)
            yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(out, pa.binary())], names=["vec_id", "vec"])

    return run


def unit(vecs: list[bytes], dtype: str) -> np.ndarray:
    """Rows of length one in double precision; scaling first keeps tiny and huge values finite."""
    x = np.frombuffer(b"".join(vecs), dtype).reshape(len(vecs), -1).astype(np.float64)
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def projector(trees: int, bits: int, dtype: str, seed: int):
    def run(batches):
        planes: dict[int, np.ndarray] = {}
        for batch in batches:
            vecs = batch.column("vec").to_pylist()
            ids = batch.column("id").to_numpy()
            for size in sorted({len(v) for v in vecs}):
                own = [k for k, v in enumerate(vecs) if len(v) == size]
                x = unit([vecs[k] for k in own], dtype)
                if size not in planes:
                    planes[size] = np.random.default_rng(seed + size).normal(size=(x.shape[1], trees * bits))
                code = (x @ planes[size] > 0).reshape(len(own), trees, bits) @ (1 << np.arange(bits - 1, -1, -1, dtype=np.int64))
                n = len(own)
                yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(trees, dtype=np.int32), n)), pa.array(np.full(n * trees, size), pa.int32()), pa.array(code.T.ravel(), pa.int64()), pa.array(np.tile(ids[own], trees), pa.int64()), pa.array([vecs[k] for k in own] * trees, pa.binary())], names=["tree", "size", "code", "id", "vec"])

    return run


LOG = logging.getLogger(__name__)
LISTS = "id long, near array<struct<s:float,j:long>>"


def as_lists(ids, rows) -> pa.RecordBatch:
    """rows: (similarities, ids) of each id."""
    counts = [len(r[0]) for r in rows]
    s = np.concatenate([r[0] for r in rows]) if rows else np.zeros(0)
    j = np.concatenate([r[1] for r in rows]) if rows else np.zeros(0)
    items = pa.StructArray.from_arrays([pa.array(s, pa.float32()), pa.array(j, pa.int64())], names=["s", "j"])
    return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(counts)]), pa.int32()), items)], names=["id", "near"])


def top(s: np.ndarray, k: int) -> np.ndarray:
    k = min(k, s.shape[1])
    return np.argpartition(-s, k - 1, axis=1)[:, :k]


def around(k: int, dtype: str, block: int):
    """Nearest rows among the `block` rows before and in the same block, in sort order."""

    def run(batches):
        held: list[tuple] = []

        def compare(rows, new):
            ids = np.array([r[2] for r in rows])
            x = unit([r[3] for r in rows], dtype).astype(np.float32)
            fresh = slice(len(rows) - new, len(rows))
            s = x @ x.T
            np.fill_diagonal(s, -2)
            if new < len(rows):
                s[: len(rows) - new, : len(rows) - new] = -2  # compared before
            at = top(s, k)
            return as_lists(ids, [(s[i, at[i]][s[i, at[i]] > -2], ids[at[i]][s[i, at[i]] > -2]) for i in range(len(rows))])

        for batch in batches:
            rows = list(zip(*(batch.column(c).to_pylist() for c in ("tree", "size", "id", "vec"))))
            for row in rows:
                if held and held[-1][:2] != row[:2]:
                    if len(held) > 1:
                        yield compare(held, min(len(held), block))
                    held = []
                held.append(row)
                if len(held) == 2 * block:
                    yield compare(held, block)
                    held = held[block:]
        if len(held) > 1:
            yield compare(held, min(len(held), block))

    return run


def runs(batches, keys: tuple[str, ...], names: tuple[str, ...]):
    """Rows of sorted batches, grouped by their keys; a run may span batches."""
    now, held = None, []
    for batch in batches:
        for row in zip(*(batch.column(c).to_pylist() for c in (*keys, *names))):
            key = row[: len(keys)]
            if key != now:
                if held:
                    yield now, held
                now, held = key, []
            held.append(row[len(keys) :])
    if held:
        yield now, held


def local_join(k: int, dtype: str):
    """Compares the members of each neighbourhood; gives each member those better than its last entry."""

    def run(batches):
        ids, rows = [], []
        for _, held in runs(batches, ("u", "part"), ("id", "vec", "last")):
            if len(held) < 2:
                continue
            own = np.array([r[0] for r in held])
            x = unit([r[1] for r in held], dtype).astype(np.float32)
            last = np.array([r[2] for r in held], np.float32)
            s = x @ x.T
            np.fill_diagonal(s, -2)
            at = top(s, k)
            best = np.take_along_axis(s, at, 1)
            good = best > np.maximum(last[:, None], -1.5)
            for i in np.flatnonzero(good.any(1)):
                ids.append(own[i])
                rows.append((best[i][good[i]], own[at[i][good[i]]]))
            if len(ids) >= 4096:
                yield as_lists(ids, rows)
                ids, rows = [], []
        if ids:
            yield as_lists(ids, rows)

    return run


def merged(lists: DataFrame, better: DataFrame | None, k: int, wide: DataFrame | None = None, width: int = 0) -> DataFrame:
    """One list for each id, the k best or, of the ids in wide, the `width` best; fresh: how many of its entries came from `better` alone."""
    # the same neighbour may come with similarities that differ in the last bit
    flat = lists.select("id", F.inline("near")).withColumn("new", F.lit(0))
    if better is not None:
        flat = flat.unionByName(better.select("id", F.inline("near")).withColumn("new", F.lit(1)))
    flat = flat.repartition("id").groupBy("id", "j").agg(F.max("s").alias("s"), F.min("new").alias("new"))
    best = flat.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("s", "j", "new")), asc=False).alias("near"))
    places = F.lit(k)
    if wide is not None:
        best = best.join(wide.withColumn("wide", F.lit(True)), "id", "left")
        places = F.when(F.col("wide"), F.lit(width)).otherwise(F.lit(max(k, width // 2)))
    best = best.withColumn("near", F.slice("near", F.lit(1), places))
    fresh = F.aggregate("near", F.lit(0), lambda n, e: n + e["new"])
    return best.select("id", F.transform("near", lambda e: F.struct(e["s"].alias("s"), e["j"].alias("j"))).alias("near"), fresh.alias("fresh"))


def saturated(lists: DataFrame, threshold: float) -> DataFrame:
    """Ids whose list may lack links: even its last entry reaches the threshold."""
    return lists.filter(F.element_at("near", -1)["s"] >= threshold - 1e-4).select("id")


def descent_round(lists: DataFrame, vecs: DataFrame, k: int, dtype: str, part_size: int, parts: int, turn: int, wide: DataFrame | None = None, width: int = 0) -> DataFrame:
    """Better neighbours of all vectors, or of those in wide and their neighbours only, whose lists have `width` places."""
    out = lists.select("id", F.explode("near").alias("e")).select(F.col("id").alias("u"), F.col("e.j").alias("id"))
    both = out.unionByName(out.select(F.col("id").alias("u"), F.col("u").alias("id"))).unionByName(lists.select(F.col("id").alias("u"), "id")).distinct()
    places = F.lit(k)
    if wide is not None:
        both = both.join(wide.withColumnRenamed("id", "u"), "u", "left_semi")
        lists = lists.join(wide.withColumn("wide", F.lit(True)), "id", "left")
        places = F.when(F.col("wide"), F.lit(width)).otherwise(F.lit(max(k, width // 2)))
    count = both.groupBy("u").agg(F.ceil(F.count(F.lit(1)) / part_size).cast("int").alias("n_part"))
    last = lists.select("id", F.when(F.size("near") < places, F.lit(-1.5)).otherwise(F.element_at("near", -1)["s"]).cast("float").alias("last"))
    members = both.join(count, "u").withColumn("part", F.pmod(F.xxhash64("id", "u", F.lit(turn)), "n_part").cast("int")).join(vecs.join(last, "id"), "id")
    members = members.select("u", "part", "id", "vec", "last").repartition(parts, "u", "part").sortWithinPartitions("u", "part")
    return members.mapInArrow(local_join(max(k, width), dtype), LISTS)


def block_counts(threshold: float, dtype: str):
    """Links of the rows of a block pair, weighted by the copies of the other side."""

    def run(batches):
        ids, counts = [], []
        for (_, i, j), held in runs(batches, ("component", "i", "j"), ("id", "vec", "copies", "block")):
            left = [r for r in held if r[3] == i]
            right = left if i == j else [r for r in held if r[3] == j]
            if not left or not right:
                continue
            for size in {len(r[1]) for r in left}:
                a, b = ([r for r in side if len(r[1]) == size] for side in (left, right))
                if not b:
                    continue
                s = unit([r[1] for r in a], dtype) @ unit([r[1] for r in b], dtype).T >= threshold
                if i == j:
                    np.fill_diagonal(s, False)
                ids += [r[0] for r in a]
                counts += (s @ np.array([r[2] for r in b], np.int64)).tolist()
                if i != j:
                    ids += [r[0] for r in b]
                    counts += (s.T @ np.array([r[2] for r in a], np.int64)).tolist()
            if len(ids) >= 4096:
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(counts, pa.int64())], names=["id", "n"])
                ids, counts = [], []
        if ids:
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(counts, pa.int64())], names=["id", "n"])

    return run


def balls(dtype: str):
    """Centre and largest angle of the vectors of each block of a component."""

    def run(batches):
        for (component, size, block), held in runs(batches, ("component", "size", "block"), ("vec",)):
            x = unit([r[0] for r in held], dtype)
            centre = x.sum(0)
            length = np.sqrt(centre @ centre)
            centre = centre / length if length > 1e-6 else x[0]
            radius = float(np.arccos(np.clip(x @ centre, -1, 1)).max())
            yield pa.RecordBatch.from_arrays([pa.array([component], pa.int64()), pa.array([size], pa.int32()), pa.array([block], pa.int32()), pa.array([centre.tobytes()], pa.binary()), pa.array([radius])], names=["component", "size", "block", "centre", "radius"])

    return run


def near_balls(angle: float, step: int = 512):
    """Pairs of balls of different components that are near enough to hold a link."""

    def run(batches):
        for (_, i, j), held in runs(batches, ("size", "i", "j"), ("ball", "component", "centre", "radius", "tile")):
            left = [r for r in held if r[4] == i]
            right = left if i == j else [r for r in held if r[4] == j]
            if not left or not right:
                continue
            centre = np.frombuffer(b"".join(r[2] for r in right)).reshape(len(right), -1).T
            radius, own, ball = (np.array([r[c] for r in right]) for c in (3, 1, 0))
            for at in range(0, len(left), step):
                some = left[at : at + step]
                x = np.frombuffer(b"".join(r[2] for r in some)).reshape(len(some), -1)
                # the margin covers rounding of the angles
                reach = np.array([r[3] for r in some])[:, None] + radius + angle + 1e-6
                near = (np.arccos(np.clip(x @ centre, -1, 1)) <= reach) & (np.array([r[1] for r in some])[:, None] != own)
                if i == j:
                    near &= np.arange(at, at + len(some))[:, None] < np.arange(len(right))
                a, b = np.nonzero(near)
                yield pa.RecordBatch.from_arrays([pa.array(np.array([r[0] for r in some], np.int64)[a]), pa.array(ball[b].astype(np.int64))], names=["a", "b"])

    return run


def ball_links(threshold: float, dtype: str):
    """One link of each pair of balls that holds any; it is enough to merge their components."""

    def run(batches):
        for (a, _), held in runs(batches, ("a", "b"), ("ball", "id", "vec")):
            left, right = [r for r in held if r[0] == a], [r for r in held if r[0] != a]
            s = unit([r[2] for r in left], dtype) @ unit([r[2] for r in right], dtype).T
            at, to = divmod(int(s.argmax()), len(right))
            if s[at, to] >= threshold:
                yield pa.RecordBatch.from_arrays([pa.array([left[at][1]], pa.int64()), pa.array([right[to][1]], pa.int64())], names=["a", "b"])

    return run


def crossings(groups: DataFrame, lists: DataFrame, vecs: DataFrame, threshold: float, dtype: str, block: int, parts: int, scratch: Scratch, tile: int = 4096) -> DataFrame:
    """Links (a, b) between saturated vectors of different components, at least one for each two components that have any."""
    full = scratch.table("saturated", saturated(lists, threshold).join(groups, "id").join(vecs, "id").withColumn("size", F.length("vec")))
    count = full.groupBy("component", "size").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("n_block"))
    placed = full.join(count, ["component", "size"]).withColumn("block", F.pmod(F.xxhash64("id"), "n_block").cast("int"))
    dealt = placed.select("component", "size", "block", "vec").repartition(parts, "component", "size", "block").sortWithinPartitions("component", "size", "block")
    ball = dealt.mapInArrow(balls(dtype), "component long, size int, block int, centre binary, radius double")
    ball = scratch.table("balls", ball.withColumn("ball", F.monotonically_increasing_id()))
    n_tile = max(1, math.ceil(ball.count() / tile))
    tiled = ball.withColumn("tile", F.pmod(F.xxhash64("ball"), F.lit(n_tile)).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(n_tile - 1))))
    tiled = tiled.select("size", F.least("tile", "other").alias("i"), F.greatest("tile", "other").alias("j"), "ball", "component", "centre", "radius", "tile")
    tiled = tiled.repartition(parts, "size", "i", "j").sortWithinPartitions("size", "i", "j")
    close = scratch.table("near-balls", tiled.mapInArrow(near_balls(math.acos(threshold)), "a long, b long"))
    members = placed.join(ball.select("component", "size", "block", "ball"), ["component", "size", "block"]).select("ball", "id", "vec")
    sides = close.select("a", "b", F.explode(F.array("a", "b")).alias("ball")).join(members, "ball")
    sides = sides.select("a", "b", "ball", "id", "vec").repartition(parts, "a", "b").sortWithinPartitions("a", "b")
    return scratch.table("crossings", sides.mapInArrow(ball_links(threshold, dtype), "a long, b long"))


def settled(lists: DataFrame, vecs: DataFrame, n: int, k: int, settle: float, dtype: str, window: int, parts: int, scratch: Scratch, threshold: float, widest: int) -> DataFrame:
    """Descent until at most `settle` of the entries are new in a round; then saturated lists are doubled, up to `widest`, and descent goes on for them.

    Entries only improve, so it ends.
    """
    lists, turn = scratch.table("lists-0", merged(lists, None, k)), 0
    wide, width, places = None, 0, n * k
    while places:
        new = places
        while new > settle * places:
            better = descent_round(lists, vecs, k, dtype, window, parts, turn, wide, width)
            after = scratch.table(f"lists-{turn + 1}", merged(lists, better, k, wide, width))
            new = after.agg(F.coalesce(F.sum("fresh"), F.lit(0))).first()[0]
            scratch.drop(f"lists-{turn}")
            lists, turn = after, turn + 1
        width = 2 * max(k, width)
        if width > widest:
            break
        wide = scratch.table(f"wide-{width}", saturated(lists, threshold))
        places = wide.count() * width
    LOG.info("descent settled after %d rounds", turn)
    return lists


def linked(reps: DataFrame, lists: DataFrame, threshold: float, dtype: str, block: int, parts: int, scratch: Scratch) -> DataFrame:
    """id, component, n (links, weighted by copies) of the vectors that have links."""
    vecs = reps.select("id", "vec")
    edges = lists.select("id", F.explode("near").alias("e")).filter(F.col("e.s") >= threshold - 1e-4)
    edges = edges.select(F.col("id").alias("a"), F.col("e.j").alias("b"))
    # edges just below the threshold in single precision are checked before they join components
    checked = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct()
    pairs = checked.join(vecs.select(F.col("id").alias("a"), F.col("vec").alias("va")), "a").join(vecs.select(F.col("id").alias("b"), F.col("vec").alias("vb")), "b")
    exact = scratch.table("edges", pairs.mapInArrow(exact_pairs(threshold, dtype), "a long, b long"))
    groups = scratch.table("groups", components(exact, scratch))
    across = crossings(groups, lists, vecs, threshold, dtype, block, parts, scratch)
    if not across.isEmpty():
        groups = scratch.table("merged-groups", components(exact.unionByName(across), scratch, "merged"))
    sizes = groups.groupBy("component").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("n_block"))
    placed = groups.join(sizes, "component").withColumn("block", F.pmod(F.xxhash64("id"), "n_block").cast("int")).join(reps, "id")
    pairs = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("n_block") - 1)))
    pairs = pairs.select("component", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "id", "vec", "copies", "block")
    pairs = pairs.repartition(parts, "component", "i", "j").sortWithinPartitions("component", "i", "j")
    links = pairs.mapInArrow(block_counts(threshold, dtype), "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    return scratch.table("found", groups.join(links, "id", "left").select("id", "component", F.coalesce("n", F.lit(0)).alias("n")))


def audit_recall(reps: DataFrame, found: DataFrame, threshold: float, dtype: str, sample: int, seed: int) -> float:
    """Share of the true links of at most `sample` random vectors that were found, by brute force in blocks over all vectors."""
    queries = reps.select("id", "vec").orderBy(F.xxhash64("id", F.lit(seed))).limit(sample).collect()
    ids = [q["id"] for q in queries]
    own = {size: [q for q in range(len(queries)) if len(queries[q]["vec"]) == size] for size in {len(q["vec"]) for q in queries}}
    base = {size: unit([bytes(queries[q]["vec"]) for q in at], dtype) for size, at in own.items()}

    def count(batches, step=1024):
        total = np.zeros(len(ids), np.int64)
        for batch in batches:
            vecs, copies = batch.column("vec").to_pylist(), batch.column("copies").to_numpy()
            for size in {len(v) for v in vecs} & set(own):
                rows = [r for r, v in enumerate(vecs) if len(v) == size]
                for at in range(0, len(rows), step):
                    some = rows[at : at + step]
                    # links at the threshold itself may differ in the last bit from one product to the other
                    total[own[size]] += copies[some] @ (unit([vecs[r] for r in some], dtype) @ base[size].T >= threshold + 1e-9)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(total)], names=["id", "n"])

    counts = reps.select("id", "vec", "copies").mapInArrow(count, "id long, n long").groupBy("id").agg(F.sum("n").alias("n"))
    # a vector is no link of its own
    truth = counts.join(reps.select("id", "copies"), "id").select("id", (F.col("n") - F.col("copies")).alias("all"))
    row = truth.join(found, "id", "left").agg(F.sum(F.least("all", F.coalesce("n", F.lit(0)))).alias("found"), F.sum("all").alias("all")).first()
    return row["found"] / row["all"] if row["all"] else 1.0


def near_duplicates(vectors: DataFrame, threshold: float = 0.95, k: int = 8, meet: float = 0.99, settle: float = 0.01, window: int = 64, block: int = 256, seed: int = 11, sample: int = 200, trees: int | None = None, widest: int | None = None) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row. `trees` of the start follow from the number of vectors unless given; lists grow from k to `widest` (2 k)."""
    spark = vectors.sparkSession
    scratch = Scratch(spark, "neardup")
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 8)
    kind = vectors.schema["embedding"].dataType
    dtype = "<f4" if isinstance(kind.elementType, T.FloatType) else "<f8"
    rows = vectors.select(id_in("vec_id").alias("vec_id"), "embedding" if dtype == "<f4" else F.col("embedding").cast("array<double>").alias("embedding"))
    rows = scratch.table("rows", rows.mapInArrow(encoder(dtype), "vec_id long, vec binary"))
    reps = rows.filter("vec IS NOT NULL").groupBy("vec").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("copies"))
    reps = scratch.table("reps", reps.withColumn("id", F.monotonically_increasing_id()))
    n = reps.count()
    angle = math.acos(threshold) / math.pi
    depth = max(1.0, math.log2(max(n, 2) / window))
    trees = trees or (max(2, math.ceil(math.log(1 - meet) / math.log(1 - (1 - angle) ** depth))) if n > window else 1)
    lists, attempt, recall = None, 0, 0.0
    while recall < meet:
        step = Scratch(spark, f"neardup-{attempt}")
        codes = reps.select("id", "vec").mapInArrow(projector(trees, 62, dtype, seed + 1_000_003 * attempt), "tree int, size int, code long, id long, vec binary")
        # windows end at the borders of partitions: few rows take few of them
        spread = max(1, min(parts, n * trees // (32 * window)))
        codes = codes.repartitionByRange(spread, "tree", "size", "code", "id").sortWithinPartitions("tree", "size", "code", "id")
        start = codes.mapInArrow(around(k, dtype, window), LISTS)
        start = start if lists is None else start.unionByName(lists.select("id", "near"))
        lists = settled(start, reps.select("id", "vec"), n, k, settle, dtype, window, parts, step, threshold, widest or 2 * k)
        found = linked(reps, lists, threshold, dtype, block, parts, step)
        recall = audit_recall(reps, found.select("id", "n"), threshold, dtype, sample, seed + attempt)
        LOG.info("%d trees added, recall %.4f in a sample of %d", trees, recall, min(sample, n))
        trees, attempt = 2 * trees, attempt + 1
    named = reps.join(found, "id", "left").select("vec", "rep", "copies", "n", F.coalesce("component", "id").alias("component"))
    least = named.groupBy("component").agg(F.min("rep").alias("component_id"))
    found = named.join(least, "component").select("vec", "component_id", (F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    out = rows.join(found, "vec", "left")
    component = F.coalesce("component_id", "vec_id")
    out = out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), (F.col("vec_id") == component).alias("kept"))
    return out.select(id_out("vec_id"), "n_links", id_out("component_id"), "kept")


def exact_pairs(threshold: float, dtype: str):
    def run(batches):
        for batch in batches:
            a, b = (batch.column(c).to_pylist() for c in ("va", "vb"))
            same = [k for k in range(len(a)) if len(a[k]) == len(b[k])]
            keep = []
            for size in {len(a[k]) for k in same}:
                own = [k for k in same if len(a[k]) == size]
                s = (unit([a[k] for k in own], dtype) * unit([b[k] for k in own], dtype)).sum(1)
                keep += [k for k, v in zip(own, s) if v >= threshold]
            yield batch.select(["a", "b"]).take(pa.array(keep, pa.int64()))

    return run


def op2_neighbour_descent(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "embeddings"))
