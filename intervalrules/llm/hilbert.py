"""Operator 1: sharding along a Hilbert curve over quantised metadata, with DataFrame functions only.

Each metadata dimension is turned into an order-preserving number (strings by their first seven bytes), quantised by
approximate quantiles over all rows into 2^bits - 1 buckets (bucket 0: null), and the bucket vector is mapped to its place on
the curve. Rows are range-sorted by (curve, key), so that a run of the order is a compact box in every dimension and the
min/max statistics of its files prune scans on any of them. Runs are cut by the law:

* ``rows``: rank * shards div rows, counts at most one apart;
* ``bytes``: by the running sum of sizes, each shard within one row of the mean.

Only ids, sizes and curve places are shuffled, never texts. What reaches the driver or is broadcast: the quantile borders
(fixed number) and one row for each partition of the sort.

Edge cases: nulls in a dimension share bucket 0, a null text has size 1 and a null checksum, repeated rows get their own slots,
an empty table gives no rows, columns that are not named are not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Scratch, table

LOCAL_BITS = 33  # monotonically_increasing_id keeps the row number of a partition in so many low bits


def ordinal(df: DataFrame, name: str) -> Column:
    """A LONG that keeps the order of the column."""
    kind = df.schema[name].dataType
    if isinstance(kind, T.StringType):
        return F.expr(f"CAST(conv(rpad(hex(substring(CAST(`{name}` AS BINARY), 1, 7)), 14, '0'), 16, 10) AS BIGINT)")
    if isinstance(kind, (T.DateType, T.TimestampType, T.TimestampNTZType)):
        return F.unix_micros(F.col(f"`{name}`").cast("timestamp"))
    return F.col(f"`{name}`").cast("bigint")


def borders(df: DataFrame, dims: list[str], bits: int, accuracy: int = 10_000) -> dict[str, list[int]]:
    """Quantile borders of each dimension over all rows."""
    steps = 2**bits - 1
    at = F.array(*[F.lit(k / steps) for k in range(1, steps)])
    row = df.select(*[F.percentile_approx(ordinal(df, d), at, accuracy).alias(d) for d in dims]).first()
    return {d: sorted(set(row[d] or [])) for d in dims}


def bucket(value: Column, cuts: list[int]) -> Column:
    above = F.lit(1)
    for cut in cuts:
        above = above + (value > F.lit(cut)).cast("int")
    return F.when(value.isNull(), F.lit(0)).otherwise(above)


def curve_index(df: DataFrame, coords: list[str], bits: int, out: str) -> DataFrame:
    """Adds the Hilbert index of integer coordinates below 2^bits; coords are consumed.

    One projection for each exchange or inversion step keeps the expressions small.
    """
    first, last = coords[0], coords[-1]
    for level in range(bits - 1, 0, -1):
        q, p = F.lit(1 << level), F.lit((1 << level) - 1)
        for name in coords:
            x, head = F.col(name), F.col(first)
            inside = x.bitwiseAND(q) != 0
            if name == first:
                df = df.withColumn(first, F.when(inside, head.bitwiseXOR(p)).otherwise(head))
            else:
                swap = head.bitwiseXOR(x).bitwiseAND(p)
                df = df.withColumns({first: F.when(inside, head.bitwiseXOR(p)).otherwise(head.bitwiseXOR(swap)), name: F.when(inside, x).otherwise(x.bitwiseXOR(swap))})
    for before, name in zip(coords, coords[1:]):
        df = df.withColumn(name, F.col(name).bitwiseXOR(F.col(before)))
    flips = F.lit(0)
    for level in range(bits - 1, 0, -1):
        flips = flips.bitwiseXOR(F.when(F.col(last).bitwiseAND(F.lit(1 << level)) != 0, F.lit((1 << level) - 1)).otherwise(F.lit(0)))
    df = df.withColumn("__flip", flips)
    df = df.withColumns({name: F.col(name).bitwiseXOR(F.col("__flip")) for name in coords})
    index = F.lit(0).cast("bigint")
    for level in range(bits - 1, -1, -1):
        for name in coords:
            index = F.shiftleft(index, 1).bitwiseOR(F.shiftright(F.col(name), level).bitwiseAND(F.lit(1)).cast("bigint"))
    return df.withColumn(out, index).drop("__flip", *coords)


def place(df: DataFrame, key: str, dims: list[str], bits: int, size: Column, extra: dict[str, Column]) -> DataFrame:
    """key, curve, size and extra columns of every row."""
    cuts = borders(df, dims, bits)
    coords = [f"__x{i}" for i in range(len(dims))]
    slim = df.select(F.col(key).alias("__key"), size.alias("__size"), *[c.alias(n) for n, c in extra.items()], *[bucket(ordinal(df, d), cuts[d]).alias(x) for d, x in zip(dims, coords)])
    return curve_index(slim, coords, bits, "curve")


def hilbert_shards(df: DataFrame, key: str, dims: list[str], size: Column, shards: int = 8, law: str = "rows", bits: int = 5, extra: dict[str, Column] | None = None) -> DataFrame:
    """Columns: key, size, the extra ones, curve, shard, slot."""
    if law not in ("rows", "bytes"):
        raise ValueError(law)
    extra = extra or {}
    placed = place(df, key, dims, bits, size, extra)
    parts = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    order = ["curve", "__key", *extra]
    run = placed.repartitionByRange(parts, *order).sortWithinPartitions(*order, "__size").withColumn("__at", F.monotonically_increasing_id())
    run = Scratch(df.sparkSession, "hilbert").table("run", run)
    run = run.withColumns({"__part": F.shiftright("__at", LOCAL_BITS), "__row": F.col("__at").bitwiseAND(F.lit((1 << LOCAL_BITS) - 1))})
    tiny = Window.orderBy("__part")
    parts_of = run.groupBy("__part").agg(F.count(F.lit(1)).alias("__n"), F.sum("__size").alias("__b"))
    parts_of = parts_of.select("__part", *[(F.sum(c).over(tiny) - F.col(c)).alias(f"{c}_before") for c in ("__n", "__b")], *[F.sum(c).over(Window.partitionBy()).alias(f"{c}_all") for c in ("__n", "__b")])
    run = run.join(F.broadcast(parts_of), "__part").withColumn("__rank", F.col("__n_before") + F.col("__row"))
    if law == "rows":
        run = run.withColumn("shard", F.expr(f"CAST(__rank * {shards} DIV __n_all AS INT)"))
        slot = F.expr(f"__rank - (shard * __n_all + {shards - 1}) DIV {shards}")
    else:
        inside = F.sum("__size").over(Window.partitionBy("__part").orderBy("__row")) - F.col("__size")
        run = run.withColumn("__in", inside).withColumn("shard", F.expr(f"CAST(least({shards - 1}, (__b_before + __in) * {shards} DIV __b_all) AS INT)"))
        run = run.join(F.broadcast(run.groupBy("shard").agg(F.min("__rank").alias("__first"))), "shard")
        slot = F.col("__rank") - F.col("__first")
    return run.select(F.col("__key").alias(key), F.col("__size").alias("size"), *extra, "curve", "shard", slot.cast("bigint").alias("slot"))


def op1_hilbert_shards(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("bigint") + 1
    out = hilbert_shards(docs, "doc_id", ["source", "lang", "n_chars"], size, shards=8, law="rows", extra={"text_crc32": F.crc32("text")})
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "curve")
