"""Rules as text lines, and the size of such files by relation layout."""

from __future__ import annotations

from collections.abc import Iterable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import relations as R


def key_text() -> Column:
    """'A,C>D|0,0' from x, y, rel."""
    return F.concat(F.array_join("x", ","), F.lit(">"), F.array_join("y", ","), F.lit("|"), F.array_join(F.transform("rel", lambda v: v.cast("string")), ","))


def relation_text(layout: str) -> Column:
    if layout == "base7":
        return F.array_join(F.transform("rel", lambda v: v.cast("string")), ",")
    if layout == "matrix":
        return F.array_join(F.flatten(R.triangle(F.col("rel"), F.size("x") + F.size("y"))), ",")
    raise ValueError(layout)


def line(layout: str = "base7") -> Column:
    conf = F.format_string("%.4f", F.col("n_rule") / F.col("n_ante"))
    parts = [F.array_join("x", ","), F.lit("==>"), F.array_join("y", ","), F.concat(F.lit("#util: "), F.col("utility").cast("string")), F.concat(F.lit("#conf: "), conf), relation_text(layout)]
    return F.concat_ws(" ", *parts)


def lines(rules: DataFrame, layout: str = "base7") -> DataFrame:
    return rules.select(line(layout).alias("value"))


def write_rules(rules: DataFrame, path: str, layout: str = "base7") -> None:
    lines(rules, layout).write.mode("overwrite").text(path)


def output_bytes(rules: DataFrame, layout: str) -> int:
    return output_sizes(rules, (layout,))[f"bytes_{layout}"]


def output_sizes(rules: DataFrame, layouts: Iterable[str]) -> dict[str, int]:
    """bytes_<layout> of the written rules, of several layouts in one pass."""
    size = lambda layout: F.coalesce(F.sum(F.octet_length(line(layout)) + 1), F.lit(0)).alias(f"bytes_{layout}")
    return rules.agg(*[size(layout) for layout in layouts]).first().asDict()
