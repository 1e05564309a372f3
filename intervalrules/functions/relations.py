"""Relations of two intervals as digits, and base-7 numbers of digits.

An ordered pair (a before b in the order start, finish, symbol) has one of seven relations, its digit:
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Digit of each relation.
NAMES = ("before", "meets", "overlaps", "contains", "finished-by", "starts", "equals")
LETTERS = "bmocfse"
BASE = 7
LONG_DIGITS = 22  # 7^22 < 2^63


def digit_sql(a_st: str, a_ft: str, b_st: str, b_ft: str) -> str:
    """The digit as an expression that Spark and ANSI SQL share."""
    return f"CASE WHEN {a_ft} < {b_st} THEN 0 WHEN {a_ft} = {b_st} THEN 1 WHEN {a_st} = {b_st} THEN CASE WHEN {a_ft} = {b_ft} THEN 6 ELSE 5 END WHEN {a_ft} < {b_ft} THEN 2 WHEN {a_ft} > {b_ft} THEN 3 ELSE 4 END"


def digit(a_st: Column, a_ft: Column, b_st: Column, b_ft: Column) -> Column:
    same = F.when(a_ft == b_ft, F.lit(6)).otherwise(F.lit(5))
    return F.when(a_ft < b_st, F.lit(0)).when(a_ft == b_st, F.lit(1)).when(a_st == b_st, same).when(a_ft < b_ft, F.lit(2)).when(a_ft > b_ft, F.lit(3)).otherwise(F.lit(4))


def allen13(a_st: Column, a_ft: Column, b_st: Column, b_ft: Column) -> Column:
    """Name of the relation of an unordered pair; the six inverses end with '-i'."""
    turned = (b_st < a_st) | ((b_st == a_st) & (b_ft < a_ft))
    return F.when(turned, F.concat(name(digit(b_st, b_ft, a_st, a_ft)), F.lit("-i"))).otherwise(name(digit(a_st, a_ft, b_st, b_ft)))


def invert(allen: Column) -> Column:
    """The relation of the swapped pair."""
    return F.when(allen == NAMES[6], allen).when(allen.endswith("-i"), F.regexp_replace(allen, "-i$", "")).otherwise(F.concat(allen, F.lit("-i")))


def name(d: Column) -> Column:
    return F.element_at(F.array(*map(F.lit, NAMES)), (d + 1).cast("int"))


def letter(d: Column) -> Column:
    return F.substring(F.lit(LETTERS), 1, 7).substr((d + 1).cast("int"), F.lit(1))


def _predicate(d: int):
    def test(a_st: Column, a_ft: Column, b_st: Column, b_ft: Column) -> Column:
        return digit(a_st, a_ft, b_st, b_ft) == d

    test.__name__ = NAMES[d].replace("-", "_")
    return test


before, meets, overlaps, contains, finished_by, starts, equals = map(_predicate, range(7))


def gap(a_ft: Column, b_st: Column) -> Column:
    """Time between two intervals, 0 if they touch or overlap."""
    return F.greatest(b_st - a_ft, F.lit(0))


def shared_length(a_st: Column, a_ft: Column, b_st: Column, b_ft: Column) -> Column:
    return F.greatest(F.least(a_ft, b_ft) - F.greatest(a_st, b_st), F.lit(0))


def number(digits: Column) -> Column:
    """Array of digits, highest first, to a LONG (22 digits at most; limbs() has no limit)."""
    return F.aggregate(digits, F.lit(0).cast("bigint"), lambda acc, d: acc * BASE + d)


def power(j: Column | int) -> Column:
    table = F.array(*[F.lit(BASE**k).cast("bigint") for k in range(LONG_DIGITS + 1)])
    return F.element_at(table, (F.lit(j) if isinstance(j, int) else j).cast("int") + 1)


def digits(num: Column, k: Column) -> Column:
    """The k digits of a LONG, highest first."""
    at = F.when(k > 0, F.sequence(k.cast("int") - 1, F.lit(0))).otherwise(F.array().cast("array<int>"))
    return F.transform(at, lambda i: (F.call_function("div", num, power(i)) % BASE).cast("int"))


# A number of any length is an array of LONGs, its limbs: 22 digits each, the highest limb first and maybe shorter. Up to 22 digits it is one limb.


def limbs(digits_: Column) -> Column:
    n = F.size(digits_)
    places = F.when(n > 0, F.sequence(F.ceil(n / LONG_DIGITS).cast("int") - 1, F.lit(0))).otherwise(F.array().cast("array<int>"))
    head = lambda i: F.greatest(F.lit(1), n - (i + 1) * LONG_DIGITS + 1)
    return F.transform(places, lambda i: number(F.slice(digits_, head(i), n - i * LONG_DIGITS - head(i) + 1)))


def limb_digits(limbs_: Column, k: Column) -> Column:
    """The k digits of a number in limbs."""
    return F.flatten(F.transform(limbs_, lambda v, i: digits(v, F.when(i == 0, k - (F.size(limbs_) - 1) * LONG_DIGITS).otherwise(LONG_DIGITS))))


def limbs_before(n: Column) -> Column:
    """Limbs of the numbers of the first n intervals together (the first interval has no number)."""
    full, rest = F.floor((n - 1) / LONG_DIGITS), (n - 1) % LONG_DIGITS
    return F.greatest(F.lit(0), LONG_DIGITS // 2 * full * (full + 1) + rest * (full + 1)).cast("int")


def limbs_at(rel: Column, j: Column) -> Column:
    """The limbs of interval j >= 2 of a relation list."""
    return F.slice(rel, limbs_before(j - 1) + 1, F.ceil((j - 1) / LONG_DIGITS).cast("int"))


def triangle(rel: Column, n: Column) -> Column:
    """The digits of each number of a relation list of n intervals."""
    at = F.when(n > 1, F.sequence(F.lit(2), n.cast("int"))).otherwise(F.array().cast("array<int>"))
    return F.transform(at, lambda j: limb_digits(limbs_at(rel, j), j - 1))


def tail_digits(digits_: Column) -> Column:
    """Digits left after leading zeros."""
    first = F.array_position(F.transform(digits_, lambda d: (d != 0).cast("int")), 1)
    return F.when(first > 0, F.size(digits_) - first + 1).otherwise(0).cast("int")


def n_digits(num: Column, most: int) -> Column:
    """As tail_digits, of a LONG that has at most `most` digits."""
    out = F.lit(0)
    for k in range(min(most, LONG_DIGITS)):
        out = out + (num >= F.lit(BASE**k)).cast("int")
    return out


def letters(rel: Column, n: Column) -> Column:
    """'b;bo' for the numbers of the second, third ... of n intervals."""
    return F.array_join(F.transform(triangle(rel, n), lambda own: F.array_join(F.transform(own, letter), "")), ";")


def subscript(rel: Column, n: Column) -> Column:
    """Base-7 text of each number with its subscript, e.g. '0₇,02₇'."""
    return F.array_join(F.transform(triangle(rel, n), lambda own: F.concat(F.array_join(own, ""), F.lit("₇"))), ",")


def digits_against(earlier: Column, st: Column, ft: Column) -> Column:
    """Digits of all earlier intervals (array of st, ft) towards a later one."""
    return F.transform(earlier, lambda q: digit(q["st"], q["ft"], st, ft))


def append_number(earlier: Column, previous: Column, st: Column, ft: Column, most: int, zero_carry: bool = True) -> Column:
    """Number of a new last interval. With zero carry, intervals that lie before the previous one are not compared again.

    earlier: array of (st, ft); previous: number of its last element; most: upper bound of the digits (22; limbs(digits_against()) has none).
    """
    if zero_carry:
        tail = n_digits(previous, most)
        earlier = F.slice(earlier, F.size(earlier) - tail, tail + 1)
    return F.aggregate(earlier, F.lit(0).cast("bigint"), lambda acc, q: acc * BASE + digit(q["st"], q["ft"], st, ft))


def insert_digit(num: Column, j: Column | int, d: Column) -> Column:
    """Puts digit d at place j from the right; higher digits move up."""
    p = power(j)
    low = num % p
    return ((num - low) * BASE + d * p + low).cast("bigint")


def matrix(intervals: Column) -> Column:
    """Full triangle of digits, every pair compared: one array for each interval but the first."""
    at = F.when(F.size(intervals) > 1, F.sequence(F.lit(2), F.size(intervals))).otherwise(F.array().cast("array<int>"))
    return F.transform(at, lambda j: F.transform(F.slice(intervals, 1, j - 1), lambda q: digit(q["st"], q["ft"], F.element_at(intervals, j)["st"], F.element_at(intervals, j)["ft"])))


def matrix_numbers(triangle_: Column) -> Column:
    """The relation list of a triangle, of any size."""
    return F.flatten(F.transform(triangle_, limbs))


def sparse(triangle: Column) -> Column:
    """The entries other than before, as (i, j, d) with places from 1."""
    rows = F.transform(triangle, lambda row, j: F.filter(F.transform(row, lambda d, i: F.struct((i + 1).alias("i"), (j + 2).alias("j"), d.alias("d"))), lambda e: e["d"] != 0))
    return F.flatten(rows)


def split_area(previous: Column, k: Column) -> Column:
    """(earlier, checking): places of intervals before the previous one, and those to be compared with a new one.

    previous: limbs of the previous interval's number; k: its place.
    """
    lead = k - 1 - tail_digits(limb_digits(previous, k - 1))
    at = F.sequence(F.lit(1), k.cast("int"))
    return F.struct(F.filter(at, lambda i: i <= lead).alias("earlier"), F.filter(at, lambda i: i > lead).alias("checking"))


def pack8(digits_: Column) -> Column:
    """Three bits for each digit, 21 digits at most."""
    return F.aggregate(digits_, F.lit(0).cast("bigint"), lambda acc, d: F.shiftleft(acc, 3).bitwiseOR(d.cast("bigint")))
