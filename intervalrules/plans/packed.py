"""The level search over whole timelines in column arrays: no occurrence is stored or shuffled.

Each pass reads the intervals of its partition in the order of `timelines.items`, makes the occurrences of the live rules of all sizes
again from their one-to-one rules, and returns sums of its partition: of class bounds, or of rules and antecedents one interval longer. What passes need of
a level are numbers for its live rules and kept classes, which are broadcast; a search whose level has more than BROADCAST_ROWS of
them goes on in `search.Search`, whose levels are tables.

A grown rule is named by (parent's number, side, symbol, own number, digit against the consequent), which fits one LONG.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from ..functions import relations as R
from . import measures, search
from .scratch import BROADCAST_ROWS

ITEMS = ("sid", "pos", "code", "st", "ft", "u", "tail", "head")
SUMS = ("utility", "n_rule", "n_occ", "open_bound", "right_bound")
NAMES = ("rid", "side", "code", "num", "dy")
PART = "kind int, " + ", ".join(f"{c} long" for c in (*NAMES, *SUMS))
RULE, ANTE, CLASS = 0, 1, 2
LEFT, RIGHT = 0, 1
CHUNK = 40_000  # intervals, and
GROWN = 300_000  # extensions that are made at a time
HELD = 2_000_000  # partial sums of a partition


class TooMany(Exception):
    """More live rules or classes than may be broadcast."""


def fits(codes: int, cap: int | None) -> bool:
    """Whether a timeline of a chunk and the name of any rule of `cap` intervals fit one LONG together."""
    return cap is not None and CHUNK * max(BROADCAST_ROWS, codes + 1) * 2 * (codes + 1) * 7**cap < 1 << 62


class Lookup:
    """Numbers of the keys in a sorted array, -1 for others."""

    def __init__(self, keys: np.ndarray, values: np.ndarray | None = None):
        order = np.argsort(keys, kind="stable")
        self.keys = keys[order]
        self.values = np.arange(len(keys))[order] if values is None else values[order]

    def __call__(self, wanted: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.full(len(wanted), -1)
        at = np.minimum(np.searchsorted(self.keys, wanted), len(self.keys) - 1)
        return np.where(self.keys[at] == wanted, self.values[at], -1)


@dataclass
class Stage:
    """What passes need of one size: numbers of live rules, of antecedents, and kept classes."""

    live: Lookup
    grows: tuple[np.ndarray, np.ndarray]  # of each number: to the left, to the right
    antes: Lookup  # of the antecedents of rules that grow left
    classes: Lookup | None = None
    ante_classes: Lookup | None = None


@dataclass
class Occ:
    """Occurrences of one shape: rule, timeline, places of the nx antecedent intervals and then of the consequent's, utility, and
    the digits of the last antecedent and of the last consequent interval against those before."""

    rid: np.ndarray
    line: np.ndarray
    places: list[np.ndarray]
    nx: int
    u: np.ndarray
    dx: list[np.ndarray]
    dy: list[np.ndarray]

    def at(self, rows) -> "Occ":
        return Occ(self.rid[rows], self.line[rows], [p[rows] for p in self.places], self.nx, self.u[rows], [d[rows] for d in self.dx], [d[rows] for d in self.dy])


def joined(numbers: list[np.ndarray]) -> np.ndarray:
    out = numbers[0].astype(np.int64)
    for d in numbers[1:]:
        out = out * 7 + d
    return out


def starts_of(sorted_keys: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.concatenate(([True], sorted_keys[1:] != sorted_keys[:-1])))


def summed(keys: np.ndarray, values: list[np.ndarray]) -> tuple[np.ndarray, list[np.ndarray]]:
    if not len(keys):
        return keys, values
    order = np.argsort(keys)
    own = keys[order]
    at = starts_of(own)
    return own[at], [np.add.reduceat(v[order], at) for v in values]


def per_line(line: np.ndarray, keys: np.ndarray, width: int, values: list[np.ndarray]) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """Of each timeline and key: the key, the highest values, the number of rows."""
    both = line * width + keys
    order = np.argsort(both)
    own = both[order]
    at = starts_of(own)
    return own[at] % width, [np.maximum.reduceat(v[order], at) for v in values], np.diff(np.append(at, len(own)))


class Chunk:
    """Whole timelines of a partition."""

    def __init__(self, cols: dict[str, np.ndarray], opt, codes: int, allowed: np.ndarray | None):
        self.opt, self.codes, self.allowed = opt, codes + 1, allowed
        first = np.concatenate(([True], cols["sid"][1:] != cols["sid"][:-1]))
        begin = np.flatnonzero(first)
        self.begin = begin  # of each timeline
        self.line = (np.cumsum(first) - 1).astype(np.int32)
        self.end = np.append(begin[1:], len(first)).astype(np.int32)[self.line]
        self.code, self.st, self.ft, self.u, self.tail, self.head = (cols[c] for c in ("code", "st", "ft", "u", "tail", "head"))
        if (cols["pos"] != np.arange(len(first)) - begin[self.line] + 1).any():
            raise RuntimeError("intervals are not in the order of timelines.items")
        new = first | np.append(True, self.st[1:] != self.st[:-1])
        self.tie = np.flatnonzero(new).astype(np.int32)[np.cumsum(new) - 1]  # place of the first interval with the same start

    def digit(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        ast, aft, bst, bft = self.st[a], self.ft[a], self.st[b], self.ft[b]
        over = np.where(aft < bft, 2, np.where(aft > bft, 3, 4))
        same = np.where(aft == bft, 6, 5)
        return np.where(aft < bst, 0, np.where(aft == bst, 1, np.where(ast == bst, same, over))).astype(np.int8)

    def digits(self, places: list[np.ndarray], before: list[np.ndarray], e: np.ndarray) -> list[np.ndarray]:
        """Digits of e against places; before: digits of the last place. An interval before the last place is before e, which starts no earlier."""
        out = []
        for k, p in enumerate(places):
            if k < len(before) and self.opt.zero_carry:
                own, check = np.zeros(len(e), np.int8), np.flatnonzero(before[k])
                own[check] = self.digit(p[check], e[check])
                out.append(own)
            else:
                out.append(self.digit(p, e))
        return out

    def expanded(self, low: np.ndarray, high: np.ndarray, groups) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(row, place) for all places from low to high of each row, a part of the rows at a time; groups(): numbers whose rows stay together."""
        counts = np.maximum(high - low, 0)
        rows = np.flatnonzero(counts)
        if not len(rows):
            return
        if counts.sum() <= GROWN:
            cuts = [0, len(rows)]
        else:
            own = groups()[rows]
            order = np.argsort(own)
            rows, own = rows[order], own[order]
            at, total = starts_of(own), np.cumsum(counts[rows])
            part = (total[np.append(at[1:], len(rows)) - 1] - 1) // GROWN
            cuts = [*at[starts_of(part)].tolist(), len(rows)]
        for a, b in zip(cuts, cuts[1:]):
            own = rows[a:b]
            n = counts[own]
            row = np.repeat(own, n)
            yield row, low[row] + np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)

    def _permitted(self, row: np.ndarray, e: np.ndarray, others: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        ok = np.ones(len(e), bool) if self.allowed is None else self.allowed[self.code[e]]
        if self.opt.disjoint == "symbol":
            for p in others:
                ok &= self.code[e] != self.code[p[row]]
        return (row, e) if ok.all() else (row[ok], e[ok])

    def roots_of(self, first: int, second: int) -> Iterator[tuple[Occ, np.ndarray]]:
        """Rules of one interval on each side with these symbols, and their names."""
        b = np.flatnonzero(self.code == second)
        line = self.line[b].astype(np.int64)
        for row, a in self.expanded(self.begin[line], self.tie[b], lambda: line):
            ok = self.code[a] == first
            a, own = a[ok], b[row[ok]]
            if len(a):
                d = self.digit(a, own)
                yield Occ(self.code[a], line[row[ok]], [a, own], 1, self.u[a] + self.u[own], [], [d]), self.name(self.code[a], RIGHT, self.code[own], d.astype(np.int64), 0, 2)

    def roots(self) -> Iterator[tuple[Occ, np.ndarray]]:
        """Rules of one interval on each side and their names."""
        at = np.arange(len(self.code))
        for a, b in self.expanded(at + 1, self.end, lambda: self.line.astype(np.int64) * self.codes + self.code):
            ok = self.st[b] > self.st[a]
            if self.opt.disjoint == "symbol":
                ok &= self.code[a] != self.code[b]
            a, b = a[ok], b[ok]
            d = self.digit(a, b)
            if len(a):
                yield Occ(self.code[a], self.line[a].astype(np.int64), [a, b], 1, self.u[a] + self.u[b], [], [d]), self.name(self.code[a], RIGHT, self.code[b], d.astype(np.int64), 0, 2)

    def name(self, rid, side, code, num, dy, size: int):
        return ((rid * 2 + side) * self.codes + code) * 7**size + num * 7 + dy

    def extended(self, occ: Occ, side: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """(row, e, digit): places of intervals that may join a side, with the relation of the side's last interval."""
        groups = lambda: occ.line * (occ.rid.max() + 1) + occ.rid
        last = occ.places[occ.nx - 1] if side == LEFT else occ.places[-1]
        high = self.tie[occ.places[occ.nx]] if side == LEFT else self.end[last]
        others = occ.places[occ.nx :] if side == LEFT else occ.places[: occ.nx]
        for row, e in self.expanded(last + 1, high, groups):
            row, e = self._permitted(row, e, others)
            if len(row):
                yield row, e, self.digit(last[row], e)

    def class_names(self, rid, side, code, digit):
        own = (rid * 2 + side) * self.codes + code
        return own * 7 + digit if self.opt.class_budget else own

    def class_bounds(self, occ: Occ, side: int) -> Iterator[tuple[np.ndarray, list[np.ndarray]]]:
        for row, e, digit in self.extended(occ, side):
            y = occ.places[occ.nx][row]
            bound = occ.u[row] + self.u[e]
            bound += np.maximum(self.tail[e] - self.head[y], 0) + self.tail[occ.places[-1][row]] if side == LEFT else self.tail[e]
            names = self.class_names(occ.rid[row], side, self.code[e], digit)
            keys, (best,), _ = per_line(occ.line[row], names, int(names.max()) + 1, [bound])
            yield summed(keys, [best])

    def grown(self, occ: Occ, side: int, classes: Lookup) -> Iterator[tuple[Occ, np.ndarray]]:
        """Occurrences one interval longer, in kept classes, and their names; rid is the parent's."""
        for row, e, digit in self.extended(occ, side):
            kept = np.flatnonzero(classes(self.class_names(occ.rid[row], side, self.code[e], digit)) >= 0)
            if not len(kept):
                continue
            e, old = e[kept], occ.at(row[kept])
            x, y = old.places[: old.nx], old.places[old.nx :]
            nx = old.nx + (side == LEFT)
            places = [*x, e, *y] if side == LEFT else [*x, *y, e]
            if self.opt.layout == "matrix":  # all pairs anew
                pairs = [[self.digit(places[j], places[k]) for j in range(k)] for k in range(len(places))]
                dx, dy = pairs[nx - 1], pairs[-1]
            elif side == LEFT:
                dx, dy = self.digits(x, old.dx, e), [*old.dy, self.digit(e, y[0])]
            else:
                dx, dy = old.dx, self.digits(old.places, old.dy, e)
            num = joined(dx if side == LEFT else dy)
            new = Occ(old.rid, old.line, places, nx, old.u + self.u[e], dx, dy)
            yield new, self.name(old.rid, side, self.code[e], num, dy[-1].astype(np.int64) if side == LEFT else 0, len(places))

    def rule_sums(self, occ: Occ, names: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        right = occ.u + self.tail[occ.places[-1]]
        open_ = right + np.maximum(self.tail[occ.places[occ.nx - 1]] - self.head[occ.places[occ.nx]], 0)
        keys, (u, open_, right), n = per_line(occ.line, names, int(names.max()) + 1, [occ.u, open_, right])
        return summed(keys, [u, np.ones(len(keys), np.int64), n, open_, right])

    def numbered(self, found: Iterator[tuple[Occ, np.ndarray]], stage: Stage) -> Iterator[Occ]:
        for occ, names in found:
            rid = stage.live(names)
            rows = np.flatnonzero(rid >= 0)
            if len(rows):
                out = occ.at(rows)
                out.rid = rid[rows]
                yield out

    def sides(self, occ: Occ, stage: Stage) -> Iterator[tuple[Occ, int]]:
        for side in (LEFT, RIGHT):
            rows = np.flatnonzero(stage.grows[side][occ.rid])
            if len(rows):
                yield occ.at(rows), side

    def rules(self, stages: list[Stage]) -> Iterator[tuple[Occ, np.ndarray]]:
        """Occurrences and names of the rules that follow the stages, depth first."""
        if not stages:
            return self.roots()
        return self._below(self.roots(), stages)

    def _below(self, found, stages):
        for occ in self.numbered(found, stages[0]):
            for own, side in self.sides(occ, stages[0]):
                new = self.grown(own, side, stages[0].classes)
                yield from self._below(new, stages[1:]) if len(stages) > 1 else new

    def bounds(self, stages: list[Stage]) -> Iterator[tuple[np.ndarray, list[np.ndarray]]]:
        for occ in self.numbered(self.rules(stages[:-1]), stages[-1]):
            for own, side in self.sides(occ, stages[-1]):
                yield from self.class_bounds(own, side)

    def antecedents(self, stages: list[Stage]) -> Iterator[tuple[np.ndarray, list[np.ndarray]]]:
        """Names of antecedents that follow the stages, with their timelines counted."""
        at = np.arange(len(self.code))
        found = [(Occ(self.code, self.line.astype(np.int64), [at], 1, self.u, [], []), self.code)]
        for k, stage in enumerate(stages):
            found = self._longer(found, stage, k)
        for occ, names in found:
            keys, _, _ = per_line(occ.line, names, int(names.max()) + 1, [])
            yield summed(keys, [np.ones(len(keys), np.int64)])

    def _longer(self, found, stage: Stage, k: int):
        for occ, names in found:
            aid = stage.antes(names)
            rows = np.flatnonzero(aid >= 0)
            if not len(rows):
                continue
            occ = occ.at(rows)
            occ.rid = aid[rows]
            last = occ.places[-1]
            for row, e in self.expanded(last + 1, self.end[last], lambda: occ.line * (occ.rid.max() + 1) + occ.rid):
                kept = np.flatnonzero(stage.ante_classes(self.class_names(occ.rid[row], LEFT, self.code[e], self.digit(last[row], e))) >= 0)
                if len(kept):
                    old, own = occ.at(row[kept]), e[kept]
                    dx = self.digits(old.places, old.dx, own)
                    yield Occ(old.rid, old.line, [*old.places, own], k + 2, old.u, dx, []), self.name(old.rid, LEFT, self.code[own], joined(dx), 0, k + 3)


def chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[dict[str, np.ndarray]]:
    """Columns of whole timelines; rows come in the order of timelines.items."""
    held, rows = [], 0
    for batch in batches:
        if batch.num_rows:
            held.append({c: batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64, copy=False) for c in ITEMS})
            rows += batch.num_rows
        if rows < CHUNK:
            continue
        own = {c: np.concatenate([h[c] for h in held]) for c in ITEMS}
        cuts = np.flatnonzero(own["sid"][1:] != own["sid"][:-1]) + 1
        while rows >= CHUNK and len(cuts):
            cut = int(cuts[max(0, np.searchsorted(cuts, CHUNK, "right") - 1)])
            yield {c: v[:cut] for c, v in own.items()}
            own = {c: v[cut:] for c, v in own.items()}
            rows, cuts = rows - cut, cuts[cuts > cut] - cut
        held = [own]
    if rows:
        yield {c: np.concatenate([h[c] for h in held]) for c in ITEMS}


class Totals:
    """Partial sums of a partition by name."""

    def __init__(self):
        self.held, self.rows, self.base = [], 0, 0

    def add(self, keys: np.ndarray, values: list[np.ndarray]) -> None:
        self.held.append((keys, values))
        self.rows += len(keys)
        if self.rows > HELD + self.base:  # merged when as much came as there was, so that each sum is merged few times
            self.held = [self.all()]
            self.rows = self.base = len(self.held[0][0])

    def all(self) -> tuple[np.ndarray, list[np.ndarray]]:
        if not self.held:
            return np.zeros(0, np.int64), []
        width = len(self.held[0][1])
        return summed(np.concatenate([k for k, _ in self.held]), [np.concatenate([v[i] for _, v in self.held]) for i in range(width)])


def rows_of(kind: int, totals: Totals, codes: int, size: int, budget: bool = True) -> Iterator[pa.RecordBatch]:
    keys, values = totals.all()
    zero = np.zeros(len(keys), np.int64)
    rest, num, dy = keys, zero, zero
    if kind == CLASS:
        if budget:
            rest, num = rest // 7, rest % 7
    else:
        rest, num = rest // 7**size, rest % 7**size
        num, dy = num // 7, num % 7
    rest, code = rest // (codes + 1), rest % (codes + 1)
    names = [rest // 2, rest % 2, code, num, dy]
    if kind == ANTE:  # one sum: timelines
        values = [zero, *values, zero, zero, zero]
    values = [*values, *[zero] * (len(SUMS) - len(values))]
    table = pa.table([pa.array(np.full(len(keys), kind, np.int32)), *map(pa.array, names), *map(pa.array, values)], names=["kind", *NAMES, *SUMS])
    yield from table.to_batches(max_chunksize=50_000)


def passed(items: DataFrame, what: int, stages: list[Stage], opt, codes: int, allowed: np.ndarray | None) -> DataFrame:
    """Partial sums of a pass over the intervals: of rules and antecedents that follow the stages, or of the last stage's classes."""
    spark = items.sparkSession
    given = spark.sparkContext.broadcast((stages, opt, codes, allowed))

    def run(batches):
        steps, options, n, permitted = given.value
        rules, antes, size = Totals(), Totals(), len(steps) + 2
        for cols in chunks(batches):
            chunk = Chunk(cols, options, n, permitted)
            if what == CLASS:
                for keys, sums in chunk.bounds(steps):
                    rules.add(keys, sums)
                continue
            for occ, names in chunk.rules(steps):
                rules.add(*chunk.rule_sums(occ, names))
            for keys, sums in chunk.antecedents(steps):
                antes.add(keys, sums)
        if what == CLASS:
            yield from rows_of(CLASS, rules, n, size, options.class_budget)
            return
        yield from rows_of(RULE, rules, n, size)
        if steps:
            yield from rows_of(ANTE, antes, n, size)
        else:  # antecedents of one interval are named by their symbol
            keys, sums = antes.all()
            zero = np.zeros(len(keys), np.int64)
            cols = {"rid": keys, "n_rule": sums[0] if sums else zero}
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), ANTE, np.int32)), *[pa.array(cols.get(c, zero)) for c in (*NAMES, *SUMS)]], names=["kind", *NAMES, *SUMS])

    return items.select(*ITEMS).mapInArrow(run, PART)


class PackedSearch(search.Search):
    """search.Search with passes over column arrays instead of stored levels."""

    def __init__(self, items: DataFrame, opt, codes: int):
        super().__init__(items, opt)
        self.codes, self.stages, self.parents, self.allowed = codes, [], None, None

    def only(self, kept: DataFrame) -> None:
        """Symbols that may still join a rule."""
        self.allowed = np.zeros(self.codes + 1, bool)
        self.allowed[kept.toArrow()["code"].to_numpy()] = True

    def rated(self, gated: bool = False) -> DataFrame:
        part = self.tables.put(f"part-{self.size}", passed(self.items, RULE, self.stages, self.opt, self.codes, self.allowed))
        stats = part.filter(F.col("kind") == RULE).groupBy(*NAMES).agg(*[F.sum(c).alias(c) for c in SUMS])
        keys = ["rid"] if self.size == 2 else ["rid", "code", "num"]
        antes = part.filter(F.col("kind") == ANTE).groupBy(*keys).agg(F.sum("n_rule").alias("n_ante"))
        if self.size == 2:
            one = lambda c: F.array(F.col(c).cast("int"))
            full = stats.join(antes, "rid").select(one("rid").alias("x"), one("code").alias("y"), F.array("num").alias("rel"), "n_ante", F.col("rid").alias("aid"), *NAMES, *SUMS)
        else:
            antes = antes.select(F.col("rid").alias("aid"), *keys[1:], F.col("n_ante").alias("n_own"))
            full = stats.join(self.parents, "rid")
            point, n = F.array(F.col("code").cast("int")), F.size("px")
            left = full.filter(F.col("side") == LEFT).join(antes, ["aid", "code", "num"]).withColumns({
                "x": F.concat("px", point), "y": F.col("py"), "n_ante": F.col("n_own"),
                "rel": F.concat(F.slice("prel", 1, n - 1), F.array("num", R.insert_digit(F.element_at("prel", -1), 0, F.col("dy")))),
            })
            right = full.filter(F.col("side") == RIGHT).withColumns({"x": F.col("px"), "y": F.concat("py", point), "n_ante": F.col("p_ante"), "rel": F.concat("prel", F.array("num"))})
            cols = ["x", "y", "rel", "n_ante", "aid", *NAMES, *SUMS]
            full = left.select(*cols).unionByName(right.select(*cols))
        if gated:
            self.seen = Observation()
            full = search.gates(full, self.opt, self.opt.minutil, self.size).observe(self.seen, *search._level())
        return self.tables.put(f"rated-{self.size}", full)

    def step_from(self, stats: DataFrame, level: dict | None = None) -> bool:
        opt, minutil = self.opt, self.opt.minutil
        if level is None:
            stats = search.gates(stats, opt, minutil, self.size)
            level = stats.agg(*search._level()).first().asDict()
        level = {k: v or 0 for k, v in level.items()}
        good = (F.col("utility") >= minutil) & measures.enough_confidence(F.col("n_rule"), F.col("n_ante"), opt.minconf)
        self.found.append(stats.filter(good).select(*search.KEY, "n_rule", "n_ante", "utility"))
        self.metrics.candidates += level["candidates"]
        self.metrics.levels.append({"size": self.size} | level)
        if not level["left"] and not level["right"]:
            return False
        if level["left"] + level["right"] > BROADCAST_ROWS:
            raise TooMany(level)
        live = stats.filter("grow_left OR grow_right").select(*search.KEY, "n_ante", "aid", *NAMES, "grow_left", "grow_right").toArrow()
        cols = {c: live[c].to_numpy() for c in ("aid", *NAMES)}
        left, right = (live[f"grow_{side}"].to_numpy().astype(bool) for side in ("left", "right"))
        name = lambda rid, side, code, num, dy: ((rid * 2 + side) * (self.codes + 1) + code) * 7**self.size + num * 7 + dy
        # antecedents of rules that grow left: a symbol, or a longer antecedent by the name that passes give it
        own = cols["rid"] if self.size == 2 else name(cols["aid"], LEFT, cols["code"], cols["num"], 0)
        named, number = np.unique(own[left], return_inverse=True)
        aid = np.full(live.num_rows, -1)
        aid[left] = number
        rid = np.arange(live.num_rows)
        stage = Stage(Lookup(name(*(cols[c] for c in NAMES))), (left, right), Lookup(named))
        kept_cols = {"rid": pa.array(rid), "px": live["x"], "py": live["y"], "prel": live["rel"], "p_ante": live["n_ante"], "aid": pa.array(aid)}
        self.parents = self.tables.put(f"live-{self.size}", self.spark.createDataFrame(pa.table(kept_cols)))
        stages = [*self.stages, stage]
        part = passed(self.items, CLASS, stages, opt, self.codes, self.allowed)
        seen, kept = Observation(), Observation()
        every = F.count(F.lit(1)).alias("n")
        by = ["rid", "side", "code", "num"]
        classes = part.groupBy(*by).agg(F.sum("utility").alias("bound")).observe(seen, every).filter(F.col("bound") >= minutil)
        classes = self.tables.put(f"classes-{self.size}", classes.select(*by).observe(kept, every))
        n = kept.get["n"]
        self.metrics.levels[-1] |= {"classes": seen.get["n"], "classes_kept": n}
        if not n:
            return False
        if n > BROADCAST_ROWS:
            raise TooMany(n)
        got = {c: v.to_numpy() for c, v in zip(by, classes.select(*by).toArrow().columns)}
        wide = lambda rid, rows: ((rid * 2 + got["side"][rows]) * (self.codes + 1) + got["code"][rows]) * (7 if opt.class_budget else 1) + got["num"][rows]
        every_row, lefts = slice(None), got["side"] == LEFT
        stage.classes = Lookup(wide(got["rid"], every_row))
        stage.ante_classes = Lookup(np.unique(wide(aid[got["rid"]][lefts], lefts)))
        self.stages = stages
        self.size += 1
        return True
