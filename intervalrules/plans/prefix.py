"""Depth-first engine: one task holds all timelines with a first antecedent symbol and searches its rules alone.

With a longest size a task's timelines are column arrays, and all extensions of a rule are found together (Subtree); otherwise they are lists (DepthFirst).
It stores no level and suits the deep tail of a search; a symbol's timelines must fit one task. The level engine has no such limit.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import packed, timelines


def relation(a, b) -> int:
    """Digit of two (st, ft, ...) in timeline order."""
    if a[1] < b[0]:
        return 0
    if a[1] == b[0]:
        return 1
    if a[0] == b[0]:
        return 6 if a[1] == b[1] else 5
    return 2 if a[1] < b[1] else 3 if a[1] > b[1] else 4


def number(earlier, e) -> int:
    out = 0
    for q in earlier:
        out = out * 7 + relation(q, e)
    return out


def limbs(num: int, k: int) -> list[int]:
    """The number of k digits as its column form has it: 22 digits a limb, the highest first."""
    out = []
    while k > 0:
        out.append(num % 7**22)
        num, k = num // 7**22, k - 22
    return out[::-1]


FIELDS = ("st", "ft", "code", "u", "tail", "tie")


def lines_of(column: pa.ChunkedArray) -> list[list[tuple]]:
    """Timelines of an Arrow column of arrays of FIELDS, its values read column by column."""
    out = []
    for chunk in column.chunks:
        flat = chunk.flatten()
        rows = list(zip(*(flat.field(c).to_numpy(zero_copy_only=False).tolist() for c in FIELDS)))
        ends = chunk.value_lengths().to_pylist()
        at = 0
        for n in ends:
            out.append(rows[at : at + n])
            at += n
    return out


class DepthFirst:
    """Rules whose antecedent starts with one symbol. lines: timelines as lists of (st, ft, code, u, tail, tie)."""

    def __init__(self, first: int, lines: list[list[tuple]], opt):
        self.first, self.lines, self.opt = first, lines, opt
        self.found, self.candidates, self.minconf = [], 0, Fraction(str(opt.minconf))
        self.counted: dict[tuple, int] = {}  # timelines of each antecedent pattern, which many consequents share

    def run(self):
        ante = {k: [(i,) for i, e in enumerate(line) if e[2] == self.first] for k, line in enumerate(self.lines)}
        self.antecedent((self.first,), (), {k: v for k, v in ante.items() if v})
        return self

    def antecedent(self, x, xrel, ante):
        """All rules that start from single consequents of one antecedent pattern."""
        classes: dict[tuple, dict[int, list]] = {}
        for k, places in ante.items():
            line = self.lines[k]
            for px in places:
                last = line[px[-1]]
                for j in range(px[-1] + 1, len(line)):
                    e = line[j]
                    if e[0] > last[0] and (self.opt.disjoint != "symbol" or e[2] not in x):
                        classes.setdefault((e[2], number([line[p] for p in px], e)), {}).setdefault(k, []).append((px, (j,)))
        return self.consequents(x, xrel, ante, classes)

    def consequents(self, x, xrel, ante, classes):
        for (code, num), occ in classes.items():
            self.rule(x, (code,), (*xrel, num), occ, len(ante), True)

    def bounds(self, k, px, py):
        line = self.lines[k]
        u = sum(line[p][3] for p in px) + sum(line[p][3] for p in py)
        tie = line[py[0]][5] - 1
        left = max(0, line[px[-1]][4] - (line[tie][4] + line[tie][3]))
        return u, left, line[py[-1]][4]

    def rule(self, x, y, rel, occ, n_ante, may_left):
        opt = self.opt
        self.candidates += 1
        utility = open_bound = right_bound = 0
        for k, places in occ.items():
            rows = [(px + py, *self.bounds(k, px, py)) for px, py in places]
            utility += max(r[1] for r in rows) if opt.occurrence == "max" else min(rows)[1]
            open_bound += max(u + a + b for _, u, a, b in rows)
            right_bound += max(u + b for _, u, _, b in rows)
        confident = len(occ) >= n_ante * self.minconf
        if utility >= opt.minutil and confident:
            self.found.append((list(x), list(y), [v for k, num in enumerate(rel, 1) for v in limbs(num, k)], len(occ), n_ante, utility))
        size = len(x) + len(y)
        if opt.max_size is not None and size >= opt.max_size:
            return
        if may_left and ("open_bound" in opt.disable or open_bound >= opt.minutil) and (opt.max_x is None or len(x) < opt.max_x):
            self.grow(x, y, rel, occ, n_ante, "left")
        if (confident or "confidence" in opt.disable) and ("right_bound" in opt.disable or right_bound >= opt.minutil) and (opt.max_y is None or len(y) < opt.max_y):
            self.grow(x, y, rel, occ, n_ante, "right")

    def grow(self, x, y, rel, occ, n_ante, side):
        opt = self.opt
        best: dict[tuple, dict[int, int]] = {}
        grown: dict[tuple, dict[int, list]] = {}
        for k, places in occ.items():
            line = self.lines[k]
            for px, py in places:
                u, left, right = self.bounds(k, px, py)
                tie = line[py[0]][5] - 1
                inside = range(px[-1] + 1, tie) if side == "left" else range(py[-1] + 1, len(line))
                behind = line[tie][4] + line[tie][3]
                prior = line[px[-1]] if side == "left" else line[py[-1]]
                for j in inside:
                    e = line[j]
                    if opt.disjoint == "symbol" and e[2] in (y if side == "left" else x):
                        continue
                    bound = u + e[3] + e[4] + (right - behind if side == "left" else 0)
                    own = (e[2], relation(prior, e)) if opt.class_budget else (e[2],)
                    seen = best.setdefault(own, {})
                    seen[k] = max(seen.get(k, 0), bound)
                    if side == "left":
                        key = (own, (*x, e[2]), y, (*rel[: len(x) - 1], number([line[p] for p in px], e), rel[-1] * 7 + relation(e, line[py[0]])))
                        grown.setdefault(key, {}).setdefault(k, []).append(((*px, j), py))
                    else:
                        key = (own, x, (*y, e[2]), (*rel, number([line[p] for p in px + py], e)))
                        grown.setdefault(key, {}).setdefault(k, []).append((px, (*py, j)))
        kept = {own for own, per in best.items() if sum(per.values()) >= opt.minutil}
        for (own, x2, y2, rel2), occ2 in grown.items():
            if own in kept:
                n = self.count(x2, rel2[: len(x2) - 1]) if side == "left" else n_ante
                self.rule(x2, y2, rel2, occ2, n, side == "left")

    def count(self, x, xrel) -> int:
        """Timelines with an antecedent pattern, scanned once for each pattern."""
        if (x, xrel) not in self.counted:
            self.counted[x, xrel] = self._scan(x, xrel)
        return self.counted[x, xrel]

    def _scan(self, x, xrel) -> int:
        total = 0
        for line in self.lines:
            open_ = [(i,) for i, e in enumerate(line) if e[2] == x[0]]
            for code, num in zip(x[1:], xrel):
                open_ = [(*p, j) for p in open_ for j in range(p[-1] + 1, len(line)) if line[j][2] == code and number([line[q] for q in p], line[j]) == num]
                if not open_:
                    break
            total += bool(open_)
        return total


def chunk_of(column: pa.ChunkedArray, opt, codes: int) -> packed.Chunk:
    """Timelines of an Arrow column of arrays of (st, ft, code, u) as column arrays."""
    flat = [chunk.flatten() for chunk in column.chunks]
    cols = {c: np.concatenate([f.field(c).to_numpy(zero_copy_only=False) for f in flat]).astype(np.int64, copy=False) for c in ("st", "ft", "code", "u")}
    n = np.concatenate([chunk.value_lengths().to_numpy() for chunk in column.chunks])
    end = np.cumsum(n)
    cols["sid"] = np.repeat(np.arange(len(n)), n)
    cols["pos"] = np.arange(len(cols["sid"])) - np.repeat(end - n, n) + 1
    upto = np.cumsum(cols["u"])
    cols["tail"] = np.repeat(upto[end - 1], n) - upto
    cols["head"] = cols["u"]
    del flat, upto
    out = packed.Chunk(cols, opt, codes, None)
    out.head = (out.tail + out.u)[out.tie]
    return out


def together(parts: list[tuple[packed.Occ, np.ndarray]]) -> tuple[packed.Occ, np.ndarray]:
    if len(parts) == 1:
        return parts[0]
    occ, names = zip(*parts)
    cat = lambda get: np.concatenate([get(o) for o in occ])
    many = lambda get: [np.concatenate(cols) for cols in zip(*map(get, occ))]
    one = packed.Occ(cat(lambda o: o.rid), cat(lambda o: o.line), many(lambda o: o.places), occ[0].nx, cat(lambda o: o.u), many(lambda o: o.dx), many(lambda o: o.dy))
    return one, np.concatenate(names)


class Subtree:
    """DepthFirst over column arrays, for the best occurrence and rules of a longest size. chunk: all timelines with the symbol, from it on."""

    def __init__(self, first: int, chunk: packed.Chunk, opt):
        self.first, self.chunk, self.opt = first, chunk, opt
        self.found, self.candidates, self.minconf = [], 0, Fraction(str(opt.minconf))
        self.counted: dict[tuple, dict[tuple, int]] = {}  # of an antecedent pattern: timelines of each that is one interval longer

    def run(self):
        lines = int(self.chunk.line[-1]) + 1
        for second in np.unique(self.chunk.code).tolist():  # one at a time, so that few occurrences are held
            if second != self.first or self.opt.disjoint != "symbol":
                self.children(list(self.chunk.roots_of(self.first, second)), (self.first,), (), (), packed.RIGHT, lines)
        return self

    def children(self, parts, x, y, rel, side, n_ante):
        """Rates the rules one interval longer than x, y, rel, and searches the subtree of each."""
        if not parts:
            return
        occ, names = together(parts)
        opt, size, width = self.opt, len(x) + len(y) + 1, self.chunk.codes
        names = names % (width * 7**size)  # without the parent's number and the side
        keys, sums = self.chunk.rule_sums(occ, names)
        self.candidates += len(keys)
        order = np.argsort(names, kind="stable")
        ends = np.append(packed.starts_of(names[order]), len(order))
        for i, (key, utility, n_rule, _, open_bound, right_bound) in enumerate(zip(keys.tolist(), *(v.tolist() for v in sums))):
            code, num, dy = key // 7**size, key % 7**size // 7, key % 7
            if side == packed.LEFT:
                x2, y2, rel2 = (*x, code), y, (*rel[: len(x) - 1], num, rel[-1] * 7 + dy)
                n = self.count(x, rel[: len(x) - 1])[code, num]
            else:
                x2, y2, rel2, n = x, (*y, code), (*rel, num), n_ante
            confident = n_rule >= n * self.minconf
            if utility >= opt.minutil and confident:
                self.found.append((list(x2), list(y2), [v for k, own in enumerate(rel2, 1) for v in limbs(own, k)], n_rule, n, utility))
            if size >= opt.max_size:
                continue
            left = len(y2) == 1 and ("open_bound" in opt.disable or open_bound >= opt.minutil) and (opt.max_x is None or len(x2) < opt.max_x)
            right = (confident or "confidence" in opt.disable) and ("right_bound" in opt.disable or right_bound >= opt.minutil) and (opt.max_y is None or len(y2) < opt.max_y)
            if left or right:
                own = occ.at(order[ends[i] : ends[i + 1]])
                own.rid = np.zeros(len(own.line), np.int64)
                for way, grows in ((packed.LEFT, left), (packed.RIGHT, right)):
                    if grows:
                        self.children(self.kept(own, way), x2, y2, rel2, way, n)

    def kept(self, occ, side):
        totals = packed.Totals()
        for keys, sums in self.chunk.class_bounds(occ, side):
            totals.add(keys, sums)
        keys, sums = totals.all()
        if not len(keys) or not (good := keys[sums[0] >= self.opt.minutil]).size:
            return []
        return list(self.chunk.grown(occ, side, packed.Lookup(good)))

    def antecedents(self, x, xrel):
        """Occurrences of an antecedent pattern, timelines at a time."""
        if len(x) == 1:
            at = np.flatnonzero(self.chunk.code == self.first)
            yield packed.Occ(self.chunk.code[at], self.chunk.line[at].astype(np.int64), [at], 1, self.chunk.u[at], [], [])
            return
        for occ, code, num in self.longer(x[:-1], xrel[:-1]):
            rows = np.flatnonzero((code == x[-1]) & (num == xrel[-1]))
            if len(rows):
                yield occ.at(rows)

    def longer(self, x, xrel):
        """(occurrences, codes, numbers) of all patterns one interval longer."""
        for occ in self.antecedents(x, xrel):
            last = occ.places[-1]
            for row, e in self.chunk.expanded(last + 1, self.chunk.end[last], lambda: occ.line):
                old = occ.at(row)
                dx = self.chunk.digits(old.places, old.dx, e)
                yield packed.Occ(old.rid, old.line, [*old.places, e], old.nx + 1, old.u, dx, []), self.chunk.code[e], packed.joined(dx)

    def count(self, x, xrel) -> dict[tuple, int]:
        """Timelines of each pattern one interval longer than x, by its symbol and number; found once for each x."""
        if (x, xrel) not in self.counted:
            totals, size = packed.Totals(), len(x)
            for occ, code, num in self.longer(x, xrel):
                names = code * 7**size + num
                keys, _, _ = packed.per_line(occ.line, names, int(names.max()) + 1, [])
                totals.add(*packed.summed(keys, [np.ones(len(keys), np.int64)]))
            keys, sums = totals.all()
            self.counted[x, xrel] = {(k // 7**size, k % 7**size): n for k, n in zip(keys.tolist(), sums[0].tolist())}
        return self.counted[x, xrel]


def mine_prefixes(coded: DataFrame, opt):
    """(rules, metrics) as of the level engine."""
    from ..llm.common import give_back
    from .scratch import Tables
    from .search import RULES, Metrics, partitions

    arrays = timelines.arrays(coded, partitions(coded))
    codes = coded.agg(F.coalesce(F.max("code"), F.lit(0))).first()[0]
    columns = opt.occurrence == "max" and packed.fits(codes, opt.max_size)
    slim = F.transform("iv", lambda e: F.struct(*[e[c].alias(c) for c in FIELDS]))
    dealt = arrays.select(F.explode(F.array_distinct(F.transform("iv", lambda e: e["code"]))).alias("first"), slim.alias("iv"))
    if columns:  # a rule lies behind its first symbol; utilities behind an interval are summed in the task
        own_codes = F.transform("iv", lambda e: e["code"])
        short = F.transform("iv", lambda e: F.struct(*[e[c].alias(c) for c in ("st", "ft", "code", "u")]))
        dealt = arrays.select(F.explode(F.array_distinct(own_codes)).alias("first"), own_codes.alias("codes"), short.alias("iv"))
        dealt = dealt.select("first", F.expr("slice(iv, CAST(array_position(codes, first) AS INT), size(iv))").alias("iv"))

    def search(group: pa.Table) -> pa.Table:
        first = group["first"][0].as_py()
        run = (Subtree(first, chunk_of(group["iv"], opt, codes), opt) if columns else DepthFirst(first, lines_of(group["iv"]), opt)).run()
        rows = [*run.found, ([], [], [], 0, 0, run.candidates)]  # the last row carries the count
        del run
        give_back()
        kinds = (pa.list_(pa.int32()), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.int64(), pa.int64(), pa.int64())
        return pa.table([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=["x", "y", "rel", "n_rule", "n_ante", "utility"])

    # ranges of symbols: hashes would put several symbols in one task and none in others
    own = dealt.repartitionByRange(2 * partitions(coded), "first")
    out = Tables(coded.sparkSession, "prefix").put("rules", own.groupBy("first").applyInArrow(search, RULES))
    count = out.filter("size(x) = 0").agg(F.coalesce(F.sum("utility"), F.lit(0))).first()[0]
    return out.filter("size(x) > 0"), Metrics(candidates=count)
