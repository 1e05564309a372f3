"""ANSI SQL (DuckDB) for the same logs, rules and measures, written from the definitions."""

from __future__ import annotations

DAY = "CAST(datediff('day', DATE '1995-01-01', CAST({} AS DATE)) AS BIGINT)"
CENTS = "CAST(floor(({}) * 100 + 0.5) AS BIGINT)"
SHIPPED = "FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE l_shipdate > o_orderdate {} GROUP BY o_orderkey, o_custkey, o_orderpriority, o_orderdate, o_totalprice"
SPANS = f"SELECT o_custkey AS sid, o_orderpriority AS sym, {DAY.format('o_orderdate')} AS st, {DAY.format('max(l_shipdate)')} AS ft, {CENTS.format('o_totalprice')} AS u " + SHIPPED
ITEMS = "SELECT l_orderkey AS sid, {sym} AS sym, " + DAY.format("l_shipdate") + " AS st, " + DAY.format("l_shipdate") + " + CAST({days} * l_quantity AS BIGINT) AS ft, " + CENTS.format("l_extendedprice * (1 - l_discount)") + " AS u FROM lineitem JOIN part ON p_partkey = l_partkey"
USAGE = "SELECT {sid} AS sid, {sym} AS sym, epoch_us(ts) AS st, epoch_us(ts) + " + CENTS.format("value") + " * {scale} AS ft, " + CENTS.format("value") + " AS u FROM events"
WEEK = "user_id * 100 + (day(ts) - 1) // 7"
RAW = {
    "order_spans": SPANS.format(""),
    "short_order_spans": SPANS.format("AND l_shipdate < o_orderdate + INTERVAL 121 DAY"),
    "quarter_spans": "SELECT o_custkey AS sid, o_orderpriority AS sym, year(o_orderdate) * 4 + quarter(o_orderdate) AS st, year(max(l_shipdate)) * 4 + quarter(max(l_shipdate)) + 1 AS ft, " + CENTS.format("o_totalprice") + " AS u " + SHIPPED.format(""),
    "items_by_type": ITEMS.format(sym="p_type", days=20),
    "items_by_brand": ITEMS.format(sym="p_brand", days=1),
    "user_weeks": USAGE.format(sid=WEEK, sym="event_type", scale=36000000),
    "user_weeks_k": USAGE.format(sid=WEEK, sym="event_type || '-' || CAST(CAST(json_extract_string(props, '$.k') AS INT) // 20 AS VARCHAR)", scale=36000000),
    "user_days": USAGE.format(sid="user_id * 100 + day(ts)", sym="event_type", scale=3600000),
    "talk_turns": "SELECT conv_id AS sid, role AS sym, ft - n - 1 AS st, ft, n AS u FROM (SELECT conv_id, role, length(text) AS n, sum(length(text) + 1) OVER (PARTITION BY conv_id ORDER BY turn) AS ft FROM conversations)",
}
EXAMPLE = "SELECT * FROM (VALUES (1,'A',1,3,8),(1,'C',5,8,10),(1,'B',7,11,7),(1,'D',10,14,9),(2,'A',1,3,2),(2,'C',4,6,2),(2,'B',7,11,4),(2,'D',10,14,6),(3,'A',1,2,2),(3,'B',3,4,4),(3,'C',5,6,2),(3,'D',7,9,6)) t(sid, sym, st, ft, u)"
RAW["example"] = EXAMPLE


def digit(a_st: str, a_ft: str, b_st: str, b_ft: str) -> str:
    """The relation table as disjoint conditions."""
    return f"(CASE WHEN {b_st} > {a_ft} THEN 0 WHEN {b_st} = {a_ft} THEN 1 WHEN {a_st} < {b_st} AND {b_ft} > {a_ft} THEN 2 WHEN {a_st} < {b_st} AND {b_ft} < {a_ft} THEN 3 WHEN {a_st} < {b_st} THEN 4 WHEN {a_ft} <> {b_ft} THEN 5 ELSE 6 END)"


def log(name: str) -> str:
    return f"log AS (SELECT CAST(sid AS BIGINT) AS sid, sym, CAST(st AS BIGINT) AS st, CAST(ft AS BIGINT) AS ft, CAST(sum(u) AS BIGINT) AS u FROM ({RAW[name]}) WHERE st < ft GROUP BY ALL)"


POINTS = "log AS (SELECT sid, sym, st * 2 AS st, st * 2 + 1 AS ft, CAST(sum(u) AS BIGINT) AS u FROM log0 GROUP BY ALL)"
# positions, utility behind, first position of the same start
IV = """iv AS (SELECT *, row_number() OVER w AS p, CAST(coalesce(sum(u) OVER (PARTITION BY sid ORDER BY st, ft, sym ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0) AS BIGINT) AS tail,
 rank() OVER (PARTITION BY sid ORDER BY st) AS tie FROM log WINDOW w AS (PARTITION BY sid ORDER BY st, ft, sym))"""


def number(k: int) -> str:
    """Number of interval k against 1 .. k-1 of a level row l and a new interval i."""
    out = "0"
    for j in range(1, k):
        out = f"({out}) * 7 + {digit(f'l.st{j}', f'l.ft{j}', 'i.st', 'i.ft')}"
    return out


def levels(cap: int) -> str:
    """L1 .. Lcap: every sub-timeline with symbols s, numbers n, positions in places."""
    out = ["L1 AS (SELECT sid, p, [sym] AS s, CAST([] AS BIGINT[]) AS n, [p] AS places, st AS st1, ft AS ft1, u FROM iv)"]
    for m in range(2, cap + 1):
        old = ", ".join(f"l.st{j}, l.ft{j}" for j in range(1, m))
        out.append(f"L{m} AS (SELECT l.sid, i.p, list_append(l.s, i.sym) AS s, list_append(l.n, CAST({number(m)} AS BIGINT)) AS n, list_append(l.places, i.p) AS places, {old}, i.st AS st{m}, i.ft AS ft{m}, l.u + i.u AS u FROM L{m - 1} l JOIN iv i ON i.sid = l.sid AND i.p > l.p)")
    return ",\n".join(out)


def split(cap: int, disjoint: str = "symbol", max_x: int = 99, max_y: int = 99) -> str:
    """occ: occurrences of all rules; ante: timelines of each antecedent."""
    rules, antes = [], []
    for m in range(2, cap + 1):
        for k in range(1, m):
            if k > max_x or m - k > max_y:
                continue
            apart = f" AND NOT list_has_any(s[1:{k}], s[{k + 1}:{m}])" if disjoint == "symbol" else ""
            rules.append(f"SELECT sid, array_to_string(s[1:{k}], ',') || '>' || array_to_string(s[{k + 1}:{m}], ',') || '|' || array_to_string(n, ',') AS rule, array_to_string(s[1:{k}], ',') || '|' || array_to_string(n[1:{k - 1}], ',') AS ante, places, u FROM L{m} WHERE st{k} < st{k + 1}{apart}")
    for k in range(1, cap):
        antes.append(f"SELECT sid, array_to_string(s, ',') || '|' || array_to_string(n, ',') AS ante FROM L{k}")
    return "occ AS (" + "\nUNION ALL ".join(rules) + "),\nante AS (SELECT ante, count(DISTINCT sid) AS n_ante FROM (" + " UNION ALL ".join(antes) + ") GROUP BY 1)"


def rated(cap: int, occurrence: str = "max", **options) -> str:
    value = {"max": "max(u)", "first": "arg_min(u, places)"}[occurrence]
    return split(cap, **options) + f",\nrated AS (SELECT rule, n_rule, n_ante, utility FROM (SELECT rule, ante, CAST(count(*) AS BIGINT) AS n_rule, CAST(sum(u) AS BIGINT) AS utility FROM (SELECT sid, rule, ante, {value} AS u FROM occ GROUP BY sid, rule, ante) GROUP BY rule, ante) JOIN ante USING (ante))"


def mine(name: str, ratio: float | None, minconf: float, cap: int, minutil: int | None = None, tail: str = "", points: bool = False, **options) -> str:
    bar = f"{minutil}" if minutil is not None else f"(SELECT ceil({ratio} * sum(u)) FROM log)"
    source = log(name).replace("log AS", "log0 AS", 1) + ",\n" + POINTS if points else log(name)
    return f"WITH {source},\n{IV},\n{levels(cap)},\n{rated(cap, **options)}\nSELECT rule, n_rule, n_ante, utility FROM rated WHERE utility >= {bar} AND n_rule * 1000000 >= n_ante * {round(minconf * 1000000)} {tail}"


def frequent(name: str, minsup: int, minconf: float, cap: int, points: bool = False) -> str:
    source = log(name).replace("log AS", "log0 AS", 1) + ",\n" + POINTS if points else log(name)
    return f"WITH {source},\n{IV},\n{levels(cap)},\n{rated(cap)}\nSELECT rule, n_rule, n_ante, utility FROM rated WHERE n_rule >= {minsup} AND n_rule * 1000000 >= n_ante * {round(minconf * 1000000)}"


def patterns(name: str, cap: int, having: str) -> str:
    every = " UNION ALL ".join(f"SELECT sid, array_to_string(s, ',') || '|' || array_to_string(n, ',') AS pattern, u FROM L{k}" for k in range(1, cap + 1))
    return f"WITH {log(name)},\n{IV},\n{levels(cap)},\nbest AS (SELECT sid, pattern, max(u) AS u FROM ({every}) GROUP BY 1, 2)\nSELECT pattern, CAST(count(*) AS BIGINT) AS support, CAST(sum(u) AS BIGINT) AS utility FROM best GROUP BY 1 HAVING {having}"




def _family(cap: int) -> str:
    """fam: occurrences of all rules with their parent, the class in which they were formed and the bound that counts in it.

    The parent of a rule of one consequent lacks the last antecedent interval, that of any other rule its last consequent interval.
    """
    out = []
    for m in range(2, cap + 1):
        for k in range(1, m):
            left = m - k == 1
            grown = k if left else m  # place of the last joined interval; the class is its symbol and digit to the one before it on its side
            key = f"array_to_string(s[1:{k}], ',') || '>' || array_to_string(s[{k + 1}:{m}], ',') || '|' || array_to_string(n, ',')"
            if m == 2:
                parent, cls = "''", "''"
            elif left:
                parent = f"array_to_string(s[1:{k - 1}], ',') || '>' || s[{m}] || '|' || array_to_string(list_append(n[1:{k - 2}], n[{m - 1}] // 7), ',')"
            else:
                parent = f"array_to_string(s[1:{k}], ',') || '>' || array_to_string(s[{k + 1}:{m - 1}], ',') || '|' || array_to_string(n[1:{m - 2}], ',')"
            if m > 2:
                cls = f"s[{grown}] || '/' || {digit(f'st{grown - 1}', f'ft{grown - 1}', f'st{grown}', f'ft{grown}')}"
            out.append(
                f"SELECT l.sid, {m} AS size, {m - k} AS ny, {key} AS rule, {parent} AS parent, {'TRUE' if left else 'FALSE'} AS to_left, {cls} AS class, l.u, "
                f"l.u + greatest(a.tail - (t.tail + t.u), 0) + b.tail AS ob, l.u + b.tail AS rb, array_to_string(s[1:{k}], ',') || '|' || array_to_string(n[1:{k - 1}], ',') AS ante "
                f"FROM L{m} l JOIN iv a ON a.sid = l.sid AND a.p = l.places[{k}] JOIN iv y ON y.sid = l.sid AND y.p = l.places[{k + 1}] JOIN iv t ON t.sid = l.sid AND t.p = y.tie JOIN iv b ON b.sid = l.sid AND b.p = l.places[{m}] "
                f"WHERE st{k} < st{k + 1} AND NOT list_has_any(s[1:{k}], s[{k + 1}:{m}])"
            )
    antes = " UNION ALL ".join(f"SELECT sid, array_to_string(s, ',') || '|' || array_to_string(n, ',') AS ante FROM L{k}" for k in range(1, cap))
    return "fam AS (" + "\nUNION ALL ".join(out) + f"),\nante AS (SELECT ante, count(DISTINCT sid) AS n_ante FROM ({antes}) GROUP BY 1)"


def sweep(name: str, ratios, variants, minconf: float, cap: int) -> str:
    """Candidates, rules and bytes of each threshold and variant. No symbol is removed at these thresholds."""
    bars = ", ".join(f"({round(r * 1_000_000)}, (SELECT CAST(ceil({r} * sum(u)) AS BIGINT) FROM log))" for r in ratios)
    ctes = [
        log(name), IV, levels(cap), _family(cap),
        f"bar AS (SELECT * FROM (VALUES {bars}) t(ppm, bar))",
        "rule_of AS (SELECT rule, parent, size, ny, to_left, class, CAST(sum(u) AS BIGINT) AS utility, count(*) AS n_rule, sum(ob) AS ob, sum(rb) AS rb, any_value(ante) AS ante FROM (SELECT sid, rule, parent, size, ny, to_left, class, ante, max(u) AS u, max(ob) AS ob, max(rb) AS rb FROM fam GROUP BY ALL) GROUP BY rule, parent, size, ny, to_left, class)",
        "rated AS (SELECT rule_of.*, n_ante FROM rule_of JOIN ante USING (ante))",
        "by_class AS (SELECT parent, to_left, class, sum(b) AS bound FROM (SELECT sid, parent, to_left, class, max(CASE WHEN to_left THEN ob ELSE rb END) AS b FROM fam WHERE size > 2 GROUP BY ALL) GROUP BY ALL)",
        "by_symbol AS (SELECT parent, to_left, symbol, sum(b) AS bound FROM (SELECT sid, parent, to_left, split_part(class, '/', 1) AS symbol, max(CASE WHEN to_left THEN ob ELSE rb END) AS b FROM fam WHERE size > 2 GROUP BY ALL) GROUP BY ALL)",
    ]
    selects = []
    for kind, table, cond in (("budget", "by_class", "c.class = r.class"), ("plain", "by_symbol", "c.symbol = split_part(r.class, '/', 1)")):
        ctes.append(f"{kind}2 AS (SELECT bar.ppm, bar.bar, r.* FROM rated r, bar WHERE size = 2)")
        for m in range(3, cap + 1):
            ctes.append(
                f"{kind}{m} AS (SELECT p.ppm, p.bar, r.* FROM rated r JOIN {kind}{m - 1} p ON p.rule = r.parent JOIN {table} c ON c.parent = r.parent AND c.to_left = r.to_left AND {cond} "
                f"WHERE r.size = {m} AND c.bound >= p.bar AND CASE WHEN r.to_left THEN p.ny = 1 AND p.ob >= p.bar ELSE p.rb >= p.bar AND p.n_rule * 1000000 >= p.n_ante * {round(minconf * 1_000_000)} END)"
            )
        ctes.append(f"{kind} AS (" + " UNION ALL ".join(f"SELECT ppm, count(*) AS n FROM {kind}{m} GROUP BY ppm" for m in range(2, cap + 1)) + ")")
    good = f"SELECT ppm, rule, utility, size FROM rated, bar WHERE utility >= bar AND n_rule * 1000000 >= n_ante * {round(minconf * 1_000_000)}"
    ctes.append(f"found AS (SELECT ppm, count(*) AS rules, sum(length(rule) + length(CAST(utility AS VARCHAR)) + 27) AS base7, sum(length(split_part(rule, '|', 1)) + size * (size - 1) + length(CAST(utility AS VARCHAR)) + 27) AS matrix FROM ({good}) GROUP BY ppm)")
    for variant in variants:
        kind = "plain" if variant in ("no_budget", "neither") else "budget"
        selects.append(f"SELECT '{name}' AS log, CAST(bar.ppm AS BIGINT) AS minutil_ppm, '{variant}' AS variant, CAST((SELECT sum(n) FROM {kind} k WHERE k.ppm = bar.ppm) AS BIGINT) AS candidates, CAST(coalesce(rules, 0) AS BIGINT) AS rules, CAST(coalesce(base7, 0) AS BIGINT) AS bytes_base7, CAST(coalesce(matrix, 0) AS BIGINT) AS bytes_matrix FROM bar LEFT JOIN found USING (ppm)")
    return "WITH " + ",\n".join(ctes) + "\n" + "\nUNION ALL ".join(selects)


PAIRS = "pairs AS (SELECT a.sid, a.p AS pa, b.p AS pb, a.sym AS sa, b.sym AS sb, " + digit("a.st", "a.ft", "b.st", "b.ft") + " AS d, a.u + b.u AS u, a.tail AS ta, b.tail AS tb, b.tie AS tie, a.st < b.st AND a.sym <> b.sym AS ok FROM iv a JOIN iv b ON a.sid = b.sid AND a.p < b.p)"
# occurrences of one-to-one rules with reserves
ROOTS = "roots AS (SELECT r.*, greatest(r.ta - (t.tail + t.u), 0) AS lr, r.tb AS rr FROM pairs r JOIN iv t ON t.sid = r.sid AND t.p = r.tie WHERE ok)"


def on(name: str, select: str, *ctes: str) -> str:
    return f"WITH {log(name)},\n{IV}" + "".join(",\n" + c for c in ctes) + f"\n{select}"
