"""Each operator against a brute-force version, and its edge cases."""

import hashlib
import json
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from intervalrules.llm import decontam, hilbert, html, langid, neardup, packing, pii, setjoin, suffix, tokencount

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, shard string"
WORDS = [a + b for a in ("ka", "lo", "mi", "su", "ter", "van", "que", "zo") for b in ("n", "ra", "st", "li", "o", "mer", "")]


def prose(rng, n):
    return " ".join(rng.choice(WORDS) for _ in range(n))


@pytest.fixture(scope="module")
def rows():
    rng = random.Random(1)
    shared = prose(rng, 60)
    out = []
    for i in range(40):
        text = prose(rng, rng.randint(1, 120))
        if i % 5 == 0:
            text = text + " " + shared + " " + prose(rng, 5)
        out.append((i, text, "en", f"src{i % 3}", len(text), "x"))
    out += [(40, None, None, None, None, None), (41, "", "en", "s", 0, "x"), (42, out[5][1], "en", "s", 5, "x"), (42, out[5][1], "en", "s", 5, "x"), (None, out[0][1], None, "s", 5, "x"), (43, "é" * 3000 + " 12", "fr", "s", 9, "x")]
    return out


@pytest.fixture(scope="module")
def docs(spark, rows):
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_hilbert_curve_visits_neighbours(spark):
    n, bits = 8, 3
    cells = spark.createDataFrame([(a, b, a, b) for a in range(n) for b in range(n)], "a int, b int, x int, y int")
    got = hilbert.curve_index(cells, ["x", "y"], bits, "i").orderBy("i").collect()
    assert [r["i"] for r in got] == list(range(n * n))
    assert all(abs(p["a"] - q["a"]) + abs(p["b"] - q["b"]) == 1 for p, q in zip(got, got[1:]))


@pytest.mark.parametrize("law", ["rows", "bytes"])
def test_hilbert_shards(docs, rows, empty, law):
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("bigint") + 1
    cut = lambda df: hilbert.hilbert_shards(df, "doc_id", ["source", "lang", "n_chars"], size, 4, law).collect()
    got = cut(docs)
    assert Counter(r["doc_id"] for r in got) == Counter(r[0] for r in rows)
    for s in range(4):
        assert sorted(r["slot"] for r in got if r["shard"] == s) == list(range(sum(r["shard"] == s for r in got)))
    if law == "rows":
        counts = Counter(r["shard"] for r in got)
        assert max(counts.values()) - min(counts.values()) <= 1
    assert cut(empty) == []


def test_hilbert_order_against_plain_python(spark, docs, rows):
    dims, bits = ["source", "n_chars"], 4
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("bigint") + 1
    got = hilbert.hilbert_shards(docs, "doc_id", dims, size, 5, "rows", bits, {"text_crc32": F.crc32("text")}).collect()
    cells = [(a, b, a, b) for a in range(1 << bits) for b in range(1 << bits)]
    grid = hilbert.curve_index(spark.createDataFrame(cells, "a int, b int, x int, y int"), ["x", "y"], bits, "i")
    place = {(r["a"], r["b"]): r["i"] for r in grid.collect()}
    cuts = hilbert.borders(docs, dims, bits)

    def ordinal(v):
        return None if v is None else v if isinstance(v, int) else int.from_bytes(v.encode()[:7].ljust(7, b"\0"), "big")

    bucket = lambda v, c: 0 if v is None else 1 + sum(v > x for x in c)
    want = Counter()
    for r in rows:
        at = place[bucket(ordinal(r[3]), cuts["source"]), bucket(ordinal(r[4]), cuts["n_chars"])]
        want[r[0], len((r[1] or "").encode()) + 1, None if r[1] is None else zlib.crc32(r[1].encode()), at] += 1
    assert Counter((r["doc_id"], r["size"], r["text_crc32"], r["curve"]) for r in got) == want
    line = sorted(got, key=lambda r: (r["shard"], r["slot"]))
    keys = [(r["curve"], r["doc_id"] is not None, r["doc_id"] or 0) for r in line]
    assert keys == sorted(keys)
    n = len(line)
    assert [r["shard"] for r in line] == [k * 5 // n for k in range(n)]


def components_of(link):
    up = list(range(len(link)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in zip(*np.nonzero(link)):
        up[root(a)] = root(b)
    return [root(x) for x in range(len(link))]


def test_neighbour_descent(spark):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(60, 16))
    vecs = [base[i % 60] + rng.normal(size=16) * 0.05 for i in range(150)] + [rng.normal(size=16) for _ in range(200)]
    data = [(i, [float(x) for x in v]) for i, v in enumerate(vecs)] + [(350, None), (351, [0.0] * 16), (352, [float("nan")] * 16), (353, [1.0, None] * 8), (354, [float(x) for x in vecs[0]])]
    df = spark.createDataFrame(data, "vec_id long, embedding array<double>")
    got = {r["vec_id"]: r for r in neardup.near_duplicates(df, block=16).collect()}
    good = [i for i, v in data if v is not None and None not in v and np.isfinite(v).all() and any(v)]
    m = np.array([data[i][1] for i in good])
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    link = m @ m.T >= 0.95
    np.fill_diagonal(link, False)
    truth, found = link.sum(1), np.array([got[i]["n_links"] for i in good])
    assert (found <= truth).all() and found.sum() >= 0.9 * truth.sum()
    assert found.tolist() == truth.tolist()
    group = components_of(link)
    least = {g: min(i for i, h in zip(good, group) if h == g) for g in group}
    assert [got[i]["component_id"] for i in good] == [least[g] for g in group]
    assert all(got[i]["n_links"] == 0 and got[i]["kept"] for i in (350, 351, 352, 353))
    assert got[354]["component_id"] == 0 and not got[354]["kept"]
    assert neardup.near_duplicates(df.limit(0)).count() == 0


def test_neighbour_descent_links_groups_wider_than_lists(spark):
    # two tight groups that meet at 0.95 to 0.98: the lists of every member hold its own group only
    rng = np.random.default_rng(5)
    ends = np.eye(32)[0], np.cos(0.28) * np.eye(32)[0] + np.sin(0.28) * np.eye(32)[1]
    m = np.array([e + rng.normal(size=32) * 0.008 for e in ends for _ in range(30)])
    s = (m / np.linalg.norm(m, axis=1, keepdims=True)) @ (m / np.linalg.norm(m, axis=1, keepdims=True)).T
    cross = np.argsort(-s, axis=1)[:, :9] // 30 != np.arange(60)[:, None] // 30
    assert not cross.any() and (s[:30, 30:] >= 0.95).any()
    df = spark.createDataFrame([(i, [float(x) for x in v]) for i, v in enumerate(m)], "vec_id long, embedding array<double>")
    got = {r["vec_id"]: r for r in neardup.near_duplicates(df, block=16).collect()}
    assert [got[i]["n_links"] for i in range(60)] == ((s >= 0.95).sum(1) - 1).tolist()
    assert {r["component_id"] for r in got.values()} == {0} and sum(r["kept"] for r in got.values()) == 1


def test_neighbour_descent_adds_trees_until_the_audit_passes(spark, caplog):
    # pairs far apart from each other, and a start of one tree with windows of two rows, which misses most of them
    rng = np.random.default_rng(9)
    base = rng.normal(size=(300, 16))
    data = [(i, [float(x) for x in base[i % 300] + rng.normal(size=16) * 0.1]) for i in range(600)]
    m = np.array([v for _, v in data])
    m /= np.linalg.norm(m, axis=1, keepdims=True)
    df = spark.createDataFrame(data, "vec_id long, embedding array<double>")
    with caplog.at_level("INFO", neardup.__name__):
        got = {r["vec_id"]: r["n_links"] for r in neardup.near_duplicates(df, k=2, window=2, trees=1, sample=600).collect()}
    truth = (m @ m.T >= 0.95).sum(1) - 1
    audits = [r.args[1] for r in caplog.records if "recall" in r.msg]
    assert audits[0] < 0.99 <= audits[-1]
    assert sum(min(t, got[i]) for i, t in enumerate(truth)) >= 0.99 * truth.sum()


def test_saturated_lists_are_enlarged(spark):
    # a group wider than the lists: every list of 4 is saturated, and some of its vectors reach over to others
    rng = np.random.default_rng(15)
    m = np.concatenate([rng.normal(size=24) + rng.normal(size=(40, 24)) * 0.02, rng.normal(size=(60, 24))])
    vecs = spark.createDataFrame([(i, v.astype("<f8").tobytes()) for i, v in enumerate(m)], "id long, vec binary")
    lists = spark.createDataFrame([(i, [(float(m[i] @ m[j] / np.linalg.norm(m[i]) / np.linalg.norm(m[j])), j) for j in range(i // 40 * 40, i // 40 * 40 + 6) if j != i]) for i in range(40)], neardup.LISTS)
    scratch = neardup.Scratch(spark, "test")
    got = neardup.settled(lists, vecs, 100, 4, 0.0, "<f8", 64, 4, scratch, 0.95, 16)
    sizes = {r["id"]: len(r["near"]) for r in got.collect()}
    assert all(sizes[i] == 16 for i in range(40))


def test_neighbour_descent_with_clashing_columns(spark):
    rows = [(1, [1.0, 0.0], 5, "x", b"y"), (2, [1.0, 0.01], 5, None, b"y"), (3, None, None, "x", None)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, id long, rep string, vec binary")
    got = neardup.near_duplicates(df).collect()
    assert sorted((r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in got) == [(1, 1, 1, True), (2, 1, 1, False), (3, 0, 3, True)]


def test_neighbour_descent_where_ids_repeat(spark):
    a, b, c = np.eye(4).tolist()[:3]
    rows = [(None, a), (None, b), (7, a), (7, c), (8, c), (9, b), (None, None)]
    got = neardup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    want = [(None, 1, None), (None, 1, None), (7, 1, None), (7, 1, 7), (8, 1, 7), (9, 1, None), (None, 0, None)]
    assert Counter((r["vec_id"], r["n_links"], r["component_id"]) for r in got) == Counter(want)


def test_language(spark):
    rng = random.Random(3)
    alphabets = {"aa": "abcdefg", "bb": "hijklmn", "cc": "opqrstu"}
    rows = [(i, " ".join("".join(rng.choice(alphabets[k]) for _ in range(5)) for _ in range(40)), k) for i in range(300) for k in [rng.choice(list(alphabets))]]
    rows += [(900, None, "aa"), (901, "", "aa"), (902, "12 34 !!", "bb")]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r["doc_id"]: r for r in langid.identify(df, langid.train(df), ["doc_id"]).collect()}
    held = [r for r in rows[:300] if zlib.crc32(str(r[0]).encode()) % 4 == 2]
    assert np.mean([got[i]["lang_pred"] == k for i, _, k in held]) > 0.95
    assert all(got[i]["lang_pred"] == "und" and got[i]["score"] == 0 for i in (900, 901, 902))
    assert langid.train(df.limit(0)) is None
    assert langid.identify(df.limit(5), None, ["doc_id"]).filter("lang_pred <> 'und'").count() == 0


def test_byte_network_gradient():
    rng = np.random.default_rng(0)
    net = langid.ByteNet(["a", "b"], 1)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    x, y = rng.integers(97, 103, (4, 20)).astype(np.uint8), np.array([0, 1, 1, 0])
    _, g = net.step(x, y)
    for k in net.p:
        at = tuple(rng.integers(s) for s in net.p[k].shape) if k != "e" else (int(x[0, 3]), 2)
        old = net.p[k][at]
        losses = []
        for d in (1e-5, -1e-5):
            net.p[k][at] = old + d
            losses.append(net.step(x, y)[0])
        net.p[k][at] = old
        assert abs((losses[0] - losses[1]) / 2e-5 - g[k][at]) < 1e-4, k


def test_prediction_equals_plain_convolution():
    rng = np.random.default_rng(3)
    net = langid.ByteNet(["a", "b", "c"], 4).tables()
    x = rng.integers(32, 128, (7, 64)).astype(np.uint8)
    want = []
    for row in x:
        e, pooled = net.p["e"][row].astype(np.float64), []
        for w in langid.WIDTHS:
            z = [[sum(e[t + j] @ net.p[f"w{w}"][j][:, f] for j in range(w)) + net.p[f"b{w}"][f] for f in range(langid.FILTERS)] for t in range(64 - w + 1)]
            pooled += [max(0, v) for v in np.max(z, 0)]
        z = np.array(pooled) @ net.p["o"] + net.p["c"]
        want.append(np.exp(z) / np.exp(z).sum())
    assert np.abs(net.predict(x) - np.array(want)).max() < 1e-4


def test_language_of_many_labels_repeated_and_missing_ids(spark):
    # 70 languages, one of which holds most rows, under one id or none
    alphabet = [chr(0x4E00 + 40 * k) + chr(0x4E01 + 40 * k) for k in range(70)]
    rows = [(None if k % 2 else 6, " ".join(rng.choice(alphabet[k]) * 3 for _ in range(60)), f"l{k}", "z") for rng in [random.Random(4)] for k in range(70) for _ in range(3 if k else 300)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, lang_pred string").repartition(3)
    net = langid.train(df, texts=700)
    assert len(net.labels) == 70
    got = langid.identify(df, net, ["doc_id"]).collect()
    assert Counter(r["doc_id"] for r in got) == Counter(r[0] for r in rows) and all(0 <= r["score"] <= 1 for r in got)
    assert langid.identify(df.limit(0), net, ["doc_id"]).count() == 0


def removed(texts):
    seen = Counter(t[p : p + 200] for t in texts for p in range(len(t) - 199))
    out = []
    for t in texts:
        mark = bytearray(len(t))
        for p in range(len(t) - 199):
            if seen[t[p : p + 200]] > 1:
                mark[p : p + 200] = b"\1" * 200
        spans = sum(1 for j, v in enumerate(mark) if v and (j == 0 or not mark[j - 1]))
        out.append((len(t), sum(mark), spans, hashlib.sha256(bytes(c for c, v in zip(t, mark) if not v)).hexdigest()))
    return out


@pytest.mark.parametrize("most", [32, 1])
def test_suffix_removal(docs, rows, empty, most):
    got = suffix.remove_repeats(docs, local_most=most, shard_most=2 * most).collect()
    want = removed([(r[1] or "").encode() for r in rows])
    assert Counter((r["doc_id"], r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got) == Counter((r[0], *w) for r, w in zip(rows, want))
    if most == 1:
        assert suffix.remove_repeats(empty).count() == 0


def test_suffix_array_and_prefixes():
    rng = np.random.default_rng(4)
    for _ in range(20):
        data = rng.integers(97, 99, rng.integers(1, 300)).astype(np.uint8)
        text = data.tobytes()
        sa = suffix.suffix_array(data, 1000)
        assert sa.tolist() == sorted(range(len(text)), key=lambda i: text[i:])
        lcp = suffix.common_prefixes(data, sa, 400)
        for i in range(1, len(sa)):
            a, b = text[sa[i] :], text[sa[i - 1] :]
            n = next((k for k, (x, y) in enumerate(zip(a, b)) if x != y), min(len(a), len(b)))
            assert lcp[i] == n


def test_prefixes_behind_a_rare_differing_byte():
    # the differing bytes 1 and 2 stand once each, at the border of their values: prefix 0 there, hundreds behind it
    rng = np.random.default_rng(6)
    tail = rng.integers(97, 123, 500).astype(np.uint8).tobytes()
    text = b"1" + tail + b"~" + b"2" + tail
    data = np.frombuffer(text, np.uint8)
    sa = suffix.suffix_array(data, 200)
    assert suffix.common_prefixes(data, sa, 600)[sa.tolist().index(503)] == 500
    marked, _ = suffix.repeated_windows([b"1" + tail, b"2" + tail], [302, 302], [1, 1], 200)
    assert [m.tolist() for m in marked] == [[False] + [True] * 301] * 2


def test_contamination(spark, docs, rows, empty):
    items = [("a", " ".join(rows[3][1].split()[:14]) if len(rows[3][1].split()) > 14 else rows[3][1]), ("b", "nothing of this kind"), ("c", None), ("d", rows[0][1].upper())]
    bench = spark.createDataFrame(items, "item_id string, text string")
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    windows = {}
    for i, t in items:
        w = word.findall((t or "").lower())
        for k in range(max(1, len(w) - 9) if w else 0):
            windows.setdefault(tuple(w[k : k + 10]), set()).add(i)
    want = Counter()
    for r in rows:
        w = word.findall((r[1] or "").lower())
        hit, found = set(), set()
        for win, ids in windows.items():
            for k in range(len(w) - len(win) + 1):
                if tuple(w[k : k + len(win)]) == win:
                    hit.update(range(k, k + len(win)))
                    found |= ids
        want[r[0], len(w), len(hit), tuple(sorted(found))] += 1
    for block in (4 << 20, 1):  # one pass, and one for each item
        got = decontam.contamination(docs, bench, block_bytes=block).collect()
        assert Counter((r["doc_id"], r["n_words"], r["n_hit"], tuple(r["items"])) for r in got) == want
        clean = decontam.without_benchmark(docs, bench, block_bytes=block)
        assert clean.columns == docs.columns and Counter(r["doc_id"] for r in clean.collect()) == Counter(k[0] for k in want.elements() if not k[2])
    assert decontam.contamination(empty, bench).count() == decontam.without_benchmark(empty, bench).count() == 0
    assert decontam.contamination(docs, bench.limit(0)).filter("n_hit > 0").count() == 0


def test_contamination_of_items_that_repeat_or_lack_an_id(spark):
    docs = spark.createDataFrame([(1, "One two three four"), (None, "x five SIX"), (None, "five six"), (2, None)], "doc_id long, text string")
    bench = spark.createDataFrame([("b", "one two"), ("b", "four"), (None, "five six"), (None, None), ("c", "")], "item_id string, text string")
    got = decontam.contamination(docs, bench).collect()
    assert Counter((r["doc_id"], r["n_words"], r["n_hit"], tuple(r["items"])) for r in got) == Counter([(1, 4, 3, ("b",)), (None, 3, 2, ()), (None, 2, 2, ()), (2, 0, 0, ())])


def test_proximity(spark):
    rng = random.Random(12)
    vocabulary = [f"w{k}" for k in range(12)]
    texts = [(i, " ".join(rng.choice(vocabulary) for _ in range(rng.randint(0, 60)))) for i in range(40)] + [(90, None), (None, "")]
    items = [("a", "w1 w2 w3 w4"), ("b", "w5 w5 w6"), ("c", "w7 w8 w9 w10 w11"), ("d", "w0 zzz w1"), ("e", None)]
    span, want = 7, set()
    for doc, text in texts:
        words = (text or "").split()
        for item, t in items:
            w = (t or "").split()
            for window in [set(w[k : k + 4]) for k in range(max(1, len(w) - 3))] if w else []:
                covers = [at for at in range(len(words)) if window <= set(words[at : at + span])]
                if covers:
                    want.add((doc, item, covers[0]))
    least = {}
    for doc, item, at in want:
        least[doc, item] = min(least.get((doc, item), at), at)
    bench = spark.createDataFrame(items, "item_id string, text string")
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    for block in (4 << 20, 1):
        got = decontam.proximity(docs, bench, 4, span, block).collect()
        assert {(r["doc_id"], r["item_id"]): r["place"] for r in got} == least and len(got) == len(least)


def plain_spans(t):
    out = [(m.start(), 0, m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [(m.start(), 1, m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in m.group().split("."))]
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        g = re.sub("[^0-9]", "", m.group())
        if 12 <= len(g) <= 19 and pii.luhn(g):
            out.append((m.start(), 2, m.end()))
    out += [(m.start(), 3, m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m.group())) <= 15]
    return sorted(out)


def test_base_patterns():
    rng = random.Random(5)
    for _ in range(5000):
        s = "".join(rng.choice("ab@.1259+ -%_()é") for _ in range(rng.randint(0, 40)))
        assert pii.base_spans(s) == plain_spans(s)


def test_field(spark, empty):
    rng = random.Random(6)
    texts = [f"{prose(rng, 5)} password={rng.getrandbits(64):016x} {prose(rng, 3)} version 2.0 of {prose(rng, 2)} a.b{i}@mail.example.com" for i in range(120)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(900, None), (901, ""), (902, "9" * 50_000)], "doc_id long, text string")
    field = pii.train(df)
    got = {r["doc_id"]: r for r in pii.find(df, field).collect()}
    assert all(got[i]["n_email"] == 1 and "secret:" in got[i]["spans"] for i in range(120))
    assert all("2.0" not in texts[i][int(s.split(":")[1]) : int(s.split(":")[2])] for i in range(120) for s in got[i]["spans"].split(","))
    assert all(got[i]["spans"] == "" for i in (900, 901, 902))
    assert pii.redact("x a@b.c y", [(2, 0, 7)]) == "x [EMAIL] y"
    assert pii.find(empty, pii.train(empty)).count() == 0


def test_marginals_of_a_tree_are_exact():
    from itertools import product

    rng = np.random.default_rng(8)
    field = pii.Field()
    field.pair = [rng.normal(size=(pii.LABELS, pii.LABELS)) for _ in range(2)]
    edges = [np.array([[0, 1], [2, 3]]), np.array([[1, 3], [3, 4]])]  # chain and skip edges without a loop
    scores = rng.normal(size=(5, pii.LABELS))
    node, joint, kind = field.beliefs(scores, edges, 1e-9)
    every = np.array(list(product(range(pii.LABELS), repeat=5)))
    weight = sum(scores[i][every[:, i]] for i in range(5)) + sum(field.pair[k][every[:, a], every[:, b]] for k, own in enumerate(edges) for a, b in own)
    weight = np.exp(weight - weight.max())
    want = np.array([[weight[every[:, i] == v].sum() for v in range(pii.LABELS)] for i in range(5)]) / weight.sum()
    assert np.abs(node - want).max() < 1e-6
    pair = np.array([[weight[(every[:, 1] == u) & (every[:, 3] == v)].sum() for v in range(pii.LABELS)] for u in range(pii.LABELS)]) / weight.sum()
    assert np.abs(joint[2] - pair).max() < 1e-6 and kind.tolist() == [0, 0, 1, 1]


def test_secrets_of_letters_alone_and_their_repeats(spark):
    rng = random.Random(16)
    letters = lambda n: "".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(n))
    texts = [f"{prose(rng, 6)} password: {w} {prose(rng, 30)} then {w} {prose(rng, 4)}" for w in [letters(14) for _ in range(80)]]
    clean = [f"{prose(rng, 12)} token of esteem: {prose(rng, 9)}" for _ in range(40)]
    df = spark.createDataFrame(list(enumerate(texts + clean)), "doc_id long, text string")
    got = {r["doc_id"]: r["spans"] for r in pii.find(df, pii.train(df)).collect()}
    for i, text in enumerate(texts):
        word = text.split("password: ")[1].split()[0]
        assert [text[int(a) : int(b)] for _, a, b in (s.split(":") for s in got[i].split(","))] == [word, word]
    assert all(got[80 + i] == "" for i in range(40))


def test_personal_data_in_very_long_texts_and_repeated_rows(spark):
    filler = "ordinary words without anything " * 40_000
    text = filler + "write to a.b@c.example.com now " + filler + "call +49 30 123456-78 " + filler
    rows = [(1, text, 7), (1, text, 7), (None, text, None), (2, "x" * 200_000 + "@", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_email long")
    got = pii.find(df, pii.train(df, sample_bytes=1 << 20)).collect()
    assert Counter((r["doc_id"], r["n_email"], r["n_phone"]) for r in got) == Counter([(1, 1, 1), (1, 1, 1), (None, 1, 1), (2, 0, 0)])
    assert len({r["spans"] for r in got if r["doc_id"] != 2}) == 1


def test_section_tokens(docs, rows, empty):
    import public_tokenizers as public

    path = str(public.path("byte_bpe_50k.tiktoken"))
    for rule in ("start", "most"):
        got = tokencount.section_tokens(docs, path, public.PATTERN, rule).collect()
        assert len(got) == len(rows) and all(sum(r["section_tokens"]) == r["n_tokens"] for r in got)
    assert tokencount.section_tokens(empty, path, public.PATTERN).count() == 0
    ends, starts = np.array([3, 8]), np.array([0, 5])
    assert tokencount.allocate(ends, starts, 8, "start")[0].tolist() == [2, 0]
    assert tokencount.allocate(ends, starts, 8, "most")[0].tolist() == [1, 1]
    assert tokencount.allocate(ends, starts, 8, "share")[0].tolist() == [1.4, 0.6]


@pytest.mark.parametrize("rule", ["start", "most", "share"])
def test_section_tokens_against_plain_python(spark, rule):
    import public_tokenizers as public

    path = str(public.path("byte_bpe_50k.tiktoken"))
    encoding, sizes = tokencount.load(path, public.PATTERN)
    rng = random.Random(13)
    texts = ["".join(rng.choice(["word", " ", "\n", "\n\n", "é", "12", "\t", "日本", "  \n "]) for _ in range(rng.randint(0, 60))) for _ in range(60)]

    def plain(text, borders):
        ends = np.cumsum([sizes[t] for t in encoding.encode(text, allowed_special="all")]).astype(int).tolist()
        spans, out = list(zip(borders, [*borders[1:], len(text.encode())])), [0.0] * len(borders)
        for a, b in zip([0, *ends], ends):
            share = [max(0, min(b, q) - max(a, p)) / (b - a) for p, q in spans]
            if rule == "share":
                out = [x + y for x, y in zip(out, share)]
            else:
                out[next(k for k, y in enumerate(share) if y) if rule == "start" else share.index(max(share))] += 1
        return out

    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    got = {r["doc_id"]: r["section_tokens"] for r in tokencount.section_tokens(df, path, public.PATTERN, rule).collect()}
    for i, t in enumerate(texts):
        lines = t.encode().split(b"\n")
        borders = [0]
        for line in lines[:-1]:
            borders.append(borders[-1] + len(line) + 1)
        borders = [b for b in borders if b < len(t.encode())]
        assert np.allclose(got[i], plain(t, borders)), t
    # given sections, and fields that are encoded as one text
    given = spark.createDataFrame([(1, "héllo wörld again", [0, 3, 8]), (2, "x", [0]), (3, None, [0]), (4, "abc", None)], "doc_id long, text string, at array<int>")
    own = {r["doc_id"]: r["section_tokens"] for r in tokencount.section_tokens(given, path, public.PATTERN, rule, "at").collect()}
    assert np.allclose(own[1], plain("héllo wörld again", [0, 4, 10])) and own[3] == [] and len(own[4]) == 1
    fields = spark.createDataFrame([(1, "a title", None, "some body\ntext"), (2, "", "x", "")], "doc_id long, title string, note string, body string")
    by = {r["doc_id"]: r for r in tokencount.field_tokens(fields, ["title", "note", "body"], path, public.PATTERN, rule).collect()}
    whole = "a title\n\nsome body\ntext"
    assert np.allclose([by[1]["fields"][f] for f in ("title", "note", "body")], plain(whole, [0, 8, 9]))
    assert by[1]["n_tokens"] == len(encoding.encode(whole)) and sum(by[2]["fields"].values()) == by[2]["n_tokens"]


def test_best_fit_choice():
    rng = random.Random(14)
    fit, bins, numbers = packing.BestFit(50, 6), [], 0
    for _ in range(3000):
        n = rng.randint(1, 50)
        fitting = [b for b in bins if b[1] >= n]
        number, offset = fit.add(n)
        if fitting:
            free = min(b[1] for b in fitting)
            chosen = next(b for b in bins if b[0] == number)
            assert chosen[1] == free
        else:
            if len(bins) >= 6:
                least = min(b[1] for b in bins)
                gone = [b for b in bins if b[1] == least and b[0] not in fit.open_numbers()]
                bins.remove(gone[0])
            chosen, numbers = [numbers, 50], numbers + 1
            bins.append(chosen)
        assert number == chosen[0] and offset == 50 - chosen[1]
        chosen[1] -= n
        if not chosen[1]:
            bins.remove(chosen)
        assert {b[0] for b in bins} == fit.open_numbers()


def test_packing(docs, rows, empty):
    from tokenizers import Tokenizer

    path = packing.tokenizer_path()
    plain = Tokenizer.from_file(path)
    got = packing.best_fit(docs, path, capacity=128, open_bins=4).collect()
    want = Counter()
    for r in rows:
        ids = np.array(plain.encode(r[1] or "", add_special_tokens=False).ids + [0], "<u4")
        for k in range(0, len(ids), 128):
            want[r[0], k // 128, k, len(ids[k : k + 128]), zlib.crc32(ids[k : k + 128].tobytes())] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == want
    bins = {}
    for r in got:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for own in bins.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= 128
    assert packing.best_fit(empty, path).count() == 0


def test_word_tokenizer_equals_whole_texts():
    tk = packing.WordTokenizer(packing.tokenizer_path())
    texts = ["Don't DO it's... x.y, z!! <|ENDOFTEXT|> a", "<|endoftext|> b.", "é\u0301. x\u0301. É! 12.5, İ. ß. STRASSE 're. foo'. bar's", "", "  ", "日本語。テスト, ǅ. ﬁ. ①2."]
    got = tk(pa.array(texts))
    assert [g.tolist() for g in got] == [e.ids for e in tk.tokenizer.encode_batch(texts, add_special_tokens=False)]


def test_main_text(spark):
    page = lambda body: f"<html><head><title>t</title><script>var a='</p>';</script></head><body><nav><ul><li><a href=x>menu</a></li></ul></nav><div class='ad'>buy</div><article><h1>Head &amp; more</h1><p>{body}<p>second  one</article><footer>&copy; x</footer></body></html>"
    rng = random.Random(7)
    bodies = [prose(rng, 20) for _ in range(40)]
    df = spark.createDataFrame([(i, "u", page(b)) for i, b in enumerate(bodies)] + [(90, "u", None), (91, "u", ""), (92, "u", "<p><b")], "page_id long, url string, html string")
    got = {r["page_id"]: r for r in html.main_text(df, html.train(df)).collect()}
    assert all(got[i]["text"] == f"Head & more\n\n{b}\n\nsecond one" and got[i]["n_chars"] == len(got[i]["text"]) for i, b in enumerate(bodies))
    assert got[90]["text"] == got[91]["text"] == got[92]["text"] == ""


LABELLED = [
    ("<article><h1>Head</h1><p>one &lt;two&gt;\n three</p></article>", ["Head", "one <two> three"]),
    ("<div class='content'><h2>Head</h2><svg class='i'/><p>one</p><template-part></template-part><p>two</p></div>", ["Head", "one", "two"]),
    ("<main><h1>Head</h1><p>one</p><select><p>two</p></main>", ["Head", "one", "two"]),
    ("<article><h1>Head</h1><p>one</p><noscript>no</noscript><p>two<p>three<ul><li>four<li>five</ul></article>", ["Head", "one", "two", "three", "four", "five"]),
    ("<article><h1>Head</h1><p>one</p><aside class='sidebar'><p>other</p></aside><p>two</p></article>", ["Head", "one", "two"]),
    ("<article><h1>Head</h1><p>one <b>bold</b> <a href=x>link</a>.</p><table><tr><td>cell</td></tr></table></article>", ["Head", "one bold link.", "cell"]),
    ("<article><h1>Head</h1><p>one</p><form><label>mail</label><input></form><p>two</p></article><section class='comments'><div class='comment'>said</div></section>", ["Head", "one", "two"]),
    ("<div class='post'><h1>Head</h1>" + "<div>" * 300 + "<p>deep</p>" + "</div>" * 300 + "<p>after</p></div>", ["Head", "deep", "after"]),
    ("<article><h1>Head</h1><blockquote>quoted</blockquote><pre>code  here</pre><!-- <p>hidden</p> --><p>end</p></article>", ["Head", "quoted", "code here", "end"]),
    ("<article><h1>Head</h1><p>one<script>var a = '<p>x</p>';</script></p><style>p {}</style><object-view>two</object-view></article>", ["Head", "one", "two"]),
]


# each word stands for a sentence like those of the training pages
LABELLED = [tuple(json.loads(re.sub(r"\b(one|two|three|four|five|deep|after|end|other|said|bold|cell|quoted)\b", lambda m: prose(random.Random(m.group()), 8), json.dumps(v))) for v in row) for row in LABELLED]


def test_labelled_pages(spark):
    rng = random.Random(17)
    around = lambda main, n: f"<html><head><title>t{n}</title></head><body><header class='site'><nav><ul><li><a href=x>home</a><li><a href=y>news</a></ul></nav></header><div class='cookie-notice'><p>we use cookies {n}</p></div>{main}<div class='ad'>buy {n}</div><aside><ul><li><a href=z>related {n}</a></ul></aside><footer><p>&copy; {n} all rights</p></footer></body></html>"
    train = spark.createDataFrame([(i, "u", around(f"<article><h1>{prose(rng, 4)}</h1>" + "".join(f"<p>{prose(rng, rng.randint(5, 30))}.</p>" for _ in range(rng.randint(1, 6))) + "</article>", i)) for i in range(120)], "page_id long, url string, html string")
    net = html.train(train)
    rows = [(i, "u", around(page, i), "clash", -1) for i, (page, _) in enumerate(LABELLED)]
    rows += [rows[0], (None, None, rows[1][2], None, None), (99, "u", None, None, None), (99, "u", "", None, None)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, text string, n_chars long")
    got = html.main_text(df, net).collect()
    want = Counter((i, "\n\n".join(blocks)) for i, (_, blocks) in enumerate(LABELLED))
    want.update([(0, "\n\n".join(LABELLED[0][1])), (None, "\n\n".join(LABELLED[1][1])), (99, ""), (99, "")])
    assert Counter((r["page_id"], r["text"]) for r in got) == want
    assert all(r["n_chars"] == len(r["text"]) for r in got)
    assert html.main_text(df.limit(0), html.train(df.limit(0))).count() == 0


def test_blocks_behind_empty_and_custom_elements():
    texts = lambda page: [b[1] for b in html.blocks_of(page)]
    for part in ("<svg class='i'/>", "<svg-icon></svg-icon>", "<template-part/>", "<select-box>", "<object-view>", "<iframe src='x'/>", "<canvas />", "<object>", "<svg title='a>b'>x</svg>"):
        assert texts(f"<p>a</p>{part}<p>article</p>") == ["a", "article"], part
    for part in ("<script>x", "<style>x", "<title>x", "<textarea>x"):
        assert texts(f"<p>a</p>{part}<p>b</p>") == ["a"], part
    assert texts("<p>a</p><svg><text>x</text></svg ><template>y</template><p>b</p>") == ["a", "b"]
    # closing tags of elements below the depth of 256 close no outer ones
    page = "<article class=outer>" + "<div>" * 300 + "x" + "</div>" * 300 + "<p>y</p></article>z"
    assert [(b[1], b[0][:2]) for b in html.blocks_of(page)] == [("x", ("article", "class:outer")), ("y", ("article", "class:outer")), ("z", ())]
    page = "<section class=outer>" + "<b>" * 260 + "<section>x</section>y</section>z"
    assert [(b[1], b[0][:1]) for b in html.blocks_of(page)] == [("x", ("section",)), ("y", ("section",)), ("z", ())]


def jaccard(rows, width=4, percent=85):
    sets, up = [], list(range(len(rows)))
    for r in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (r[1] or "").lower())
        sets.append(set() if not w else {tuple(w)} if len(w) < width else {tuple(w[k : k + width]) for k in range(len(w) - width + 1)})

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b]:
                n = len(sets[a] & sets[b])
                if 100 * n >= percent * (len(sets[a]) + len(sets[b]) - n):
                    up[root(a)] = root(b)
    groups = {}
    for k in range(len(rows)):
        groups.setdefault(root(k), []).append(rows[k][0])
    low = {g: min(v, key=lambda x: (x is not None, x)) for g, v in groups.items()}
    return Counter((rows[k][0], len(sets[k]), low[root(k)]) for k in range(len(rows)))


@pytest.mark.parametrize("small", [16, 2])
def test_set_join(spark, rows, empty, small):
    rng = random.Random(8)
    base = [rng.choice(WORDS) + str(rng.randint(0, 300)) for _ in range(120)]
    near = []
    for i in range(60):
        own = list(base)
        for _ in range(rng.randint(0, 8)):
            own[rng.randrange(120)] = "z" + str(rng.randint(0, 10**6))
        near.append((100 + i, " ".join(own), "en", "s", 1, "x"))
    every = rows + near
    got = setjoin.jaccard_classes(spark.createDataFrame(every, SCHEMA).repartition(4), small=small, block=16).collect()
    assert Counter((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got) == jaccard(every)
    if small == 2:
        assert setjoin.jaccard_classes(empty).count() == 0
        assert setjoin.one_of_each(empty).count() == 0


def test_set_join_by_text_where_ids_repeat(spark):
    rng = random.Random(10)
    one, two, three = (prose(rng, 80) for _ in range(3))
    every = [(None, one, "en", "s", 1, "x"), (None, two, None, "s", 1, "x"), (-1, one + " more", "en", None, None, "x"), (5, two, "en", "s", 1, "x"), (5, three, "en", "s", 1, "x"), (6, three + " tail", "en", "s", 1, "x"), (None, None, "en", "s", 1, "x"), (None, " ", "en", "s", 1, "x")]
    df = spark.createDataFrame(every * 2, SCHEMA).repartition(3)
    got = setjoin.jaccard_classes(df).collect()
    want = {(None, one): None, (None, two): None, (-1, one + " more"): None, (5, two): None, (5, three): 5, (6, three + " tail"): 5}
    assert Counter((r["doc_id"], r["component_id"]) for r in got if r["n_shingles"]) == Counter([(k[0], v) for k, v in want.items()] * 2)
    kept = setjoin.one_of_each(df)
    assert kept.columns == df.columns
    assert Counter((r["doc_id"], r["text"]) for r in kept.collect()) == Counter([(None, one), (None, two), (5, three)] + [(None, None), (None, " ")] * 2)


def test_pipeline_stages(spark, rows, tmp_path):
    rng = random.Random(9)
    item = prose(rng, 30)
    own = [r[:5] for r in rows if r[0] is not None] + [(200, prose(rng, 9) + " " + item, "en", "s", 1), (201, "no letters 12".replace("no letters ", ""), "en", "s", 2), (202, prose(rng, 30) + " a.b@c.example.com", "en", "s", 3)]
    spark.createDataFrame(own, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([("i", item)], "item_id string, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    seen = {}
    for name, stage in corpus_pipeline.STAGES[:4]:
        docs = corpus_pipeline.Scratch(spark, "test").table(name, stage(spark, docs, str(tmp_path)))
        assert docs.columns == list(corpus_pipeline.COLUMNS)
        seen[name] = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert 201 not in seen["language"] and 41 not in seen["language"] and 0 in seen["language"]
    kept = [r for r in own if r[0] in seen["language"]]
    assert set(seen["near_duplicates"]) == {c for _, _, c in jaccard(kept)}
    assert 200 not in seen["benchmark"] and len(seen["benchmark"]) == len(seen["near_duplicates"]) - 1
    assert seen["personal_data"][202].endswith("[EMAIL]")
    pieces = corpus_pipeline.pack(spark, docs, str(tmp_path))
    assert {r["doc_id"] for r in pieces.collect()} == set(seen["personal_data"])


def test_pipeline_stages_on_empty_and_odd_tables(spark, tmp_path):
    """Nulls in every column, rows without an id, repeated rows, an empty table, clashing column names."""
    rng = random.Random(18)
    texts = [prose(rng, 40) for _ in range(6)]
    odd = [(None, None, None, None, None, 1, "a"), (None, texts[0], None, None, None, 1, None), (None, texts[1], "en", "s", 3, 1, "a"), (1, texts[0], "en", "s", None, 1, "a"), (1, texts[0], "en", "s", None, 1, "a"), (2, "", "en", "s", 0, 1, "a"), (3, texts[2] + " x@y.example.org", "en", None, 3, 1, "a"), *((10 + i, t, "en", "s", 1, 2, "b") for i, t in enumerate(texts[3:]))]
    kind = "doc_id long, text string, lang string, source string, n_chars long, shard int, component_id string"
    spark.createDataFrame([], "item_id string, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    for rows in (odd, []):
        docs = spark.createDataFrame(rows, kind)
        for name, stage in corpus_pipeline.STAGES:
            docs = corpus_pipeline.Scratch(spark, "test").table(name, stage(spark, docs, str(tmp_path)))
            if name != "packing":
                assert docs.columns == list(corpus_pipeline.COLUMNS), name
                docs = docs.withColumns({"shard": F.lit(1), "component_id": F.lit("z")})
            if name == "near_duplicates" and rows:
                assert Counter(r["text"] for r in docs.collect()) == Counter(t for t in {r[1] for r in odd} if t)
        assert (docs.count() > 0) == bool(rows)


def test_components_of_a_long_chain(spark):
    from intervalrules.llm import graph

    n = 300
    order = random.Random(19).sample(range(n), n)
    edges = spark.createDataFrame([(order[k], order[k + 1]) for k in range(n - 1)] + [(1000, 1001)], "a long, b long")
    got = {r["id"]: r["component"] for r in graph.components(edges, neardup.Scratch(spark, "test")).collect()}
    assert got == {k: 0 for k in range(n)} | {1000: 1000, 1001: 1000}


def test_workers_give_memory_back():
    """What a function of batches leaves free does not stay with the worker."""
    import ctypes

    from intervalrules.llm.common import tidy

    def resident():
        with open("/proc/self/status") as f:
            return next(int(line.split()[1]) for line in f if line.startswith("VmRSS")) >> 10

    ctypes.CDLL(None).malloc_trim(0)
    before = resident()

    def run(batches):
        kept = []
        for batch in batches:
            small = [bytes(4000 + k % 50) for k in range(50_000)]  # small blocks, which the allocator keeps
            kept.append(bytes(100))  # one that lives on, behind them
            del small
            yield batch

    assert list(tidy(run)([1, 2])) == [1, 2]
    assert resident() - before < 60
