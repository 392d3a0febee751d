"""Training-data operators against brute force, round trips, oracles and held-out labels."""

import hashlib
import os
import random
import re
import sys
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(__file__)))
from parity import assert_same

from clipforge.llm import leak_windows, license_digests, line_spread, private_spans, quality_cnn, shingle_forest, source_mix, token_codes, toxicity
from clipforge.llm.leak_windows import drop_leaks, edit_distance, find_leaks, plain
from clipforge.llm.queries import ORACLES, QUERIES
from clipforge.operators.graph import connected
from clipforge.llm.shingle_forest import Forest, Shingler, _nodes, forest_ties, join_documents, keep_one, prefix_length
from clipforge.llm.vantage_trees import nearest, usable

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, rows, extra=""):
    return spark.createDataFrame([(i, t, "en", s, len(t) if t is not None else None) for i, t, s in rows], DOCS)


@pytest.fixture(scope="module")
def documents(spark, sf):
    return [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "source").collect()]


ODD = [(1, None, "a"), (2, "", None), (3, " \t\n ", "a"), (None, "one two", "b"), (5, "one two", "b"), (5, "one two", "b"), (6, "x" * 70_000, "a"), (7, "word " * 30_000, "c"), (8, "naïve — ÀÉÎ 日本 \U0001f600 'll", "a")]


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_oracles(spark, sf, duck, name):
    assert_same(QUERIES[name](spark, sf), duck, ORACLES[name])


# --- 1 -------------------------------------------------------------------------------------------

def brute_links(rows, threshold=0.8):
    cut = Shingler()
    sets = [set(cut(t).tolist()) for _, t, _ in rows]
    holders = defaultdict(list)
    for i, s in enumerate(sets):
        for x in s:
            holders[x].append(i)
    common = Counter()
    for h in holders.values():
        for a in range(len(h)):
            for b in range(a + 1, len(h)):
                common[h[a], h[b]] += 1
    links = {p for p, n in common.items() if n >= threshold * (len(sets[p[0]]) + len(sets[p[1]]) - n) - 1e-9}
    same = defaultdict(list)
    for i, (_, t, _) in enumerate(rows):
        same[t or ""].append(i)
    links |= {(h[a], h[b]) for h in same.values() for a in range(len(h)) for b in range(a + 1, len(h))}
    root = list(range(len(rows)))

    def find(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for a, b in links:
        root[find(a)] = find(b)
    n_links = Counter(x for p in links for x in p)
    least = {}
    for i, (d, _, _) in enumerate(rows):
        if d is not None:
            least[find(i)] = min(least.get(find(i), d), d)
    return Counter((d, least.get(find(i)), n_links[i]) for i, (d, _, _) in enumerate(rows))


def test_shingles_are_word_runs():
    cut = Shingler()
    assert len(cut("a b c d e f")) == 2 and len(cut("a b")) == 1 and len(cut("")) == len(cut(None)) == 0
    assert set(cut("A b\tc  D e\nf").tolist()) == set(cut("a b c d e f").tolist())
    words = [str(x) for x in np.random.default_rng(0).integers(0, 9, 400)]
    assert len(cut(" ".join(words))) == len({tuple(words[i:i + 5]) for i in range(396)})


def test_prefix_is_shortened_to_the_recall():
    d = prefix_length()
    assert 1 - (1 - 0.8 ** d) ** 24 >= 0.999 > 1 - (1 - 0.8 ** (d + 1)) ** 24
    assert prefix_length(recall=0.9) >= d


def near_copies(edits, groups=250, words=200, seed=6):
    """Pairs of texts, and the pairs' second ones with so many of their words changed."""
    rng, rows = random.Random(seed), []
    for g in range(groups):
        base = [f"w{rng.randrange(40_000)}" for _ in range(words)]
        other = list(base)
        for k in rng.sample(range(words), edits):
            other[k] = f"x{g}"
        rows += [(2 * g, " ".join(base), "s"), (2 * g + 1, " ".join(other), "s")]
    return rows


def test_paths_agree_as_often_as_texts_are_similar():
    cut, forest = Shingler(), Forest()
    a, b = (cut(t) for _, t, _ in near_copies(4, 1, 2000))
    j = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
    for x, y in ((a, b), (a[:300], b[:300])):
        j = len(np.intersect1d(x, y)) / len(np.union1d(x, y))
        same = np.mean(forest.paths(x).view(np.uint8) == forest.paths(y).view(np.uint8))
        assert abs(same - j) < 0.09


def test_forest_depth_follows_the_data(spark):
    depths = {}
    for edits in (1, 6):
        docs = docs_of(spark, near_copies(edits))
        ties, depths[edits] = forest_ties(_nodes(docs, 24, 5))
        assert ties.count() >= 200
    assert depths[1] == 8 and prefix_length() <= depths[6] < 8


@pytest.mark.parametrize("edits", [1, 2, 4])
def test_forest_recall(spark, edits):
    rows = near_copies(edits)
    want, got = brute_links(rows), Counter(tuple(r) for r in join_documents(docs_of(spark, rows)).collect())
    linked = sum(n for (_, _, k), n in want.items() if k)
    assert sum(n for (_, _, k), n in got.items() if k) >= 0.99 * linked and not got - want - Counter({r: n for r, n in got.items() if not r[2]})


def test_components_of_chains_stars_and_loops(spark):
    rng = random.Random(2)
    edges = [(i, i + 1) for i in range(0, 300)] + [(1000, 1001 + i) for i in range(300)] + [(5000, 5000)] + [(rng.randrange(2000, 2400), rng.randrange(2000, 2400)) for _ in range(150)]
    got = {r["node"]: r["label"] for r in connected(spark.createDataFrame(edges, "a long, b long")).collect()}
    root = {}

    def find(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        if a != b:
            root[find(a)] = find(b)
    want = {x: find(x) for x in root}
    assert set(got) == set(want)
    pairs = {(got[x], want[x]) for x in want}
    assert len(pairs) == len({a for a, _ in pairs}) == len({b for _, b in pairs})
    assert connected(spark.createDataFrame([], "a long, b long")).count() == 0


def test_join_matches_brute_force(spark, documents):
    rows = [(i, t, s) for i, t, s in documents if len(t) < 6000]
    got = Counter(tuple(r) for r in join_documents(docs_of(spark, rows)).collect())
    assert got == brute_links(rows)


def test_join_large_group_and_odd_rows(spark, monkeypatch):
    monkeypatch.setattr(shingle_forest, "BLOCK", 160)
    rng = random.Random(4)
    base = [f"w{rng.randrange(5000)}" for _ in range(300)]
    rows = []
    for i in range(420):  # more than two blocks of near copies
        words = list(base)
        words[rng.randrange(300)] = f"v{i}"
        rows.append((1000 + i, " ".join(words), "s"))
    rows += ODD[:6] + ODD[8:] + [(3000 + i, "same text in many rows of one table", "z") for i in range(50)]
    docs = docs_of(spark, rows)
    assert Counter(tuple(r) for r in join_documents(docs).collect()) == brute_links(rows)
    kept = keep_one(docs)
    assert kept.columns == docs.columns
    ids = [r["doc_id"] for r in kept.collect()]
    assert ids.count(1000) == 1 and sum(1000 <= (x or 0) < 1420 for x in ids) == 1 and ids.count(3000) == 1 and ids.count(5) == 1


# --- 2 -------------------------------------------------------------------------------------------

def test_license_forms(spark):
    mit = license_digests.KNOWN["MIT"]
    rows = [(1, f"Copyright (c) 2020 Someone\n\n{mit.upper()}", "a"), (2, mit.replace("sublicense", "sub-license").replace(", ", " ,\n"), "a"), (3, mit + " extra", "a"), (4, "text\nreleased under the mit licence\nmore", "a"), (5, None, None)]
    got = {r["doc_id"]: r for r in license_digests.scan_licenses(docs_of(spark, rows)).collect()}
    assert got[1]["license_id"] == got[2]["license_id"] == "MIT" and got[3]["license_id"] is None
    assert (got[4]["n_notices"], got[4]["notices"]) == (1, "MIT-notice") and (got[5]["n_notices"], got[5]["license_id"]) == (0, None)
    table_ = spark.createDataFrame(sorted(license_digests.KNOWN.items()), "license_id string, text string")
    assert {r["doc_id"]: r for r in license_digests.scan_licenses(docs_of(spark, rows), table_).collect()} == got


def test_licenses_match_however_they_are_wrapped(spark):
    import textwrap

    folder = "/usr/share/common-licenses"
    whole = {**license_digests.KNOWN, **{k: open(f"{folder}/{f}").read() for k, f in (("Apache-2.0", "Apache-2.0"), ("MPL-2.0", "MPL-2.0"), ("GPL-3.0", "GPL-3")) if os.path.exists(f"{folder}/{f}")}}
    rows, want = [], {}
    for k, text in whole.items():
        paragraphs: list = [[]]
        for line in text.split("\n"):
            if not line.strip() or re.match(license_digests.COPYRIGHT_LINE[4:], line.lower()) or k in license_digests.KNOWN:
                paragraphs += [[line], []]
            else:
                paragraphs[-1].append(line)
        paragraphs = [" ".join(" ".join(p).split()) for p in paragraphs]
        for width in range(50, 101):
            want[len(rows)] = k
            rows.append((len(rows), "Copyright (c) 2019-2024 A. Writer\n# Copyright 2020 B\n\n" + "\n".join(textwrap.fill(p, width) if "opyright (" not in p else p for p in paragraphs), "s"))
    got = {r["doc_id"]: r["license_id"] for r in license_digests.scan_licenses(docs_of(spark, rows)).collect()}
    assert [(i, want[i]) for i in want if got[i] != want[i]] == []


def test_license_oracle_on_odd_rows(spark):
    import duckdb

    texts = ["Copyright holders be liable", "  // copyright 2020 x", "(c) you must", "(C) 1999 y\nRELEASED under the MIT Licence", "© z", "copyright: 2001", "copyright (c) w", "Copyright [yyyy] q", None, "", "all rights\treserved", *[f"Copyright © 2001\n{t}" for t in license_digests.KNOWN.values()]]
    con = duckdb.connect()
    con.execute("create table documents(doc_id bigint, text varchar)")
    con.executemany("insert into documents values (?, ?)", list(enumerate(texts)))
    assert_same(license_digests.scan_licenses(docs_of(spark, [(i, t, "s") for i, t in enumerate(texts)])), con, license_digests.ORACLE)


def test_many_known_licenses_take_the_other_way(spark, monkeypatch):
    monkeypatch.setattr(license_digests, "MAX_BROADCAST", 2)
    monkeypatch.setattr(license_digests, "MAX_MAP", 2)
    rows = [(1, license_digests.KNOWN["ISC"], "a"), (2, "a\nAll rights reserved.\nAll Rights Reserved", "a")]
    got = {r["doc_id"]: r for r in license_digests.scan_licenses(docs_of(spark, rows)).collect()}
    assert got[1]["license_id"] == "ISC" and (got[2]["n_notices"], got[2]["notices"]) == (2, "All-rights-reserved")


# --- 3 -------------------------------------------------------------------------------------------

def brute_nearest(vectors, query_ids, k):
    ids = np.array(sorted(vectors))
    m = np.array([vectors[i] for i in ids], np.float64)
    out = {}
    for q in query_ids:
        s = (m * np.array(vectors[q], np.float64)).sum(1)
        order = [i for i in np.lexsort((ids, -s)) if ids[i] != q][:k]
        out[q] = [(int(ids[i]), float(s[i])) for i in order]
    return out


def test_nearest_exact_with_ties_and_odd_vectors(spark):
    rng = np.random.default_rng(2)
    vectors = {i: (rng.normal(size=8) * (1 + i % 5)).astype(np.float32).tolist() for i in range(400)}
    for i in range(0, 120):
        vectors[1000 + i] = vectors[20]
    odd = [(2000, None), (2001, [0.0] * 8), (2002, [float("nan")] * 8), (None, [1.0] * 8), (2004, [None] * 8), (2005, []), (2006, [float("inf")] * 8)]
    rows = usable(spark.createDataFrame([*vectors.items(), *odd], "vec_id long, embedding array<float>"))
    got = defaultdict(list)
    for r in nearest(rows, rows.filter("vec_id % 20 = 0"), k=20, relax=1.0, shard_rows=100, block_rows=8, least_rows=3).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    want = brute_nearest(vectors, [i for i in vectors if i % 20 == 0], 20)
    assert set(got) == set(want)
    for q in want:
        assert [x for x, _ in got[q]] == [x for x, _ in want[q]]
        assert np.allclose([s for _, s in got[q]], [s for _, s in want[q]], rtol=1e-12)


def test_nearest_recall_with_production_parameters(spark, sf):
    raw = {r["vec_id"]: r["embedding"] for r in spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet").collect()}
    got = defaultdict(set)
    for r in QUERIES["op3_vantage_trees"](spark, "/root/testdata/sf0.1").collect():
        got[r["query_id"]].add(r["vec_id"])
    want = brute_nearest(raw, [i for i in raw if i % 20 == 0], 20)
    assert np.mean([len(got[q] & {i for i, _ in w}) / 20 for q, w in want.items()]) >= 0.9


def test_nearest_empty(spark):
    rows = usable(spark.createDataFrame([], "vec_id long, embedding array<float>"))
    assert nearest(rows, rows).count() == 0


# --- 4, 5 ----------------------------------------------------------------------------------------

@pytest.mark.parametrize(("name", "label", "least"), [("op4_quality_cnn", "quality", 0.9), ("op5_toxicity", "toxic", 0.9)])
def test_classifiers_on_held_out_labels(spark, sf, name, label, least):
    out = QUERIES[name](spark, "/root/testdata/sf0.1")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    rows = out.join(labels, "doc_id").filter("held_out").select("predicted", label, "score", "doc_id").collect()
    assert all(0 <= r["score"] <= 1 and zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0 for r in rows)
    assert np.mean([r["predicted"] == r[label] for r in rows]) >= least


def test_toxicity_score_is_the_sum_over_characters(spark):
    rng = random.Random(3)
    words = ["über", "naïve", "日本語", "plain", "a", "ñandú", "\U0001f600"]
    texts = [" ".join(rng.choice(words) for _ in range(rng.randrange(0, 12))) for _ in range(60)]
    model = toxicity.fit(texts, [int("ñ" in t) for t in texts])
    scorer = toxicity.Scorer(model)

    def slot(gram):
        code = 0
        for c in gram:
            code = (code * 0x01000193 + (ord(c) + 1) * 0x9E3779B1) % (1 << 32)
        return (((code ^ (code >> 15)) * (0x85EBCA6B + 2 * len(gram))) % (1 << 32)) >> (32 - toxicity.BITS)

    for t in [*texts, "", "É", "ÀB"]:
        whole = f" {t.lower()} "
        slots = {slot(whole[i:i + n]) for n in toxicity.ORDERS for i in range(len(whole) - n + 1)}
        z = sum(float(scorer.weights[s]) for s in slots) + scorer.bias
        assert scorer(t) == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-9)
    assert np.mean([(scorer(t) >= 0.5) == ("ñ" in t) for t in texts]) > 0.95


def test_network_score_is_what_its_definition_says():
    rng = np.random.default_rng(4)
    net = quality_cnn.Network()
    for k in net.p:
        net.p[k] = rng.normal(0, 0.3, net.p[k].shape).astype(np.float32)
    for text in ("", "short", "é" * 300, "some words of a text " * 40):
        raw = [b + 1 for b in text.encode()]
        blocks = max(2, -(-len(raw) // quality_cnn.BLOCK))
        raw += [0] * (blocks * quality_cnn.BLOCK + quality_cnn.WIDTH - 1 - len(raw))
        peaks = [[max(sum(net.p["tables"][j, raw[i + j], f] for j in range(quality_cnn.WIDTH)) for i in range(b * quality_cnn.BLOCK, (b + 1) * quality_cnn.BLOCK)) for f in range(quality_cnn.FILTERS)] for b in range(blocks)]
        ratings = []
        for b in range(blocks - 1):
            a = np.maximum(np.maximum(peaks[b], peaks[b + 1]), 0)
            ratings.append(float(np.maximum(a @ net.p["w1"] + net.p["b1"], 0) @ net.p["w2"] + net.p["b2"][0]))
        z = np.dot([np.mean(ratings), max(ratings), min(ratings)], net.p["w3"]) + net.p["b3"][0]
        assert net.score(text) == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-4)


@pytest.mark.parametrize("module", [toxicity, quality_cnn])
def test_classifier_odd_rows(spark, module):
    docs = docs_of(spark, ODD)
    labels = spark.createDataFrame([(1, 1, 1), (2, 0, 0), (None, 1, 1), (5, None, None)], "doc_id long, quality int, toxic int")
    model = module.train(docs, labels)
    scores = [r["score"] for r in module.with_score(docs, model).collect()]
    assert len(scores) == len(ODD) and all(0 <= s <= 1 for s in scores)
    none = module.train(docs, labels.limit(0))
    assert module.with_score(docs.limit(0), none).count() == 0


def test_network_gradient_is_the_slope():
    rng = np.random.default_rng(0)
    net = quality_cnn.Network()
    for k in net.p:
        net.p[k] = rng.normal(0, 0.3, net.p[k].shape)
    data = quality_cnn._bytes("some text, some more text " * 30)
    grads = {k: np.zeros(v.shape) for k, v in net.p.items()}
    net.gradient(data, 1.0, grads)

    def loss():
        z = net.head(net.respond(data))["z"]
        return np.log1p(np.exp(-z))

    for k in net.p:
        flat = np.flatnonzero(np.abs(grads[k].ravel()) > 1e-3)[:5]
        for i in flat:
            old = net.p[k].ravel()[i]
            vals = []
            for d in (1e-4, -1e-4):
                net.p[k].ravel()[i] = old + d
                vals.append(loss())
            net.p[k].ravel()[i] = old
            assert abs((vals[0] - vals[1]) / 2e-4 - grads[k].ravel()[i]) < 2e-2 * max(1, abs(grads[k].ravel()[i]))


# --- 6 -------------------------------------------------------------------------------------------

def test_mix_reaches_targets(spark, sf):
    rows = QUERIES["op6_source_mix"](spark, sf).collect()
    docs = {r["doc_id"]: r for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    size = {i: len(re.findall(r"[^\x20\x09-\x0D]+", d["text"])) for i, d in docs.items()}
    by = defaultdict(int)
    for i, d in docs.items():
        by[d["source"]] += size[i]
    names = sorted(by, key=lambda s: s.encode())
    weights, fixed, total = {s: 1 + i % 3 for i, s in enumerate(names)}, {}, sum(by.values())
    while True:
        rest = [s for s in names if s not in fixed]
        share = {s: (total - sum(fixed.values())) * weights[s] / sum(weights[x] for x in rest) for s in rest}
        over = [s for s in rest if share[s] > 3 * by[s]]
        if not over:
            break
        fixed |= {s: 3 * by[s] for s in over}
    target, taken = {**fixed, **share}, defaultdict(int)
    for r in rows:
        s = docs[r["doc_id"]]["source"]
        assert r["size"] == size[r["doc_id"]] and r["source_size"] == by[s] and abs(r["target"] - target[s]) < 1e-6 * target[s]
        assert 0 <= r["taken"] <= 3 * r["size"] and r["taken"] % max(1, r["size"]) == 0
        taken[s] += r["taken"]
    assert all(abs(taken[s] - target[s]) <= 0.02 * target[s] for s in names), {s: (taken[s], target[s]) for s in names}
    again = QUERIES["op6_source_mix"](spark, sf)
    assert Counter(map(tuple, rows)) == Counter(map(tuple, again.collect()))


def test_route_is_cheapest(spark):
    flow = source_mix.route({("a",): 10, ("a", "b"): 10, ("b",): 2}, {"a": 20, "b": 8})
    assert sum(f for (p, s), f in flow.items() if s == "a") == pytest.approx(20) and sum(f for (p, s), f in flow.items() if s == "b") == pytest.approx(8)
    passes = defaultdict(float)
    for (p, _), f in flow.items():
        passes[p] += f
    # 28 wanted of 22 unique: six words are repeats whichever way, none taken a third time
    assert sum(max(0, passes[p] - n) for p, n in ((("a",), 10), (("a", "b"), 10), (("b",), 2))) == pytest.approx(6)


def cheapest(supply, quota, repeats=3):
    """Most words that whole-number flows can place, and the least cost of placing so many, by trying all."""
    arcs = [(p, s) for p in supply for s in p]
    start = (tuple(0 for _ in supply), tuple(0 for _ in quota))
    states, names, order = {start}, list(quota), list(supply)
    for p, s in arcs:
        i, j = order.index(p), names.index(s)
        states = {(t[:i] + (t[i] + f,) + t[i + 1:], q[:j] + (q[j] + f,) + q[j + 1:]) for t, q in states for f in range(min(repeats * supply[p] - t[i], quota[s] - q[j]) + 1)}
    most = max(sum(t) for t, _ in states)
    price = lambda t: sum(k * min(max(x - k * supply[p], 0), supply[p]) for p, x in zip(order, t, strict=True) for k in range(repeats))
    return most, min(price(t) for t, _ in states if sum(t) == most), price, order


def test_flow_is_the_best_of_all_flows():
    rng = random.Random(9)
    for _ in range(25):
        supply = {p: rng.randrange(1, 4) for p in rng.sample([("a",), ("b",), ("a", "b"), ("b", "c"), ("a", "c"), ("d",)], 3)}
        quota = {s: rng.randrange(0, 6) for s in sorted({s for p in supply for s in p})}
        given = source_mix.route_groups(supply, quota)
        most, least, price, order = cheapest(supply, quota)
        assert sum(given.values()) == pytest.approx(most) and price([given[p] for p in order]) == pytest.approx(least)


def test_mix_of_overlapping_sources(spark):
    from pyspark.sql import functions as F

    rng = random.Random(12)
    rows = [(i, "w " * rng.randrange(1, 9), rng.choice(["a", "b", "a,b", "b,c", "d"])) for i in range(3000)]
    docs = docs_of(spark, rows)
    ranked, sources, _ = source_mix.plan_mix(docs, F.col("doc_id"), F.split("source", ","), bin_rows=100)
    taken, supply = defaultdict(int), defaultdict(int)
    for r in ranked.collect():
        taken[tuple(r["pattern"])] += r["size"] * r["copies"]
        supply[tuple(r["pattern"])] += r["size"]
    target = {r["name"]: r["target"] for r in sources.collect()}
    want = source_mix.route_groups(dict(supply), target)
    assert all(abs(taken[p] - want[p]) <= 8 for p in supply) and sum(want.values()) == pytest.approx(min(sum(target.values()), 3 * sum(supply.values())), rel=0.2)


def test_mix_odd_rows(spark):
    docs = docs_of(spark, ODD).withColumnRenamed("lang", "target")
    out = source_mix.mix_sources(docs).collect()
    assert len(out) == len(ODD) and all(r["taken"] == 0 for r in out if r["size"] == 0)
    mixed = source_mix.mix_documents(docs)
    assert mixed.columns == docs.columns and mixed.count() == sum(r["taken"] // r["size"] for r in out if r["size"])
    assert source_mix.mix_sources(docs.limit(0)).count() == 0 and source_mix.mix_documents(docs.limit(0)).count() == 0


def test_mix_keeps_columns_with_clashing_names(spark):
    from pyspark.sql import functions as F

    odd = docs_of(spark, ODD)
    own = ["copy", "times", "n", "takes", "row", "key", "pattern", "size", "draw", "bin", "k1_", "n_", "target", "name", "source_size", "base"]
    docs = odd.withColumns({c: F.lit(7) for c in own}).withColumns({"bag": F.create_map(F.lit("a"), F.col("doc_id")), "a.b": F.lit(1)})
    mixed, plain_ = source_mix.mix_documents(docs), source_mix.mix_documents(odd)
    assert mixed.columns == docs.columns and mixed.count() == plain_.count() and all(r[c] == 7 for r in mixed.collect() for c in own)
    assert {tuple(r) for r in mixed.select(*odd.columns).collect()} <= {tuple(r) for r in odd.collect()}
    assert source_mix.mix_sources(docs).count() == len(ODD)


def test_mix_of_many_sources_and_of_rows_that_repeat(spark, monkeypatch):
    rows = [(1, "one two three", "a")] * 500 + [(i, "four five", f"s{i}") for i in range(300)]
    docs = docs_of(spark, rows)
    out = Counter(tuple(r) for r in source_mix.mix_sources(docs).collect())
    mixed = source_mix.mix_documents(docs, part=64)
    assert mixed.count() == sum(n * t[4] // t[1] for t, n in out.items())
    monkeypatch.setattr(source_mix, "MAX_BROADCAST", 3)
    assert Counter(tuple(r) for r in source_mix.mix_sources(docs).collect()) == out


# --- 7 -------------------------------------------------------------------------------------------

def slow_distance(item, text):
    row = [0] * (len(text) + 1)
    for i, c in enumerate(item):
        prev, row[0] = row[0], i + 1
        for j, d in enumerate(text):
            prev, row[j + 1] = row[j + 1], min(prev + (c != d), row[j] + 1, row[j + 1] + 1)
    return min(row)


@pytest.mark.parametrize("pairs", [8, 400])
def test_edit_distances(pairs):
    """Alone (few pairs) and all together (many): the least edits within the bound, else one more than it."""
    rng = random.Random(pairs)
    items, texts, most = [], [], []
    for _ in range(pairs):
        items.append(bytes(rng.choice(b"ab ") for _ in range(rng.choice([1, 5, 40, 63, 64, 65, 130]))))
        near = bytearray(items[-1])
        for _ in range(len(near) // 6):
            near[rng.randrange(len(near))] = 99
        texts.append(bytes(rng.choice(b"ab ") for _ in range(rng.randrange(0, 60))) + (bytes(near) if rng.random() < 0.5 else b""))
        most.append(rng.choice([len(items[-1]), len(items[-1]) // 5]))
    best, end = leak_windows.edit_distances(items, texts, most)
    for i, t, m, b, e in zip(items, texts, most, best.tolist(), end.tolist(), strict=True):
        want = slow_distance(i, t)
        assert b == min(want, m + 1) and (b > m or b == len(i) or slow_distance(i, t[:e]) == b)


def test_long_item(spark):
    rng = random.Random(6)
    item = " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randrange(2, 9))) for _ in range(4000))
    index = leak_windows.Index([(1, item.encode()), (2, item[:300].encode())])
    edited = "".join(c if rng.random() > 0.05 else rng.choice("xyz ") for c in item)
    assert [(t, i) for t, i, *_ in index.scan([f"before {edited} after", item[2000:3000], "nothing at all"])] == [(0, 0), (0, 1)]


def test_planted_leaks_are_found(spark, documents, sf):
    items = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()]
    rng, rows, want = random.Random(3), [], set()
    hosts = [t for _, t, _ in documents if 200 < len(t) < 3000 and not any(plain(x) in plain(t) for _, x in items)][:300]
    for k, host in enumerate(hosts):
        if k % 3:
            rows.append((k, host, "s"))
            continue
        item, text = items[rng.randrange(len(items))]
        words = text.split(" ")
        for _ in range(len(words) * (k % 4) // 30):  # up to a tenth of the words changed
            words[rng.randrange(len(words))] = rng.choice(["xyzzy", "the", ""])
        cut = rng.randrange(len(host))
        rows.append((k, host[:cut] + " " + " ".join(words).upper() + " " + host[cut:], "s"))
        want.add((k, item))
    got = {(r["doc_id"], r["item_id"]) for r in find_leaks(docs_of(spark, rows), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got == want
    kept = drop_leaks(docs_of(spark, rows), spark.createDataFrame(items, "item_id long, text string"))
    assert {r["doc_id"] for r in kept.collect()} == {k for k, _, _ in rows} - {k for k, _ in want}


def test_leaks_of_whole_table_against_literal_search(spark, sf, documents):
    items = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()]
    literal = {(d, i) for d, t, _ in documents for i, x in items if plain(x) in plain(t)}
    got = {(r["doc_id"], r["item_id"]): r["edits"] for r in QUERIES["op7_leak_windows"](spark, sf).collect()}
    assert literal <= set(got) and all((e == 0) == (p in literal) for p, e in got.items())


@pytest.mark.parametrize("least,most", [(5, 19), (20, 39), (40, 50), (50, 70), (70, 100), (100, 160), (160, 300)])
def test_leaks_reach_the_target_at_every_length_and_edit_rate(duck, least, most):
    rng, letters = random.Random(5), "abcdefghijklmnopqrstuvwxyz "
    passages = [t for (t,) in duck.execute("select text from benchmark").fetchall()]
    hosts = [t for (t,) in duck.execute("select text from documents where length(text) > 600 limit 200").fetchall()]

    def damage(text, edits):
        t = list(text)
        for _ in range(edits):
            at, how = rng.randrange(len(t)), rng.randrange(3)
            t[at:at + 1] = [[rng.choice(letters)], [], [t[at], rng.choice(letters)]][how]
        return "".join(t)

    items = set()
    while len(items) < 80:
        words = rng.choice(passages).split()
        text = plain(" ".join(words[rng.randrange(len(words)):])[:rng.randint(least, most)])
        if least <= len(text) <= most:
            items.add(text.decode("utf-8", "ignore").strip().encode())
    items = list(enumerate(sorted(t for t in items if len(t) >= least)))
    index = leak_windows.Index(items)
    for rate in (0.05, 0.1, 0.15, 0.19):
        docs = []
        for i, text in items:
            for _ in range(2):
                host, at = rng.choice(hosts), rng.randrange(400)
                docs.append((i, text, f"{host[at:at + 100]} {damage(text.decode(), int(rate * len(text)))} {host[at + 100:at + 200]}"))
        docs = [d for d in docs if edit_distance(d[1], plain(d[2]))[0] <= int(0.2 * len(d[1]))]
        found = {(t, index.items[k][0]) for t, k, *_ in index.scan([d for *_, d in docs])}
        assert len(docs) > 100 and np.mean([(k, i) in found for k, (i, _, _) in enumerate(docs)]) >= (0.9 if least >= 40 else 1), rate


def test_leaks_in_text_without_blanks():
    rng = random.Random(8)
    item = "".join(rng.choice("abcdefghijklmnop") for _ in range(120))
    index = leak_windows.Index([(1, item.encode())])
    edited = item[:30] + "q" + item[31:70] + item[71:]
    assert [(t, i) for t, i, *_ in index.scan(["z" * 90 + edited + "y" * 50, "z" * 300])] == [(0, 0)]


def test_leaks_odd_rows(spark):
    items = spark.createDataFrame([(1, "short one"), (2, None), (None, "x"), (3, ""), (4, "a passage that is long enough to be walked over more than once")], "item_id long, text string")
    items = items.union(spark.createDataFrame([(5, "q7z")], items.schema))
    rows = [*ODD, (20, "has Short  one here", "a"), (21, "shorrt one", "a"), (22, "intro. A passage that is long enough to be walked  over more than once", "a"), (23, "(Q7Z), aq7z", "a"), (24, "q7zz", "a"), (25, "short ones.", "a"), (26, "shhhort", "a")]
    got = {(r["doc_id"], r["item_id"], r["edits"]) for r in find_leaks(docs_of(spark, rows), items).collect()}
    assert got == {(20, 1, 0), (21, 1, 1), (22, 4, 0), (23, 5, 0), (25, 1, 0)}
    assert find_leaks(docs_of(spark, rows).limit(0), items).count() == 0 and find_leaks(docs_of(spark, rows), items.limit(0)).count() == 0


def test_leaks_by_blocks_of_items(spark, sf, monkeypatch):
    docs, items = (spark.read.parquet(f"{sf}/{t}.parquet") for t in ("documents", "benchmark"))
    whole, kept = Counter(map(tuple, find_leaks(docs, items).collect())), drop_leaks(docs, items).count()
    monkeypatch.setattr(leak_windows, "ITEM_BLOCK", 15)
    assert Counter(map(tuple, find_leaks(docs, items).collect())) == whole and drop_leaks(docs, items).count() == kept


# --- 8 -------------------------------------------------------------------------------------------

def test_line_spread_odd_rows(spark):
    rows = [(i, f"banner line\nown {i}\n\nrare", f"s{i % 12}") for i in range(24)] + ODD + [(90, "banner line", None), (91, "half", "s1")] + [(100 + i, "half", f"s{i}") for i in range(9)]
    from pyspark.sql import functions as F
    out = {r["doc_id"]: r for r in line_spread.clean_documents(docs_of(spark, rows), F.col("source"), 10).collect()}
    assert out[3]["clean_text"] == " \t\n " and out[90]["clean_text"] == "" and out[91]["clean_text"] == "half"
    assert out[10]["n_removed"] == 2 and out[10]["clean_text"] == "own 10\n" and out[1]["n_lines"] == 0
    assert line_spread.clean_documents(docs_of(spark, ODD).limit(0), F.col("source"), 10).count() == 0
    own = ["t1", "t2", "k1", "k2", "h1", "gone", "row", "body", "site", "cut", "likely", "p_", "page_", "b_", "pos", "line"]
    clash = line_spread.clean_documents(docs_of(spark, rows).withColumns({c: F.lit(7) for c in own}), F.col("source"), 10)
    assert all(r[c] == 7 for r in clash.select(*own).collect() for c in own)
    assert Counter(tuple(r) for r in clash.drop(*own).collect()) == Counter(tuple(r) for r in line_spread.clean_documents(docs_of(spark, rows), F.col("source"), 10).collect())


def test_line_spread_of_one_text_with_very_many_lines(spark):
    from pyspark.sql import functions as F

    long = "\n".join(["gone", "own"] * 60_000)
    rows = [(i, long.replace("own", f"own {i}") if i < 2 else "gone", f"s{i}") for i in range(12)]
    out = {r["doc_id"]: r for r in line_spread.clean_documents(docs_of(spark, rows), F.col("source"), 10).collect()}
    assert out[1]["n_removed"] == 60_000 and out[1]["clean_text"] == "\n".join(["own 1"] * 60_000) and out[5]["clean_text"] == ""


# --- 9 -------------------------------------------------------------------------------------------

SPEC = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(digits):
    return sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(digits))) % 10 == 0


def spec_spans(text):
    out = []
    for kind, pattern in SPEC.items():
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            ok = {"email": True, "ip": all(int(p) <= 255 for p in m[0].split(".")) if kind == "ip" else True, "card": 13 <= len(digits) <= 19 and luhn(digits), "phone": 9 <= len(digits) <= 15}[kind]
            if ok:
                out.append((kind, m.start(), m.end()))
    return out


def test_base_spans_follow_the_patterns(spark, documents):
    rng = random.Random(8)
    bits = ["a.b@c-d.ef", "x@y", "1.2.3.4", "256.1.1.1", "1.2.3.4.5", "000.00.0.0255", "4111 1111 1111 1111", "4111111111111112", "+1 (555) 123-4567", "+12", "++3 44 555 66 77 (", "ü@b.c", "1-2-3", " ", ".", "-", "@", "é", "\U0001f600", "\n", "a", "9", "%_", "q@r.s_t@u.v"]
    rows = [(i, "".join(rng.choice(bits) for _ in range(rng.randrange(1, 14))), "s") for i in range(600)] + [(1000 + i, t, s) for i, t, s in documents[:300]] + [(5000, None, "s"), (5001, "a" * 40_000, "s"), (5002, "1" * 20_000, "s"), (5003, "", None)]
    got = {r["doc_id"]: r for r in private_spans.with_base(docs_of(spark, rows)).select("row.doc_id", *[f"base_{k}" for k in private_spans.KINDS]).collect()}
    for i, text, _ in rows:
        found = [(k, s["start"], s["end"]) for k in private_spans.KINDS for s in got[i][f"base_{k}"]]
        assert found == spec_spans(text), (text or "")[:200]


def test_private_query(spark, sf, documents):
    texts = {i: t for i, t, _ in documents}
    rows = QUERIES["op9_private_spans"](spark, sf).collect()
    assert len(rows) == len(texts)
    for r in rows:
        spans = spec_spans(texts[r["doc_id"]])
        base = [f"{k}:{a}:{b}" for k, a, b in spans]
        assert r["base_sha256"] == hashlib.sha256(",".join(base).encode()).hexdigest()
        assert set(base) <= set(r["spans"].split(",")) | ({""} if not base else set())
        assert r["n_added"] + len(base) == len([x for x in r["spans"].split(",") if x]) == r["n_private"] - r["n_secret"]
        assert [r[f"n_{k}"] for k in private_spans.KINDS] == [sum(s[0] == k for s in spans) for k in private_spans.KINDS]


def naive_proposals(text):
    """(kind, start, end, sound, same, features) by a plain walk with Python's patterns."""
    import regex

    out = []
    for k, kind in enumerate(private_spans.KINDS):
        hits = list(regex.finditer(private_spans.LOOSE[kind], text)) if re.search(private_spans.LOOSE_GATE[kind], text) else []
        for i, m in enumerate(hits):
            hit, digits = m[0], re.sub("[^0-9]", "", m[0])
            before = text[max(hits[i - 1].start() if i else 0, m.start() - private_spans.CONTEXT_LENGTH):m.start()]
            after = text[m.end():m.end() + 1]
            plain_ = hit
            if kind == "email":
                plain_ = re.sub(r" ?\. ", ".", re.sub(r" ?(\(dot\)|\[dot\]) ?", ".", re.sub(r" ?(\(at\)|\[at\]|@) ?", "@", hit)))
            elif kind == "ip":
                plain_ = hit.replace(" ", "")
            check = lambda x, kind=kind: {"email": lambda: True, "ip": lambda: bool(re.fullmatch(SPEC["ip"], x)) and all(int(p) <= 255 for p in x.split(".")), "card": lambda: 13 <= len(re.sub("[^0-9]", "", x)) <= 19 and luhn(re.sub("[^0-9]", "", x)), "phone": lambda: 9 <= len(re.sub("[^0-9]", "", x)) <= 15}[kind]()
            sound = bool(regex.search(r"^[^@ ]+@[^@ ]+\.\p{L}{2,}$", plain_)) if kind == "email" else check(plain_)
            same = bool(re.fullmatch(SPEC[kind], hit)) and check(hit)
            edge = lambda c: 0 if not c else 1 if c.isspace() else 2 if c.isalpha() or c.isnumeric() or c == "_" else 3
            bins = lambda x, cuts: sum(x >= c for c in cuts)
            marks = 3 if re.search(r"\((?:at|dot)\)|\[(?:at|dot)\]| @|@ | \.|\. ", hit) else 2 if re.search("[./]", hit) else 1 if re.search("[ ()-]", hit) else 0
            context = 2 if re.search(private_spans.NEGATIVE, before) else 1 if re.search(private_spans.CONTEXT, before) else 0
            out.append((k, m.start(), m.end(), sound, same, (k, bins(len(digits), (1, 9, 13, 16, 20)), bins(len(re.findall("[0-9]+", hit)), (2, 3, 4, 5)), marks, edge(before[-1:]), edge(after), context)))
    return out


def naive_added(text, trees, least):
    base = spec_spans(text)
    free = [(a, -sum(private_spans.tree_value(t, x) for t in trees), k, b) for k, a, b, sound, same, x in naive_proposals(text) if sound and not same and not any(c < b and a < d for _, c, d in base)]
    passed = sorted(s for s in free if s[2] in least and -s[1] >= least[s[2]])
    return [(k, a, b) for i, (a, _, k, b) in enumerate(passed) if all(e <= a for *_, e in passed[:i])]


def private_texts():
    """Invented texts with personal data in the base forms, in other forms, and numbers that are none."""
    rng, out = random.Random(21), []
    words = "the of und les hein tion casa ring über".split()
    number = lambda n: "".join(rng.choice("0123456789") for _ in range(n))
    name = lambda: "".join(rng.choice("abcdefghij") for _ in range(5))

    def card(sep):
        digits = "4" + number(14)
        digits += next(c for c in "0123456789" if luhn(digits + c))
        return sep.join(digits[i:i + 4] for i in range(0, 16, 4))

    forms = [lambda: f"{name()}.{number(2)}@{name()}.com", lambda: ".".join(str(rng.randrange(256)) for _ in range(4)), lambda: card(" "), lambda: f"+{rng.randrange(1, 9)} ({number(3)}) {number(3)}-{number(4)}"]
    others = [lambda: f"{name()} (at) {name()} (dot) org", lambda: f"{name()}[at]{name()}.net", lambda: " . ".join(str(rng.randrange(256)) for _ in range(4)), lambda: card("."), lambda: f"({number(3)}) {number(3)}-{number(4)}", lambda: f"{number(3)}-{number(3)}-{number(4)}"]
    none = [lambda: f"version {number(1)}.{number(1)}.{number(2)}.{number(1)}", lambda: f"order {number(10)}", lambda: number(16), lambda: "300.400.1.2", lambda: f"id {number(4)} {number(4)} {number(4)}", lambda: f"{name()}@{name()}"]
    for i in range(900):
        kinds = forms * 3 + none * 2 + (others if i % 5 == 0 else [])
        parts = [rng.choice([rng.choice(kinds), lambda: rng.choice(words)])() for _ in range(rng.randrange(3, 14))]
        out.append((i, " ".join(rng.choice(words) + " " + p for p in parts), "s"))
    return out


def test_added_spans_are_those_of_a_plain_walk(spark):
    rows = [*private_texts(), (5000, "", "s"), (5001, None, "s"), (5002, "\U0001f600 (555) 123-4567, 4111.1111.1111.1111\n" * 70, "s")]
    proposed = private_spans._with_held(private_spans.with_proposals(private_spans.with_base(docs_of(spark, rows))))
    trees, least = private_spans.train(proposed)
    assert set(least) == {0, 1, 2, 3}
    got = {r["doc_id"]: [(s["kind"], s["start"], s["end"]) for s in r["added"]] for r in private_spans.select_spans(proposed, (trees, least)).select("row.doc_id", "added").collect()}
    seen = {r["doc_id"]: sorted((x["p"]["kind"], x["p"]["start"], x["p"]["end"], x["p"]["sound"], x["p"]["same"], tuple(x["p"][n] for n in private_spans.NAMES)) for x in r["proposals"] or []) for r in proposed.select("row.doc_id", "proposals").collect()}
    kinds = Counter()
    for i, text, _ in rows:
        assert seen[i] == sorted(naive_proposals(text or "")), text
        assert got[i] == naive_added(text or "", trees, least), text
        kinds.update(k for k, *_ in got[i])
    assert all(kinds[k] >= 10 for k in range(4)), kinds  # each kind in a form that the base pattern does not have
    for i, text, _ in rows[:900]:
        assert not any(re.match(r"version|order|id ", text[max(0, a - 8):a]) or text[a:b].isdigit() for _, a, b in got[i])


def test_private_columns_with_clashing_names(spark):
    from pyspark.sql import functions as F

    own = ["body", "proposals", "passed", "row", "held", "p", "free", "kind", "start", "loose_ip", "hits", "kept"]
    docs = docs_of(spark, private_texts()[:60] + ODD)
    clash = private_spans.find_private(docs.withColumns({c: F.lit(7) for c in own}))
    assert all(r[c] == 7 for r in clash.select(*own).collect() for c in own)
    assert sorted(map(str, clash.drop(*own).collect())) == sorted(map(str, private_spans.find_private(docs).collect()))
    assert private_spans.find_private(docs.limit(0)).count() == 0 and private_spans.redact(docs.withColumn("clean_text", F.lit(1))).columns == [*docs.columns, "clean_text"]


def test_one_text_with_very_many_spans(spark):
    n = 20_000
    docs = docs_of(spark, [(1, "a.b@c.de +1 (555) 123-4567 " * n, "s"), (2, "(" * 300_000, "s"), (3, "( 1" * 100_000, "s"), (4, "+1" + " " * 300_000, "s")])
    r = {r["doc_id"]: r for r in private_spans.find_private(docs).collect()}
    assert len(r[1]["base_email"]) == len(r[1]["base_phone"]) == n and r[1]["base_phone"][-1]["end"] == 27 * n - 1


def test_redaction(spark):
    docs = docs_of(spark, [(1, "mail a.b@c.de or +1 (555) 123-4567 now", "s"), (2, None, "s"), (3, "+1 555 666 777 8, 1.2.3.4 \U0001f600 é x@y.zz", "s"), (4, "none", "s")])
    out = {r["doc_id"]: r["clean_text"] for r in private_spans.redact(docs).collect()}
    assert out == {1: "mail [private] or [private] now", 2: "", 3: "[private], [private] \U0001f600 é [private]", 4: "none"}


def test_boosting_learns_a_rule():
    cells = [((0, d, 0, p, 1, 1, 0), 50 * (p == 1 and d >= 2), 50) for d in range(5) for p in range(2)]
    trees = private_spans.boost(cells)
    margin = {x: sum(private_spans.tree_value(t, x) for t in trees) for x, _, _ in cells}
    assert all((margin[x] > 0) == (pos > 0) for x, pos, _ in cells)
    assert set(private_spans.thresholds(trees, cells)) == {0}


# --- 10 ------------------------------------------------------------------------------------------

def test_codes_round_trip_and_random_access():
    ids = np.random.default_rng(0).choice([1, 255, 256, 50_000, 70_000, 20_000_000], 5000).astype(np.uint32)
    codes = token_codes.Codes(token_codes.pack_codes(ids))
    assert (codes.slice(0, len(ids)) == ids).all() and len(codes) == len(ids)
    for i in (0, 1, 511, 512, 513, 4999):
        assert codes[i] == ids[i] and (codes.slice(i, min(i + 700, 5000)) == ids[i:i + 700]).all()
    assert len(token_codes.Codes(token_codes.pack_codes(ids[:0]))) == 0


def test_encoder_is_the_library(documents):
    from tokenizers import Tokenizer

    own, lib = token_codes.PieceEncoder(token_codes.default_tokenizer(), span=5000), Tokenizer.from_file(token_codes.default_tokenizer())
    lib.encode_special_tokens = True
    texts = [t for _, t, _ in documents[:200]] + [t or "" for _, t, _ in ODD] + ["'s don't I'll 'tis  '' x's!'s\n's \n\n x", "a  'll'd've're  \t\n b <|endoftext|>", "　x ½ y² 12a"]
    assert [x.tolist() for x in own.encode(texts)] == [e.ids for e in lib.encode_batch(texts, add_special_tokens=False)]


def test_added_tokens_are_those_of_the_library(spark):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(token_codes.default_tokenizer())
    end = "<|endoftext|>"
    texts = [f"a {end} b", end, f"{end}{end}", f"x  {end}  y{end}'s", f"{end}\n", f"<|endof{end}text|>", "<|endoftext", "plain", "", f"word {end} " * 300]
    assert [x.tolist() for x in token_codes.encoder_of(token_codes.default_tokenizer()).encode(texts)] == [lib.encode(t, add_special_tokens=False).ids for t in texts]
    start, want = 0, {}
    for i, t in enumerate(texts):
        ids = np.array([*lib.encode(t, add_special_tokens=False).ids, 2], "<u4")
        want[i] = (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    rows = token_codes.token_codes(docs_of(spark, [(i, t, "s") for i, t in enumerate(texts)])).collect()
    assert {r["doc_id"]: (r["start"], r["n_tokens"], r["ids_crc32"]) for r in rows} == want


def test_token_query(spark, sf, documents):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(token_codes.default_tokenizer())
    start, want = 0, {}
    for i, t, _ in sorted(documents):
        ids = np.array([*lib.encode(t, add_special_tokens=False).ids, 2], "<u4")
        want[i] = (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    got = {r["doc_id"]: (r["start"], r["n_tokens"], r["ids_crc32"]) for r in QUERIES["op10_token_codes"](spark, sf).collect()}
    assert got == want


def test_token_odd_rows(spark):
    out = token_codes.token_codes(docs_of(spark, ODD)).collect()
    assert len(out) == len(ODD) and sum(r["n_tokens"] for r in out) == max(r["start"] + r["n_tokens"] for r in out)
    assert min(out, key=lambda r: r["start"])["doc_id"] is None
    assert token_codes.token_codes(docs_of(spark, ODD).limit(0)).count() == 0
