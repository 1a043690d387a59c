import random

import numpy as np
import pytest

from locpref.llm import common, minhash
from locpref.llm.components import components, forest_components
from locpref.llm.common import Scratch
from locpref.llm.queries import OP8_SQL, op8_minhash

from .oracle import same


def brute(texts, k, percent=80):
    """Component by id from all pairs of true shingle sets."""
    sets = {}
    for i, t in texts.items():
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    parent = {i: i for i in texts}

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    post = {}
    for i, s in sets.items():
        for x in s:
            post.setdefault(x, []).append(i)
    inter = {}
    for ids in post.values():
        for a in range(len(ids)):
            for b in range(a):
                key = (min(ids[a], ids[b]), max(ids[a], ids[b]))
                inter[key] = inter.get(key, 0) + 1
    for (a, b), c in inter.items():
        if 100 * c >= percent * (len(sets[a]) + len(sets[b]) - c):
            x, y = root(a), root(b)
            parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), root(i)) for i in texts}


def test_op8_equals_all_pairs(spark, small):
    for where in (small, "/root/testdata/sf0.01"):
        texts = {r.doc_id: r.text for r in spark.read.parquet(f"{where}/documents.parquet").collect()}
        got = {r.doc_id: (r.n_shingles, r.component_id) for r in op8_minhash(spark, where).collect()}
        assert got == brute(texts, 4)


def test_op8_equals_sql(spark):
    d = "/root/testdata/sf0.01"
    same(op8_minhash(spark, d), OP8_SQL, d)


def test_near_copies_chains_and_odd_rows(spark):
    rng = random.Random(3)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(6))
    base = [word() for _ in range(80)]
    rows, at = [], 10
    drift = list(base)
    for _ in range(60):  # each differs a little from the one before: chains
        drift = list(drift)
        drift[rng.randrange(80)] = word()
        rows.append((at, " ".join(drift)))
        at += 1
    rows += [(at + i, " ".join(base)) for i in range(40)]
    rows += [(1, None), (2, ""), (3, " \n"), (4, "one two"), (5, "ONE  two"), (6, "one"), (9, "x " * 30000)]
    docs = spark.createDataFrame([(i, t, 7, True) for i, t in rows], "doc_id long, text string, n int, kept boolean")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(docs, k=4).collect()}
    assert got == brute(dict(rows), 4)
    twice = minhash.near_duplicates(docs.unionByName(docs), k=4)
    assert twice.count() == 2 * len(rows)
    bare = spark.createDataFrame([(None, "one two three four five"), (3, "one two three four five")], "doc_id long, text string")
    assert {(r.doc_id, r.component_id, r.kept) for r in minhash.near_duplicates(bare).collect()} == {(None, None, True), (3, 3, True)}
    assert minhash.near_duplicates(docs.limit(0)).count() == 0


def test_sketch_fills_and_estimates():
    rng = np.random.default_rng(1)
    a = rng.integers(0, 2**63, 900).astype(np.uint64)
    for cut in (0, 100, 400):
        b = np.concatenate([a[cut:], rng.integers(0, 2**63, cut).astype(np.uint64)])
        s = minhash.sketch(np.concatenate([a, b]), np.repeat([0, 1], 900), 2, 336)
        assert not (s == minhash._EMPTY).any()
        j = (900 - cut) / (900 + cut)
        assert abs((s[0] == s[1]).mean() - j) < 4 * (0.25 / 336) ** 0.5 + 1e-9
    few = minhash.sketch(a[:3], np.zeros(3, int), 1, 336)
    assert not (few == minhash._EMPTY).any()
    alone = minhash.sketch(a[:50], np.zeros(50, int), 1, 64)
    among = minhash.sketch(np.concatenate([a[:50], a]), np.repeat([0, 1], [50, 900]), 2, 64)
    assert (alone[0] == among[0]).all()


def test_components(spark):
    rng = random.Random(2)
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1000 + i) for i in range(1, 50)] + [(rng.randrange(5000, 5300), rng.randrange(5000, 5300)) for _ in range(150)]
    parent = {}
    find = lambda x: x if parent.setdefault(x, x) == x else find(parent[x])
    for a, b in edges:
        if a != b:
            x, y = find(a), find(b)
            parent[max(x, y)] = min(x, y)
    got = components(spark.createDataFrame(edges, "u long, v long"), Scratch(spark, "test")).collect()
    assert {r.node: r.component for r in got} == {x: find(x) for x in parent}
    assert len(got) == len(parent)


@pytest.mark.parametrize(("weight", "least"), [(1.0, 2000), (1e9, 5), (0.0, 5)])
def test_a_crowd_near_the_threshold(spark, monkeypatch, weight, least):
    """Hundreds of variants of one text, many of them just below or above the threshold to each other; by clusters, by buckets, with hot keys."""
    monkeypatch.setattr(minhash, "BUCKET_WEIGHT", weight)
    monkeypatch.setattr(minhash, "BLOCK_ROWS", 40)
    monkeypatch.setattr(common, "LEAST_HOT", least)
    monkeypatch.setattr(common, "MOST_HOT", 10_000 if least > 5 else 50)
    rng = random.Random(11)
    base = [f"b{i}" for i in range(70)]
    rows = {}
    for i in range(420):
        words = list(base)
        for j in range(rng.choice([1, 2, 2, 3, 4])):
            words[rng.randrange(70)] = f"e{i}x{j}"
        rows[1000 + (i * 7919) % 5000] = " ".join(words)
    docs = spark.createDataFrame(list(rows.items()), "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(docs, k=4).collect()}
    want = brute(rows, 4)
    assert got == want
    assert len({c for _, c in want.values()}) > 3


def test_spanning_links_join_what_all_pairs_join():
    rng = np.random.default_rng(6)
    base = rng.integers(0, 2**40, 60).astype(np.uint64)
    sets = [np.unique(np.concatenate([base[rng.random(60) < 0.9], rng.integers(0, 2**40, 4).astype(np.uint64)])) for _ in range(40)]
    comp = np.array([i // 2 for i in range(40)])
    side = np.array([0] * 20 + [1] * 20)
    got = minhash.spanning_links(sets, side, comp, 80)
    linked = lambda a, b: 100 * len(np.intersect1d(a, b)) >= 80 * len(np.union1d(a, b))

    def classes(pairs):
        parent = list(range(20))
        find = lambda x: x if parent[x] == x else find(parent[x])
        for a, b in pairs:
            parent[find(comp[a])] = find(comp[b])
        return [{i for i in range(20) if find(i) == find(k)} for k in range(20)]

    all_pairs = [(a, b) for a in range(20) for b in range(20, 40) if comp[a] != comp[b] and linked(sets[a], sets[b])]
    assert classes(got) == classes(all_pairs) and len(got) < 20
    assert all(linked(sets[a], sets[b]) for a, b in got)


def test_forest(spark):
    rng = random.Random(7)
    parent = {v: rng.randrange(max(0, v - 6), v) for v in range(1, 400) if v % 50}
    relabel = rng.sample(range(10_000), 400)
    find = lambda v: find(parent[v]) if v in parent else v
    least = {}
    for v in range(400):
        least[find(v)] = min(least.get(find(v), 10**9), relabel[v])
    nodes = set(parent) | set(parent.values())
    got = forest_components(spark.createDataFrame([(relabel[u], relabel[v]) for v, u in parent.items()], "u long, v long"), Scratch(spark, "test"))
    assert {r.node: r.component for r in got.collect()} == {relabel[v]: least[find(v)] for v in nodes}
    assert got.count() == len(nodes)
