import math

import numpy as np

from locpref.llm import metric_tree
from locpref.llm.queries import OP4_SQL, op4_metric_tree

from .oracle import same


def brute(rows, queries, k):
    out = {}
    for q, v in queries.items():
        scored = sorted((-int(np.dot(v, w)), i) for i, w in rows if i != q and len(w) == len(v))
        out[q] = [(i, -s) for s, i in scored[:k]]
    return out


def test_op4(spark):
    for d in ("/root/testdata/sf0.001", "/root/testdata/sf0.01"):
        same(op4_metric_tree(spark, d), OP4_SQL, d)


def test_tree_equals_scan():
    rng = np.random.default_rng(3)
    centres = rng.normal(0, 60, (6, 8))
    v = np.floor(np.vstack([centres[rng.integers(0, 6, 1500)] + rng.normal(0, 4, (1500, 8)), np.repeat(centres[:1], 700, axis=0)]))
    ids = rng.permutation(len(v)).astype(np.int64)
    longest = float((v * v).sum(axis=1).max())
    tree = metric_tree.Tree(metric_tree.build(ids, v, longest), 8, longest)
    assert sum(len(i) for i in tree.ids) == len(v) and max(len(i) for i in tree.ids) <= metric_tree.PAGE_ROWS
    for n in range(0, len(v), 40):
        found, score, computed = tree.search(int(ids[n]), v[n], 20)
        got = [(int(i), int(s)) for i, s in zip(found, score)]
        assert computed <= len(v) + len(tree.pages)
        again = tree.search(int(ids[n]), v[n], 20, float(score[-1]))
        assert again[0].tolist() == found.tolist() and again[2] <= computed
        assert got == brute(list(zip(ids.tolist(), v)), {int(ids[n]): v[n]}, 20)[int(ids[n])]


def test_search_leaves_pages_out():
    rng = np.random.default_rng(4)
    v = np.floor(np.repeat(np.eye(8) * 200, 400, axis=0) + rng.normal(0, 5, (3200, 8)))
    longest = float((v * v).sum(axis=1).max())
    tree = metric_tree.Tree(metric_tree.build(np.arange(3200), v, longest), 8, longest)
    seen, before = set(), metric_tree.heapq.heappop
    metric_tree.heapq.heappop = lambda h: seen.add(h[0][1]) or before(h)
    try:
        tree.search(0, v[0], 5)
    finally:
        metric_tree.heapq.heappop = before
    assert len(seen) < len(tree.pages) / 2


def test_odd_vectors(spark):
    rng = np.random.default_rng(5)
    rows = [(i, rng.normal(0, 1, 4).tolist()) for i in range(60)] + [(100, None), (101, []), (102, [1.0, None, 2.0, 3.0]), (103, [math.nan, 1.0, 1.0, 1.0]), (104, [math.inf, 1.0, 1.0, 1.0]), (None, [1.0] * 4), (120, [1.0, 2.0]), (140, [3.0, 1.0]), (30, rows_30 := [0.5] * 4)]
    df = spark.createDataFrame([(i, v, 9.0, 1) for i, v in rows], "vec_id long, embedding array<double>, score double, rank int")
    got = {}
    for r in metric_tree.top_k(df, df.where("vec_id % 20 = 0"), 5).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    good = [(i, [math.floor(64 * x) for x in v]) for i, v in rows if i is not None and v and all(x is not None and math.isfinite(x) for x in v)]
    queries = {i: v for i, v in good if i % 20 == 0}
    assert got == {q: v for q, v in brute(good, queries, 5).items() if v}
    assert metric_tree.top_k(df.limit(0), df, 5).count() == 0
    assert metric_tree.top_k(df, df.limit(0), 5).count() == 0


def test_blocks_and_bounds_leave_work_out(spark, monkeypatch):
    """Clustered vectors: a query's own block bounds the rest; the rows are those of a scan. Copies fill a block of their own."""
    monkeypatch.setattr(metric_tree, "BLOCK_ROWS", 300)
    rng = np.random.default_rng(7)
    centres = rng.normal(0, 4, (8, 12))
    rows = [(i, (centres[i % 8] + rng.normal(0, 0.2, 12)).tolist()) for i in range(2400)] + [(5000 + i, centres[0].tolist()) for i in range(700)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    queries = df.where("vec_id % 100 = 0")
    got = {}
    for r in metric_tree.top_k(df, queries, 5).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    scaled = [(i, [math.floor(64 * x) for x in v]) for i, v in rows]
    assert got == brute(scaled, {i: v for i, v in scaled if i % 100 == 0}, 5)
    done = metric_tree.work(df, queries, 5).collect()
    assert len(done) == len(got) and sum(r.computed for r in done) < 0.5 * len(done) * len(rows)


def test_parts_groups_and_ties(spark, monkeypatch):
    """Near-isotropic vectors and copies over many parts, regions and groups: the rows of a scan, and no batch of many blocks."""
    for name, value in (("BLOCK_ROWS", 100), ("CHUNK_ROWS", 8), ("PART_QUERIES", 32), ("SLICE_QUERIES", 16), ("ROOT_ROWS", 5), ("GROUP_BLOCKS", 3), ("MIN_GROUPS", 1), ("MOST_FOUND", 100)):
        monkeypatch.setattr(metric_tree, name, value)
    held, keep = {}, metric_tree.Scratch.keep
    monkeypatch.setattr(metric_tree.Scratch, "keep", lambda self, df, name: held.update({name: spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")}) or keep(self, df, name))
    rng = np.random.default_rng(9)
    rows = [(i, rng.normal(0, 0.2, 16).tolist()) for i in range(1500)] + [(1500 + 7 * i, [0.3] * 16) for i in range(400)] + [(9000 + i, [float(2000 * i), 1.0]) for i in range(30)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {}
    for r in metric_tree.top_k(df, df.where("vec_id % 9 = 0"), 6).orderBy("query_id", "rank").collect():
        got.setdefault(r.query_id, []).append((r.vec_id, r.score))
    scaled = [(i, [math.floor(64 * x) for x in v]) for i, v in rows]
    assert got == brute(scaled, {i: v for i, v in scaled if i % 9 == 0}, 6)
    assert int(held["results"]) <= 16 and int(held["own-results"]) <= 16
