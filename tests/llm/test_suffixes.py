import random

import numpy as np

from locpref.llm import common, suffixes
from locpref.llm.queries import OP2_SQL, op2_suffix_arrays

from .oracle import same


def brute(texts, length):
    words = {i: [m.group() for m in suffixes.WORD.finditer(t)] for i, t in texts.items() if t}
    seen = {}
    for i, w in words.items():
        for s in range(len(w) - length + 1):
            seen.setdefault(tuple(w[s : s + length]), set()).add(i)
    out = set()
    for i, w in words.items():
        held, again, first = set(), set(), {}
        for s in range(len(w) - length + 1):
            ids = seen[tuple(w[s : s + length])]
            if len(ids) > 1:
                held |= set(range(s, s + length))
                first[s] = min(ids)
                if min(ids) < i:
                    again |= set(range(s, s + length))
        for s in sorted(held):
            if s - 1 not in held:
                e = s
                while e in held:
                    e += 1
                out.add((i, s, e, min(f for x, f in first.items() if s <= x < e), len(again & set(range(s, e)))))
    return out


def test_picked_is_leftmost_least():
    rng = np.random.default_rng(2)
    for wide in (1, 2, 5, 8, 41):
        v = rng.integers(0, 6, 300)
        assert suffixes.picked(v, wide).tolist() == [i + int(np.argmin(v[i : i + wide])) for i in range(300 - wide + 1)]


def test_op2(spark):
    d = "/root/testdata/sf0.01"
    same(op2_suffix_arrays(spark, d), OP2_SQL, d)


def test_interleaved_passages_and_cuts(spark):
    rng = random.Random(9)
    pool = [" ".join(f"w{rng.randrange(400)}" for _ in range(rng.randrange(8, 40))) for _ in range(14)]
    rows = [(i, "  ".join(rng.choice(pool) if rng.random() < 0.6 else f"own{i}x{j}" for j in range(rng.randrange(1, 14)))) for i in range(60)]
    rows += [(100, None), (101, ""), (102, " \n "), (103, "a b c"), (104, rows[3][1]), (105, rows[3][1]), (106, "same " * 3000), (107, "same " * 2000)]
    docs = spark.createDataFrame([(i, t, 5, 0) for i, t in rows], "doc_id long, text string, start_word int, redundant int")
    texts = dict(rows)
    for length, gram in ((12, 4), (20, 6), (20, 20)):
        got = {(r.doc_id, r.start_word, r.end_word, r.first_doc_id, r.n_redundant) for r in suffixes.repeated_passages(docs, length, gram).collect()}
        assert got == brute(texts, length)
    left = {r.doc_id: r.text for r in suffixes.drop_redundant(docs, 12, 4).collect()}
    assert 104 not in left and 105 not in left and left[100] is None and left[101] == ""
    assert brute(left, 24) == set()
    whole = suffixes.drop_redundant(docs, 12, 4)
    assert whole.columns == docs.columns
    nul = spark.createDataFrame([(None, rows[3][1]), (None, rows[3][1])], "doc_id long, text string")
    assert suffixes.drop_redundant(nul).count() == 2
    assert suffixes.repeated_passages(docs.unionByName(docs), 12, 4).count() == suffixes.repeated_passages(docs, 12, 4).count()
    assert suffixes.repeated_passages(docs.limit(0)).count() == 0


def test_words_are_cut_in_place():
    assert suffixes.without_words("a b\nc d  e", [(1, 3)]) == "a  d  e"
    assert suffixes.without_words("a b", [(0, 2)]) == ""


def test_hot_grams_and_classes_take_another_way(spark, monkeypatch):
    """Grams with too many classes meet by content, hot keys by a broadcast: the same windows."""
    rng = random.Random(4)
    common = " ".join(f"c{i}" for i in range(9))
    texts = {i: " ".join([*(f"w{rng.randrange(30)}" for _ in range(6)), common, *(f"w{rng.randrange(4)}" for _ in range(8))]) for i in range(80)}
    texts |= {100 + i: texts[3] for i in range(30)}
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    want = brute(texts, 12)
    for most, least in ((10_000, 2000), (5, 2)):
        monkeypatch.setattr(common, "MOST_HOT", most)
        monkeypatch.setattr(common, "LEAST_HOT", least)
        monkeypatch.setattr(suffixes, "SORTED_CLASSES", 20_000 if most > 5 else 3)
        got = {(r.doc_id, r.start_word, r.end_word, r.first_doc_id, r.n_redundant) for r in suffixes.repeated_passages(docs, 12, 4).collect()}
        assert got == want


def test_neighbours_in_suffix_order_share_windows():
    """Against all pairs of suffixes of one gram: window length 6, gram 2."""
    rng = np.random.default_rng(8)
    left, right = rng.integers(0, 2, (200, 4)), rng.integers(0, 2, (200, 4))
    order = np.lexsort(right.T[::-1])
    left, right = left[order], right[order]
    before = np.ma.masked_all((200, 5), np.int64)
    lowest = rng.integers(0, 2, 200)
    for i in range(200):
        for j in range(lowest[i], 5):
            before[i, j - lowest[i]] = hash(tuple(left[i, 4 - j :].tolist()))
    a = rng.integers(0, 20, 200)
    got = set(zip(*(x.tolist() for x in suffixes.shared_windows(np.zeros(200, np.int64), right.astype(np.uint64), before, lowest, a, a, 6, 2))))
    want = set()
    for j in range(5):
        rows = [i for i in range(200) if lowest[i] <= j]
        for i in rows:
            same = [a[k] for k in rows if (left[k, 4 - j :] == left[i, 4 - j :]).all() and (right[k, : 4 - j] == right[i, : 4 - j]).all()]
            if min(same) != max(same):
                want.add((i, j, int(min(same))))
    assert got == want
