import random
import re

from locpref.llm import quality
from locpref.llm.queries import op6_quality

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute(text):
    t = text or ""
    w = WORD.findall(t)
    seen = {}
    for i in range(len(w) - 4):
        seen.setdefault(tuple(w[i : i + 5]), []).append(i)
    covered = {p for at in seen.values() if len(at) > 1 for i in at for p in range(i, i + 5)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    failed = len(w) < 10 or 100 * len(covered) > 20 * len(w)
    return (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered), failed)


def test_counts(spark):
    rng = random.Random(0)
    texts = [None, "", " \n\t", "a", "a b c d e", "a b c d e a b c d e", "x " * 4000, "é#ü*\nñ<>\x0b\x0c y\ny \ny"]
    texts += [" ".join(rng.choice(["a", "b", "c", "\n", "dd|", "é"]) for _ in range(rng.randrange(120))) for _ in range(200)]
    docs = spark.createDataFrame([(i, t, 1) for i, t in enumerate(texts)], "doc_id long, text string, kept int")
    rows = quality.judge(docs, quality.DecisionList(())).collect()
    assert len(rows) == len(texts)
    for r in rows:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == brute(texts[r.doc_id])
        assert r.kept == (not r.base_failed)
    assert quality.judge(docs.limit(0), quality.DecisionList(())).count() == 0


def test_covering_finds_a_planted_list():
    rng = random.Random(1)
    rows = []
    for _ in range(900):
        r = {t: rng.random() for t in quality.TESTS}
        bad = (r["symbol_share"] > 0.7 and r["word_length"] <= 0.5) or r["upper_share"] > 0.9
        rows.append((r, not bad))
    rules = quality.learn(rows)
    assert len(rules.rules) >= 2
    assert sum(rules.verdict(r) == y for r, y in rows) > 0.97 * len(rows)


def test_op6(spark):
    d = "/root/testdata/sf0.1"
    docs = {r.doc_id: r.text for r in spark.read.parquet(f"{d}/documents.parquet").collect()}
    rows = op6_quality(spark, d).collect()
    assert len(rows) == len(docs)
    for r in rows:
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == brute(docs[r.doc_id])
    good = {r.doc_id: r.quality for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    judged = [(r.kept, good[r.doc_id]) for r in rows if r.doc_id in good]
    kept = sum(k for k, y in judged if y) / sum(y for _, y in judged)
    cut = sum(not k for k, y in judged if not y) / sum(not y for _, y in judged)
    print("good kept", kept, "bad cut", cut)
    assert kept > 0.97 and cut > 0.8


def test_column_equals_verdict(spark):
    rules = quality.DecisionList((quality.Rule((("n_words", True, 3.0), ("symbol_share", False, 0.2)), False), quality.Rule((("n_words", False, 1.0),), False)))
    docs = spark.createDataFrame([(1, "a b c d"), (2, "# # # #"), (3, "a"), (4, "a b")], "doc_id long, text string")
    got = {r.doc_id: r.k for r in quality.counted(docs).withColumn("k", rules.column()).select("doc_id", "k").collect()}
    assert got == {1: False, 2: True, 3: False, 4: True}
