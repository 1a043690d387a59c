"""The pipeline against a plain-Python version of every stage."""

import numpy as np
from tokenizers import Tokenizer

import corpus_pipeline as cp
from locpref.llm import packing, suffixes, toxicity
from locpref.llm.queries import tokenizer_paths

from .test_minhash import brute as groups
from .test_secrets import brute as spans



def passages_cut(texts):
    """Texts without the words that a window of an earlier document covers."""
    words = {i: [(m.start(), m.end(), m.group()) for m in suffixes.WORD.finditer(t)] for i, t in texts.items() if t}
    seen = {}
    for i, w in words.items():
        for s in range(len(w) - 49):
            seen.setdefault(tuple(x[2] for x in w[s : s + 50]), set()).add(i)
    out = dict(texts)
    for i, w in words.items():
        gone = {p for s in range(len(w) - 49) if min(seen[tuple(x[2] for x in w[s : s + 50])]) < i for p in range(s, s + 50)}
        if not gone:
            continue
        runs = suffixes._runs(np.array(sorted(gone)), np.array(sorted(gone)) + 1)
        out[i] = suffixes.without_words(texts[i], runs)
        if not suffixes.WORD.search(out[i]):
            del out[i]
    return out


def test_stages(spark):
    d = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{d}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    got = docs
    model = toxicity.fit(docs, spark.read.parquet(f"{d}/labels.parquet"))
    for name, stage in cp.STAGES:
        before = got
        got = stage(spark, got, d).cache()
        if name == "toxicity":
            texts = {i: t for i, t in texts.items() if model.score(t) < 0.5}
        elif name == "near_duplicates":
            texts = {i: t for i, t in texts.items() if groups(texts, 5)[i][1] == i} if len(texts) < 5 else {i: t for (i, t), (_, r) in zip(sorted(texts.items()), [v for _, v in sorted(groups(texts, 5).items())]) if r == i}
        elif name == "repeated_passages":
            texts = passages_cut(texts)
        elif name == "secrets":
            for i, t in texts.items():
                for s, _, e in reversed(spans(t)):
                    assert t[s:e] not in {r.doc_id: r.text for r in got.where(got.doc_id == i).collect()}[i]
            assert {r.doc_id for r in got.collect()} == texts.keys()
            texts = {r.doc_id: r.text for r in got.collect()}
        if name != "packing":
            assert got.columns == docs.columns and got.schema["text"].dataType == docs.schema["text"].dataType
            assert {r.doc_id: r.text for r in got.collect()} == texts
            assert before.count() >= got.count() > 0
    tok = Tokenizer.from_file(tokenizer_paths()[0])
    rows = {}
    for r in got.collect():
        rows.setdefault(r.doc_id, []).append(r)
    assert rows.keys() == texts.keys()
    for i, pieces in rows.items():
        ids = np.concatenate([np.frombuffer(p.tokens, "<u4") for p in sorted(pieces, key=lambda p: p.start)]).tolist()
        assert ids == [*tok.encode(texts[i] or "", add_special_tokens=False).ids, 0]
        assert [p.length for p in sorted(pieces, key=lambda p: p.start)] == packing.binary_lengths(len(ids), 1024)


def test_run(spark):
    out = cp.run(spark, "/root/testdata/sf0.001")
    assert out.count() > 0 and out.columns == ["doc_id", "start", "length", "tokens", "doc_tokens", "sequence_id", "offset"]


def test_stages_on_odd_rows(spark, tmp_path):
    schema = "doc_id long, text string, lang string, source string, n_chars long, kept boolean, score double, found string"
    same = " ".join(f"w{i}" for i in range(70))
    rows = [(None, None), (None, same), (1, None), (2, ""), (3, same), (3, same), (4, same), (5, "p " * 90_000), (6, "token = '" + "a1" * 30 + "'")]
    docs = spark.createDataFrame([(i, t, None, None, None, True, None, "x") for i, t in rows], schema)
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    for empty in (False, True):
        got = docs.limit(0) if empty else docs
        for name, stage in cp.STAGES[:-1]:
            got = stage(spark, got, str(tmp_path))
            assert got.columns == docs.columns
        ids = sorted((r.doc_id for r in got.collect()), key=lambda x: (x is None, x))
        assert ids == ([] if empty else [1, 2, 3, 5, 6, None, None])
        cp.STAGES[-1][1](spark, got, str(tmp_path)).count()
