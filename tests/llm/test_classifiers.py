import math
import random
import zlib

import numpy as np
import public_tokenizers as P

from locpref.llm import language_id, toxicity
from locpref.llm.queries import op7_toxicity, op9_language

PATH = P.path("piece_bpe_32k.model")


def distance(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (x != y)))
        row = new
    return row[-1]


def test_automaton_and_trie_equal_edit_distance():
    rng = random.Random(4)
    make = lambda: "".join(rng.choice("abcd") for _ in range(rng.randrange(1, 9)))
    terms = sorted({make() for _ in range(60)})
    trie = toxicity.Trie(terms)
    for _ in range(500):
        w = make()
        for k in (0, 1, 2):
            best = min(distance(w, t) for t in terms)
            t, e = trie.near(w, k)
            assert (t >= 0) == (best <= k)
            if t >= 0:
                assert e == best == distance(w, terms[t])


def test_misspellings_and_quotation():
    lex = toxicity.Lexicon(["idiot", "worthless", "lowei-"], [5.0, 4.0, 6.0], frozenset(["worthles"]))
    assert lex.match("Loweichen,") == (2, 0)
    assert lex.match("lowe") is None
    assert lex.match("IDIOT!!") == (0, 0)
    assert lex.match("id1ot,") == (0, 1)
    assert lex.match("idi0t.") == (0, 1)
    assert lex.match("idiiot") == (0, 1)
    assert lex.match("idiot-like") == (0, 0)
    assert lex.match("worthlss") == (1, 1)
    assert lex.match("worthles") is None
    assert lex.match("radio") is None and lex.match("!!") is None
    abuse, quote = toxicity.features("you are an idiot and so on", lex), toxicity.features('he said the word "idiot" is rude', lex)
    assert abuse[0] > 1 and abuse[2] == 0
    assert quote[0] == 0 and quote[2] > 1


def test_op7(spark):
    d = "/root/testdata/sf0.1"
    rows = op7_toxicity(spark, d).toPandas()
    assert len(rows) == spark.read.parquet(f"{d}/documents.parquet").count()
    assert ((rows.score >= 0) & (rows.score <= 1)).all()
    assert (rows.held_out == [zlib.crc32(str(i).encode()) % 5 == 0 for i in rows.doc_id]).all()
    m = rows[rows.held_out].merge(spark.read.parquet(f"{d}/labels.parquet").toPandas(), on="doc_id")
    bad, good = m[m.toxic == 1], m[m.toxic == 0]
    print("toxic recall", bad.predicted.mean(), "false", good.predicted.mean(), len(bad), len(good))
    assert good.predicted.mean() < 0.01
    assert bad.predicted.mean() > 0.55


def test_toxicity_edges(spark):
    docs = spark.createDataFrame([(1, None, 1.0), (2, "", 1.0), (2, "", 1.0), (None, "idiot " * 50_000, 2.0)], "doc_id long, text string, score double")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    model = toxicity.fit(docs, labels)
    assert toxicity.score(docs, model).count() == 4
    assert toxicity.score(docs.limit(0), model).count() == 0
    model = toxicity.Model(toxicity.Lexicon(["idiot"], [6.0]), [2.0, 1.0, 0.1, 0.3, 1.0, -6.0])
    got = {(r.doc_id, r.predicted) for r in toxicity.score(docs, model).collect()}
    assert got == {(1, 0), (2, 0), (None, 1)}


def test_forward_and_backward_sum_all_segmentations():
    rng = np.random.default_rng(0)
    size = 32_000
    p = rng.random((size, 2)) * 1e-2
    words = ["the", "ñandú", "straße", "x", "漢字", "ꙮꙮ"]

    pieces, longest, byte = language_id.pieces_of(PATH)

    def total(w, at, k):
        if at == len(w):
            return 1.0
        out = 0.0
        for e in range(at + 1, min(len(w), at + longest) + 1):
            if w[at:e] in pieces:
                out += p[pieces[w[at:e]], k] * total(w, e, k)
            elif e == at + 1:
                out += math.prod(p[[byte[b] for b in w[at].encode()], k]) * total(w, e, k)
        return out

    net = language_id.Lattice(words, PATH)
    known = {(i, s, e): ids for i, s, e, ids in net.edges()}
    for i, w in enumerate(words):
        w = "▁" + w
        want = {(i, s, e): (pieces[w[s:e]],) for s in range(len(w)) for e in range(s + 1, min(len(w), s + longest) + 1) if w[s:e] in pieces}
        want |= {(i, s, s + 1): tuple(byte[b] for b in w[s].encode()) for s in range(len(w)) if w[s] not in pieces}
        assert {k: v for k, v in known.items() if k[0] == i} == want
    got = net.pass_over(net.weights(p))[np.arange(len(words)), net.length]
    back = net.pass_over(net.weights(p), True)[:, 0]
    for i, w in enumerate(words):
        for k in range(2):
            want = total("▁" + w, 0, k)
            assert abs(got[i, k] / want - 1) < 1e-9 and abs(back[i, k] / want - 1) < 1e-9
        assert np.allclose(language_id.long_word(w, p, PATH), np.log(got[i]))


def test_op9(spark):
    d = "/root/testdata/sf0.01"
    rows = op9_language(spark, d).toPandas()
    docs = spark.read.parquet(f"{d}/documents.parquet").toPandas()
    assert len(rows) == len(docs)
    assert (rows.held_out == [zlib.crc32(str(i).encode()) % 3 == 1 for i in rows.doc_id]).all()
    m = rows[rows.held_out].merge(docs, on="doc_id")
    print("language accuracy", (m.lang == m.lang_pred).mean(), len(m))
    assert (m.lang == m.lang_pred).mean() > 0.97
    assert ((rows.score >= 0) & (rows.score <= 1)).all()


def test_language_edges(spark):
    docs = spark.createDataFrame([(1, None, "en"), (2, "123 !!", "en"), (3, "the and that", None), (None, "der die das", "de"), (5, "le la les " * 9000 + "x" * 50_000, "fr"), (7, "de la que", "fr"), (7, "de la que", "fr")], "doc_id long, text string, lang string")
    model = language_id.fit(docs, PATH)
    got = language_id.predict(docs.withColumn("score", docs.doc_id), model).collect()
    assert len(got) == 7
    assert {(r.doc_id, r.lang_pred, r.score) for r in got if r.doc_id in (1, 2)} == {(1, "und", 0.0), (2, "und", 0.0)}
    empty = language_id.fit(docs.limit(0), PATH)
    assert {r.lang_pred for r in language_id.predict(docs, empty).collect()} == {"und"}


def test_deletions_joined_parts_and_long_words():
    lex = toxicity.Lexicon(["idiot", "worthless", "trash", "donaudampfschifffahrtsgesellschaftskapitaensmuetze"], [5.0, 4.0, 3.0, 2.0], frozenset(["tras"]))
    assert lex.match("idot") == (0, 1)  # the term's length decides, not the misspelled word's
    assert lex.match("trsh") == (2, 1) and lex.match("tras") is None
    assert lex.match("you,idi0t") == (0, 1) and lex.match("oh/idiiot/no") == (0, 1)
    assert lex.match("ido") is None and lex.match("wrthles") == (1, 2)
    assert lex.match("donaudampfschiffahrtsgesellschaftskapitaensmuetze") == (3, 1)
    assert lex.match("x" * 200_000) is None


def brute_match(lex, chunk):
    """By edit distances to every term, no automaton and no filter."""
    low = toxicity._EDGE.sub("", chunk.lower())
    parts = [low] if low.isalnum() else [low, *toxicity._INNER.findall(low)]
    for p in parts:
        if p in lex.words:
            return lex.words[p], 0
        for n in range(1, len(p) + 1):
            if p[:n] in lex.stems:
                return lex.stems[p[:n]], 0
    for p in parts:
        if p in lex.innocent:
            continue
        plain = p.translate(toxicity.LOOKALIKES)
        if not plain.isalpha():
            plain = "".join(c for c in plain if c.isalnum() or c == "*")
        if plain in lex.words:
            return lex.words[plain], 1
        near = [(distance(plain, t), i) for t, i in lex.words.items() if abs(len(t) - len(plain)) <= toxicity.allowed_errors(len(t))]
        near = [(e, i) for e, i in near if e <= toxicity.allowed_errors(len(lex.terms[i]))]
        if near:
            return min(near)[0]
    return None


def test_op7_rows_equal_brute_force(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    rows = {r.doc_id: r for r in op7_toxicity(spark, small).collect()}
    model = toxicity.fit(docs, spark.read.parquet(f"{small}/labels.parquet"))
    lex, known = model.lexicon, {}

    def hit(chunk):
        if chunk not in known:
            known[chunk] = brute_match(lex, chunk) if toxicity._EDGE.sub("", chunk.lower()) else None
        return known[chunk]

    texts = {r.doc_id: r.text for r in docs.collect()}
    assert rows.keys() == texts.keys()
    for i, t in texts.items():
        chunks = (t or "").split()
        found = [(k, hit(c)) for k, c in enumerate(chunks)]
        for k, h in found:
            m = lex.match(chunks[k])
            assert (m is None) == (h is None)
            if m is not None:
                assert m == h if isinstance(h, tuple) else m[1] == h  # several terms can be as near
        sums = [0.0, 0.0, 0.0, 0.0]
        for k, h in found:
            if h is None:
                continue
            term, e = lex.match(chunks[k])
            w, q = lex.weights[term], toxicity.quotation(chunks, k)
            sums[2] += w * q
            sums[1 if e else 0] += w * (1 - q) / max(e, 1)
            sums[3] = max(sums[3], 0 if e else w * (1 - q))
        hits = sum(h is not None for _, h in found)
        f = [*map(math.log1p, sums[:3]), sums[3], min(1.0, 100 * hits / (len(chunks) + 50)), 1.0]
        z = sum(a * b for a, b in zip(f, model.beta))
        want = 1 / (1 + math.exp(-max(-40.0, min(40.0, z))))
        assert abs(rows[i].score - want) < 1e-9 and rows[i].predicted == int(rows[i].score >= 0.5)
        assert rows[i].held_out == (zlib.crc32(str(i).encode()) % 5 == 0)


def test_number_forms_are_no_letters(spark):
    docs = spark.createDataFrame([(1, "½ ² ① Ⅷ ៣", "en"), (2, "der die das", "de"), (3, "the and of", "en"), (6, "a½b", "en")], "doc_id long, text string, lang string")
    model = language_id.fit(docs, PATH)
    got = {r.doc_id: r for r in language_id.predict(docs, model).collect()}
    assert (got[1].lang_pred, got[1].score) == ("und", 0.0) and got[6].lang_pred in ("de", "en")


def test_expected_counts_of_long_words():
    rng = np.random.default_rng(1)
    pieces, _, byte = language_id.pieces_of(PATH)
    p = rng.random((max(max(pieces.values()), max(byte)) + 1, 1)) * 1e-2
    words = ["straße", "international", "漢字x", "ꙮꙮ", "aaaaaaaaaa"]
    net = language_id.Lattice(words, PATH)
    w = net.weights(p)
    a, b = net.pass_over(w), net.pass_over(w, True)
    c = a[net.word, net.start, 0] * w[:, 0] * b[net.word, net.end, 0] / a[net.word, net.length[net.word], 0]
    for i, x in enumerate(words):
        want = {}
        for (k, _, _, ids), v in zip(net.edges(), c):
            for q in ids if k == i else ():
                want[q] = want.get(q, 0.0) + v
        got = language_id.long_counts(x, p[:, 0], PATH)
        assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-9 for k in want)
    assert sum(language_id.long_counts("ab" * 2000, p[:, 0], PATH).values()) > 200


def test_many_languages_and_long_words_are_learned(spark):
    rows = [(9 * i, f"mot{i}uno " * 30 + f"q{i}" * 30, f"l{i:03}") for i in range(230)]
    rows = [r for r in rows if zlib.crc32(str(r[0]).encode()) % 3 != 1]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.fit(docs, PATH, rounds=1)
    assert model.languages == sorted(r[2] for r in rows) and model.p.shape[1] == len(rows)


def test_sampled_ids_are_the_least_hashes(spark):
    docs = spark.range(3000).selectExpr("id % 2800 AS doc_id", "case when id % 10 = 0 then 'b' else 'a' end AS lang", "'x' AS text")
    got = language_id.sampled_ids(docs, {"a": 2700, "b": 300}, 40)
    want = docs.selectExpr("doc_id", "lang", f"xxhash64(doc_id) & {2**63 - 1} AS h").distinct().collect()
    for lang in "ab":
        ids = [r.doc_id for r in sorted((r for r in want if r.lang == lang), key=lambda r: (r.h, r.doc_id))[:40]]
        assert sorted(r.doc_id for r in got.where(f"lang = '{lang}'").collect()) == sorted(ids)


def test_op9_rows_equal_brute_force(spark, small):
    """Scores by a plain sum over segmentations of every word, with the fitted piece probabilities."""
    docs = spark.read.parquet(f"{small}/documents.parquet")
    model = language_id.fit(docs, PATH)
    pieces, longest, byte = language_id.pieces_of(PATH)
    import regex

    known = {}

    def word_log(w):
        if w not in known:
            marked, rows, log = "▁" + w, [np.ones(model.p.shape[1])], np.zeros(model.p.shape[1])
            for e in range(1, len(marked) + 1):
                total = np.zeros(model.p.shape[1])
                for s in range(max(0, e - longest), e):
                    i = pieces.get(marked[s:e])
                    x = model.p[i] if i is not None else np.prod(model.p[[byte[b] for b in marked[s].encode()]], axis=0) if e == s + 1 else 0.0
                    total = total + rows[s] * x
                log, rows = log + np.log(total), [r / total for r in rows] + [np.ones(model.p.shape[1])]
            known[w] = log
        return known[w]

    texts = {r.doc_id: r.text for r in docs.collect()}
    rows = op9_language(spark, small).collect()
    assert len(rows) == len(texts)
    for r in rows:
        words = regex.findall(r"\p{L}+", (texts[r.doc_id] or "").lower())
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1)
        if not words:
            assert (r.lang_pred, r.score) == ("und", 0.0)
            continue
        total = sum(word_log(w) for w in words) / math.sqrt(len(words))
        e = np.exp(total - total.max())
        assert r.lang_pred == model.languages[int(e.argmax())] and abs(r.score - e.max() / e.sum()) < 1e-6


def test_parts_of_terms_rule_no_near_word_out():
    """Words within a term's errors are found by its parts, and unlike words are ruled out without a table of all terms."""
    import random

    rng = random.Random(8)
    terms = sorted({"".join(rng.choice("abcdefgh") for _ in range(rng.randrange(4, 12))) for _ in range(300)})
    lexicon = toxicity.Lexicon(terms, [1.0] * len(terms))
    words = [*terms, *("".join(rng.choice("abcdefgh") for _ in range(rng.randrange(3, 13))) for _ in range(200))]
    for _ in range(600):
        w = list(rng.choice(terms))
        for _ in range(rng.randrange(1, 3)):
            at, kind = rng.randrange(len(w)), rng.randrange(3)
            w[at : at + (kind < 2)] = [] if kind == 0 else [rng.choice("abcdefghz")]
        words.append("".join(w))
    for w in words:
        every = lexicon.trie.near(w, 2, lexicon.bounds)
        some = lexicon.possible(w)
        got = lexicon.trie.near(w, max(lexicon.bounds[i] for i in some), lexicon.bounds, some) if some else (-1, 0)
        assert got[1] == every[1] and (got[0] >= 0) == (every[0] >= 0) or every[1] == 0
    assert toxicity.Lexicon(["abcdefgh"], [1.0]).possible("hgfedcba") == []


def test_a_word_is_matched_once_for_all_its_chunks(monkeypatch):
    seen = []
    lexicon = toxicity.Lexicon(["badword"], [1.0])
    near = lexicon.trie.near
    monkeypatch.setattr(lexicon.trie, "near", lambda w, *a: seen.append(w) or near(w, *a))
    assert [h[1:] for h in lexicon.hits(["badwrd", "badwrd,", "(badwrd)", "Badwrd!"])] == [(0, 1)] * 4 and seen == ["badwrd"]
