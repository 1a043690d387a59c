import hashlib
import random
import zlib

import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from tokenizers import Tokenizer

from locpref.llm import bpe, packing, token_counts
from locpref.llm.queries import op1_token_counts, op5_packing, op10_byte_bpe, tokenizer_paths
from locpref.llm.vocab import ByteVocabulary, ranks_of

DOCS = "doc_id long, text string, n_tokens int, section string"
ODD = [(1, None), (2, ""), (3, " "), (4, "a" * 9000), (5, "x\ny\n\nz"), (6, "né‍\U0001f600 ça\n\n ok"), (7, "<|endoftext|> same"), (7, "<|endoftext|> same"), (None, "no id"), (8, "ab" * 5000 + " " * 7000)]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(i, t, 1, "s") for i, t in ODD], DOCS)


def test_rank_queue_equals_library():
    path = P.path("byte_bpe_multi_50k.tiktoken")
    ours = bpe.Encoder(ranks_of(path), P.PATTERN)
    theirs = tiktoken.Encoding("t", pat_str=P.PATTERN, mergeable_ranks=ranks_of(path), special_tokens={})
    back = bpe.Decoder(ranks_of(path))
    rng = random.Random(5)
    texts = ["".join(rng.choice("abcé ñü漢字 \n\t'sll0123!!") for _ in range(rng.randrange(1, 400))) for _ in range(400)] + ["aaaa" * 900, "th" * 3000]
    for t in texts:
        ids = np.frombuffer(ours.encode(t), "<u4").tolist()
        assert ids == theirs.encode_ordinary(t)
        assert back.decode(ours.encode(t)) == t.encode()


def test_rank_queue_takes_lower_ranks_that_appear_meanwhile():
    ranks = {bytes([b]): 200 + b for b in b"abc"} | {b"ab": 5, b"abc": 2, b"abcab": 1}
    piece = b"ababcabcabab"
    queue = bpe.Encoder(ranks, r".+")
    library = tiktoken.Encoding("t", pat_str=r".+", mergeable_ranks=ranks | {bytes([b]): 600 + b for b in range(256) if b not in b"abc"}, special_tokens={})
    assert [np.frombuffer(x, "<u4").tolist() for x in queue.merge([piece, b"abc" * 5])] == [library.encode_ordinary(piece.decode()), library.encode_ordinary("abc" * 5)]


def test_op10(spark, small):
    enc = tiktoken.Encoding("t", pat_str=P.PATTERN, mergeable_ranks=ranks_of(P.path("byte_bpe_multi_50k.tiktoken")), special_tokens={})
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    got = op10_byte_bpe(spark, small).collect()
    assert len(got) == len(texts)
    for r in got:
        raw = np.array(enc.encode_ordinary(texts[r.doc_id] or ""), "<u4").tobytes()
        assert (r.n_tokens, r.ids_sha256) == (len(raw) // 4, hashlib.sha256(raw).hexdigest())
        assert r.decoded_sha256 == hashlib.sha256((texts[r.doc_id] or "").encode()).hexdigest()


def test_fast_ids_are_the_defining_library_s(spark, small):
    paths = tokenizer_paths()
    v, t = ByteVocabulary(*paths), Tokenizer.from_file(paths[0])
    for text in [x or "" for _, x in ODD] + [r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()]:
        assert v.ids(text).tolist() == t.encode(text, add_special_tokens=False).ids


def test_op5(spark, small, odd):
    t = Tokenizer.from_file(tokenizer_paths()[0])
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    rows = op5_packing(spark, small).collect()
    assert len({r.sequence_id for r in rows}) == len(rows)
    by = {}
    for r in rows:
        by.setdefault(r.doc_id, []).append(r)
    assert by.keys() == texts.keys()
    for doc, pieces in by.items():
        ids = [*t.encode(texts[doc] or "", add_special_tokens=False).ids, 0]
        at = 0
        for r in sorted(pieces, key=lambda r: r.start):
            assert (r.start, r.doc_tokens, r.offset) == (at, len(ids), 0)
            assert r.length <= 1024 and r.length & (r.length - 1) == 0
            assert r.ids_crc32 == zlib.crc32(np.array(ids[at : at + r.length], "<u4").tobytes())
            at += r.length
        assert at == len(ids)
    few = packing.pack(odd, *tokenizer_paths()).collect()
    assert {r.doc_id for r in few} == {i for i, _ in ODD}
    assert sum(r.length for r in few if r.doc_id == 1) == 1
    assert packing.pack(odd.limit(0), *tokenizer_paths()).count() == 0
    assert packing.binary_lengths(2 * 1024 + 5, 1024) == [1024, 1024, 4, 1]


def test_op1(spark, small, odd):
    t = Tokenizer.from_file(tokenizer_paths()[0])
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{small}/documents.parquet").collect()}
    got = {(r.doc_id, r.section): r for r in op1_token_counts(spark, small).collect()}
    seen = 0
    for doc, text in texts.items():
        if not text:
            continue
        e = t.encode(text, add_special_tokens=False)
        edges = [0, *(i + 1 for i, c in enumerate(text[:-1]) if c == "\n"), len(text)]
        want = [0] * (len(edges) - 1)
        for a, b in e.offsets:
            held = [max(0, min(b, y) - max(a, x)) for x, y in zip(edges, edges[1:])]
            want[held.index(max(held))] += 1
        assert [got[doc, k].n_tokens for k in range(len(want))] == want
        assert [(got[doc, k].char_start, got[doc, k].char_end) for k in range(len(want))] == list(zip(edges, edges[1:]))
        seen += len(want)
    assert seen == len(got)
    for rule in token_counts.RULES:
        rows = token_counts.count_tokens(odd, *tokenizer_paths(), rule=rule).collect()
        assert {r.doc_id for r in rows} == {i for i, x in ODD if x}
        total = {}
        for r in rows:
            total.setdefault(r.doc_id, [0, r.doc_tokens])[0] += r.n_tokens
        assert all(abs(a - b * (2 if k == 7 else 1)) < 1e-6 for k, (a, b) in total.items())


@pytest.mark.parametrize(("rule", "want"), [("majority", [1, 2]), ("start", [2, 1]), ("fraction", [1.25, 1.75])])
def test_boundary_rules(rule, want):
    share, inside, crossing = token_counts.attribute(np.array([0, 2, 6]), np.array([2, 6, 7]), np.array([0, 3]), 7, rule)
    assert share.tolist() == want
    assert (inside.tolist(), crossing.tolist()) == ([1, 1], [1, 1])


def _library():
    return tiktoken.Encoding("t", pat_str=P.PATTERN, mergeable_ranks=ranks_of(P.path("byte_bpe_multi_50k.tiktoken")), special_tokens={})


def test_slices_without_a_mergeable_pair(spark):
    path, theirs = P.path("byte_bpe_multi_50k.tiktoken"), _library()
    ours = bpe.Encoder(ranks_of(path), P.PATTERN)
    for t in ("Zq", "qzx", "\x00\x01", "", "Zq", "Zq qzx", "a", "Zq"):  # later ones meet a warm memo
        assert np.frombuffer(ours.encode(t), "<u4").tolist() == theirs.encode_ordinary(t)
    for rows in ([(1, "Zq")], [(1, "")], [(1, None)], []):
        df = spark.createDataFrame(rows, "doc_id long, text string")
        got = bpe.decode(bpe.encode(df, path, P.PATTERN), path).collect()
        assert [(r.doc_id, bytes(r.decoded)) for r in got] == [(i, (t or "").encode()) for i, t in rows]


def test_every_code_point_is_cut_as_the_library_does():
    ours, theirs = bpe.Encoder(ranks_of(P.path("byte_bpe_multi_50k.tiktoken")), P.PATTERN), _library()
    odd = sorted(bpe.told_apart())
    assert odd  # the two engines follow different tables
    every = [c for c in range(0x3000) if not 0xD800 <= c < 0xE000] + list(range(0x3000, 0x110000, 97)) + odd
    texts = [t for c in every if not 0xD800 <= c < 0xE000 for t in (chr(c), f"{chr(c)}a 1{chr(c)}  {chr(c)}")]
    for t, ids in zip(texts, ours.encode_all(texts)):
        assert np.frombuffer(ids, "<u4").tolist() == theirs.encode_ordinary(t)


def test_buckets_hold_equal_lengths(spark, odd, tmp_path):
    pieces = packing.pack(odd, *tokenizer_paths()).cache()
    packing.write_buckets(pieces, f"{tmp_path}/b")
    sizes = {r.length: (r.sequences, r.tokens) for r in packing.bucket_sizes(pieces).collect()}
    assert all(n & (n - 1) == 0 for n in sizes) and sum(t for _, t in sizes.values()) == sum(r.length for r in pieces.collect())
    for n, (count, tokens) in sizes.items():
        rows = packing.read_bucket(spark, f"{tmp_path}/b", n).collect()
        assert len(rows) == count and {len(r.tokens) for r in rows} == {4 * n} and tokens == n * count
    assert packing.bucket_sizes(pieces.limit(0)).count() == 0
