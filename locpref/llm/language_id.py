"""Language identification by segmentation-marginalised unigrams.

Each language has a probability for every piece of a fixed public vocabulary. The
probability of a word is the sum over all its segmentations into pieces, which a
forward pass over the word's positions gives; a text scores the sum of its words' log
probabilities. Characters without a piece fall back to the vocabulary's byte pieces.
The piece probabilities are fitted by expectation maximisation: forward and backward
passes give expected piece counts.

Texts are cut into runs of letters (category L; number forms and enclosed digits
aren't letters), lower-cased. Passes run over all distinct words of a slice at once,
edges sorted by the position they end at; words too long for plain products are summed
on their own with rescaling, in training too.

Training: a bounded sample (``per_language`` documents of each language, those with the
least hashes of their ids). Every labelled language is learned: the model has a column
for each. Defined cases: a null text or one without letters is ``und`` with score 0;
so is every text when no labelled document is there; repeated rows are scored each on
its own.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import arrow_rows, crc_mod

#: Documents of a language that the model learns from.
PER_LANGUAGE = 2_000
#: Longer words are summed with rescaling, where plain products could underflow.
PLAIN_LENGTH = 40
MEMO_ENTRIES = 300_000
#: Characters of texts that are held as words at a time, or one text.
PART_CHARS = 1_500_000
UNKNOWN = "und"


@lru_cache(maxsize=2)
def pieces_of(path: str) -> tuple[dict[str, int], int, list[int]]:
    """Piece ids, the longest piece's length and the ids of the 256 byte pieces."""
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=path)
    ids = {m.id_to_piece(i): i for i in range(m.get_piece_size()) if not m.is_control(i) and not m.is_unknown(i) and not m.is_byte(i)}
    byte = [m.piece_to_id(f"<0x{b:02X}>") for b in range(256)]
    return ids, max(map(len, ids)), byte


@lru_cache(maxsize=1)
def _letters():
    import regex

    return regex.compile(r"\p{L}+")


def words_of(text: str | None) -> list[str]:
    return _letters().findall((text or "").lower())


class PieceTrie:
    """The vocabulary's trie as one open hash table: (node, character) to child node."""

    def __init__(self, path: str):
        ids, self.longest, self.byte = pieces_of(path)
        child: dict[int, int] = {}
        piece = [-1]
        for text, i in ids.items():
            node = 0
            for c in text[: self.longest + 1]:
                key = node << 21 | ord(c)
                if key not in child:
                    child[key] = len(piece)
                    piece.append(-1)
                node = child[key]
            if len(text) <= self.longest:
                piece[node] = i
        self.piece = np.array(piece)
        bits = max(4, (2 * len(child)).bit_length())
        self.shift = np.uint64(64 - bits)
        self.keys, self.children = np.full((1 << bits) + 64, -1, np.int64), np.zeros((1 << bits) + 64, np.int64)
        keys = np.fromiter(child, np.int64, len(child))
        for key, slot, node in zip(child, self.slots(keys).tolist(), child.values(), strict=True):
            while self.keys[slot] >= 0:
                slot += 1
            self.keys[slot], self.children[slot] = key, node

    def slots(self, keys: np.ndarray) -> np.ndarray:
        return ((keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> self.shift).astype(np.int64)

    def step(self, node: np.ndarray, char: np.ndarray) -> np.ndarray:
        """Child nodes, 0 where there is none."""
        key = node << 21 | char
        slot = self.slots(key)
        out = np.zeros(len(key), np.int64)
        left = np.arange(len(key))
        while len(left):
            held = self.keys[slot[left]]
            hit = held == key[left]
            out[left[hit]] = self.children[slot[left[hit]]]
            left = left[~hit & (held >= 0)]
            slot[left] += 1
        return out


@lru_cache(maxsize=2)
def trie_of(path: str) -> PieceTrie:
    return PieceTrie(path)


class Lattice:
    """The pieces of many words, each with its start mark, as arrays of edges.

    All positions of all words go down the trie at once; those that no piece goes on
    from drop out.
    """

    def __init__(self, words: list[str], path: str):
        trie = trie_of(path)
        marked = "▁" + "▁".join(words) if words else ""
        char = np.frombuffer(marked.encode("utf-32-le"), np.uint32).astype(np.int64)
        self.n = len(words)
        self.length = np.fromiter((len(w) + 1 for w in words), np.int64, self.n)
        base = np.cumsum(self.length) - self.length
        word_of = np.repeat(np.arange(self.n), self.length)
        end_of = np.repeat(base + self.length, self.length)
        at, node = np.arange(len(char)), np.zeros(len(char), np.int64)
        found: list[tuple[np.ndarray, ...]] = []
        bare = np.ones(len(char), bool)
        for k in range(trie.longest):
            inside = at + k < end_of[at]
            at, node = at[inside], node[inside]
            node = trie.step(node, char[at + k])
            at, node = at[node > 0], node[node > 0]
            if not len(at):
                break
            piece = trie.piece[node]
            hit = piece >= 0
            found.append((at[hit], np.full(int(hit.sum()), k + 1), piece[hit]))
            if k == 0:
                bare[at[hit]] = False
        rest = np.flatnonzero(bare)  # characters without a piece: byte pieces
        spelled = [[trie.byte[b] for b in chr(c).encode()] for c in char[rest].tolist()]
        found.append((rest, np.ones(len(rest), np.int64), np.array([x[0] for x in spelled], np.int64)))
        start, size, self.piece = (np.concatenate(x) for x in zip(*found, strict=True))
        self.word = word_of[start]
        self.start = start - base[self.word]
        self.end = self.start + size
        first = len(start) - len(rest)
        self.extra = [(first + i, tuple(x)) for i, x in enumerate(spelled) if len(x) > 1]

    def edges(self) -> list[tuple[int, int, int, tuple[int, ...]]]:
        """Word, start, end and piece ids of every edge."""
        more = dict(self.extra)
        return [(w, s, e, more.get(i, (p,))) for i, (w, s, e, p) in enumerate(zip(self.word.tolist(), self.start.tolist(), self.end.tolist(), self.piece.tolist(), strict=True))]

    def weights(self, p: np.ndarray) -> np.ndarray:
        out = p[self.piece]
        for at, ids in self.extra:
            out[at] = np.prod(p[list(ids)], axis=0)
        return out

    def pass_over(self, weight: np.ndarray, backward: bool = False) -> np.ndarray:
        """Sums over all segmentations up to (or from) every position of every word."""
        most = int(self.length.max(initial=0)) + 1
        out = np.zeros((self.n, most, weight.shape[1]))
        source, target = (self.end, self.start) if backward else (self.start, self.end)
        if backward:
            out[np.arange(self.n), self.length] = 1
        else:
            out[:, 0] = 1
        order = np.lexsort((self.word, target))
        cuts = np.searchsorted(target[order], np.arange(most + 1))
        for at in range(most - 1, -1, -1) if backward else range(1, most):
            own = order[cuts[at] : cuts[at + 1]]
            if len(own):
                w = self.word[own]
                new = np.flatnonzero(np.diff(w, prepend=-1))
                out[w[new], at] = np.add.reduceat(out[w, source[own]] * weight[own], new, axis=0)
        return out


def long_word(word: str, p: np.ndarray, path: str) -> np.ndarray:
    """Log probability of a long word by language, rescaled at every position."""
    longest = pieces_of(path)[1]
    ids, _, byte = pieces_of(path)
    w = "▁" + word
    rows: dict[int, np.ndarray] = {0: np.ones(p.shape[1])}
    log = np.zeros(p.shape[1])
    for e in range(1, len(w) + 1):
        total = np.zeros(p.shape[1])
        for s in range(max(0, e - longest), e):
            i = ids.get(w[s:e])
            if i is not None:
                total += rows[s] * p[i]
            elif e == s + 1:
                total += rows[s] * np.prod(p[[byte[b] for b in w[s].encode()]], axis=0)
        rows.pop(e - longest, None)
        for s in rows:
            rows[s] = rows[s] / total
        log += np.log(total)
        rows[e] = np.ones(p.shape[1])
    return log


def long_counts(word: str, p: np.ndarray, path: str) -> dict[int, float]:
    """Expected counts of the pieces in one long word, by forward and backward sums rescaled at every position."""
    ids, longest, byte = pieces_of(path)
    w = "▁" + word
    n = len(w)
    spelled = {c: [byte[b] for b in c.encode()] for c in set(w) if c not in ids}
    edges: list[list[tuple[int, float, list[int]]]] = [[] for _ in range(n + 1)]  # by end: start, weight, pieces
    for s in range(n):
        for e in range(s + 1, min(n, s + longest) + 1):
            i = ids.get(w[s:e])
            if i is not None:
                edges[e].append((s, p[i], [i]))
            elif e == s + 1:
                edges[e].append((s, float(np.prod(p[spelled[w[s]]])), spelled[w[s]]))
    scale = np.ones(n + 1)  # the sum up to a position is the product of the scales up to it
    for e in range(1, n + 1):
        scale[e] = sum(x / np.prod(scale[s + 1 : e]) for s, x, _ in edges[e])
    b = np.zeros(n + 1)
    b[n] = 1
    out: dict[int, float] = {}
    for e in range(n, 0, -1):
        for s, x, pieces in edges[e]:
            share = x * b[e] / np.prod(scale[s + 1 : e + 1])
            b[s] += share
            for i in pieces:
                out[i] = out.get(i, 0.0) + share
    return out


class Model:
    def __init__(self, languages: list[str], p: np.ndarray, path: str):
        self.languages, self.p, self.path = languages, p, path
        self.memo: dict[str, int] = {}
        self.logs = np.zeros((0, len(languages)))

    def __getstate__(self) -> tuple:
        return self.languages, self.p, self.path

    def __setstate__(self, state: tuple) -> None:
        self.__init__(*state)

    def word_logs(self, words: list[str]) -> np.ndarray:
        """Log probabilities (words x languages)."""
        out = np.zeros((len(words), len(self.languages)))
        short = [i for i, w in enumerate(words) if len(w) <= PLAIN_LENGTH]
        for at in range(0, len(short), 4096):
            part = short[at : at + 4096]
            net = Lattice([words[i] for i in part], self.path)
            out[part] = np.log(net.pass_over(net.weights(self.p))[np.arange(net.n), net.length])
        for i, w in enumerate(words):
            if len(w) > PLAIN_LENGTH:
                out[i] = long_word(w, self.p, self.path)
        return out

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        names: list[str] = []
        scores: list[float] = []
        at = 0
        while at < len(texts):  # PART_CHARS characters at a time, or one text
            cut, size = at, 0
            while cut < len(texts) and (cut == at or size + len(texts[cut] or "") <= PART_CHARS):
                size += len(texts[cut] or "")
                cut += 1
            for name, score in self._predict([words_of(t) for t in texts[at:cut]]):
                names.append(name)
                scores.append(score)
            at = cut
        return names, scores

    def _predict(self, found: list[list[str]]) -> Iterator[tuple[str, float]]:
        wanted = set().union(*found)
        missing = list(wanted.difference(self.memo))
        if len(self.memo) + len(missing) > MEMO_ENTRIES:
            self.memo, self.logs, missing = {}, self.logs[:0], list(wanted)
        if missing:
            old = len(self.memo)
            self.memo.update(zip(missing, range(old, old + len(missing)), strict=True))
            self.grow(self.word_logs(missing), old)
        for f in found:
            if not f or not self.languages:
                yield UNKNOWN, 0.0
                continue
            total = self.logs[list(map(self.memo.__getitem__, f))].sum(axis=0) / math.sqrt(len(f))
            e = np.exp(total - total.max())
            k = int(e.argmax())
            yield self.languages[k], float(e[k] / e.sum())

    def grow(self, rows: np.ndarray, at: int) -> None:
        """Append rows to the table of logs, which doubles when it is full."""
        if len(self.logs) < at + len(rows):
            self.logs = np.concatenate([self.logs[:at], np.zeros((max(at, 2 * len(rows)), rows.shape[1]))])
        self.logs[at : at + len(rows)] = rows


def _maximised(counts: np.ndarray, prior: float = 200.0) -> np.ndarray:
    """Piece probabilities by language, drawn to the mean of all languages, none zero."""
    share = counts / np.maximum(counts.sum(axis=0), 1e-9)
    base = share.mean(axis=1, keepdims=True) * 0.99 + 0.01 / len(counts)
    total = counts.sum(axis=0)
    return (counts + prior * base) / (total + prior)


def sampled_ids(train: DataFrame, n_of: dict[str, int], per_language: int) -> DataFrame:
    """``doc_id, lang`` of the documents with a language's ``per_language`` least hashes of the id.

    A language's size gives a bound that about twice as many hashes are under, so only
    those are dealt out and sorted, whatever the language's share of all rows.
    """
    spark = train.sparkSession
    reach = [(k, min(1.0, (2 * per_language + 200) / n)) for k, n in n_of.items()]
    bound = spark.createDataFrame([(k, int(x * 2.0**63) if x < 1 else 2**63 - 1) for k, x in reach], "lang string, bound long")
    hashed = train.select("doc_id", "lang", F.xxhash64("doc_id").bitwiseAND(F.lit(2**63 - 1)).alias("_h"))
    near = hashed.join(F.broadcast(bound), "lang").where("_h <= bound").select("doc_id", "lang", "_h").distinct()  # a row for each language
    by_hash = Window.partitionBy("lang").orderBy("_h", "doc_id")
    return near.withColumn("_r", F.row_number().over(by_hash)).where(F.col("_r") <= per_language).select("doc_id", "lang")


def fit(docs: DataFrame, path: str, per_language: int = PER_LANGUAGE, rounds: int = 3) -> Model:
    """Fit on documents with a language whose id isn't in the held-out part."""
    train = docs.where((crc_mod("doc_id", 3) != 1) & F.col("lang").isNotNull())
    found = train.groupBy("lang").agg(F.count("*").alias("n")).collect()  # a row for each language
    languages = sorted(r.lang for r in found)
    size = max(max(pieces_of(path)[0].values()), max(pieces_of(path)[2])) + 1
    if not languages:
        return Model([], np.zeros((size, 0)), path)
    ids = sampled_ids(train, {r.lang: r.n for r in found}, per_language)
    sample = docs.select("doc_id", "lang", "text").join(F.broadcast(ids), ["doc_id", "lang"])  # per_language * languages ids at most
    number = {x: i for i, x in enumerate(languages)}
    counted = pa.schema([("lang", pa.int32()), ("word", pa.string()), ("n", pa.int64())])

    def count(cols: dict[str, list]) -> dict[str, list]:
        c: Counter = Counter()
        for lang, text in zip(cols["lang"], cols["text"], strict=True):
            k = number[lang]
            c.update((k, w) for w in words_of(text))
        return {"lang": [k for k, _ in c], "word": [w for _, w in c], "n": list(c.values())}

    words = sample.mapInArrow(arrow_rows(count, counted), "lang int, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n")).cache()
    expected = pa.schema([("lang", pa.int32()), ("piece", pa.int32()), ("c", pa.float64())])
    p = np.full((size, len(languages)), 1.0 / size)
    for _ in range(rounds):

        def expect(cols: dict[str, list], p: np.ndarray = p) -> dict[str, list]:
            long = [i for i, x in enumerate(cols["word"]) if len(x) > PLAIN_LENGTH]
            short = [i for i, x in enumerate(cols["word"]) if len(x) <= PLAIN_LENGTH]
            net = Lattice([cols["word"][i] for i in short], path)
            lang, n = np.array([cols["lang"][i] for i in short], np.int64), np.array([cols["n"][i] for i in short], float)
            w = net.weights(p)[np.arange(len(net.word)), lang[net.word]][:, None]
            a, b = net.pass_over(w), net.pass_over(w, True)
            whole = a[np.arange(net.n), net.length, 0]
            c = a[net.word, net.start, 0] * w[:, 0] * b[net.word, net.end, 0] * (n / whole)[net.word]
            key = lang[net.word] * size + net.piece
            for at, ids in net.extra:
                key = np.append(key, lang[net.word[at]] * size + np.array(ids[1:]))
                c = np.append(c, np.full(len(ids) - 1, c[at]))
            for i in long:
                k = cols["lang"][i]
                own = long_counts(cols["word"][i], p[:, k], path)
                key = np.append(key, k * size + np.fromiter(own, np.int64, len(own)))
                c = np.append(c, cols["n"][i] * np.fromiter(own.values(), float, len(own)))
            keys, place = np.unique(key, return_inverse=True)
            return {"lang": keys // size, "piece": keys % size, "c": np.bincount(place, c)}

        got = words.mapInArrow(arrow_rows(expect, expected, 2048), "lang int, piece int, c double").groupBy("lang", "piece").agg(F.sum("c").alias("c")).collect()  # vocabulary * languages rows at most
        counts = np.zeros((size, len(languages)))
        for r in got:
            counts[r.piece, r.lang] = r.c
        p = _maximised(counts)
    words.unpersist()
    return Model(languages, p, path)


def predict(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, lang_pred, score`` for every row."""
    schema = pa.schema([("doc_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64())])
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))

    def each(cols: dict[str, list]) -> dict[str, list]:
        names, scores = model.predict(cols["text"])
        return {"doc_id": cols["doc_id"], "lang_pred": names, "score": scores}

    return src.mapInArrow(arrow_rows(each, schema), "doc_id long, lang_pred string, score double")
