"""Toxicity scores from a learned lexicon, misspellings included.

Lexicon: words and word stems that labelled toxic documents hold far more often than
clean ones, with their log odds as weights. Evidence counts once per context (the words
beside it), so copies of one document don't make its words into terms. Each distinct
chunk of a text is matched against the lexicon's trie by walking it together with a
Levenshtein automaton of the chunk: a bit set of chunk positions for every number of
errors. A branch ends when no bit is left. How many errors count is up to the term, not
to the misspelled word. Chunks joined by punctuation are matched whole and part by part.
Words that clean documents use are innocent neighbours, not misspellings. Stems match
exactly: a stem is no word that one could misspell.

A hit's window of words tells quotation from abuse: quotation marks around it or a
reporting word near it move its weight to a quoted sum. A logistic model over the sums
gives the score.

Labels: a bounded sample (``max_train``, by hash of the id) of labelled rows; nothing
but the text enters a score. The lexicon holds every term that passes the thresholds on
those rows, whatever its length. Defined cases: a null or empty text has no hits and gets
the model's base score; repeated rows are scored each on its own; without labelled
rows of both kinds every score is the share of toxic labels (0 if there are none).
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_rows, crc_mod, release, slices

#: Labelled documents that a model is fitted on at most.
MAX_TRAIN = 20_000
#: Lengths of stems that are looked at.
STEMS = range(4, 9)
WINDOW = 6
MEMO_ENTRIES = 250_000
# Reporting words, and characters that stand for letters.
REPORTING = frozenset("said says wrote writes quoted quote quotes called calls word words term terms meaning means sagte schrieb wort nannte dit écrit mot appelé dijo escribió palabra llamó".split())
LOOKALIKES = str.maketrans("0134578@$!", "oieastbasi")
QUOTES = "\"'“”„«»‘’"

_INNER = re.compile(r"[^\W_]+")
_EDGE = re.compile(r"^[\W_]+|[\W_]+$")


def allowed_errors(length: int) -> int:
    """Errors that a term of this length may have."""
    return 0 if length < 5 else 1 if length < 8 else 2


def letters_of(word: str) -> int:
    """The set of a word's characters as bits, some of which share one."""
    out = 0
    for c in word:
        out |= 1 << (ord(c) & 63)
    return out


class Trie:
    def __init__(self, terms: list[str]):
        self.child: list[dict[str, int]] = [{}]
        self.term: list[int] = [-1]
        self.paths: list[list[int]] = []
        for i, t in enumerate(terms):
            at, path = 0, []
            for c in t:
                if c not in self.child[at]:
                    self.child[at][c] = len(self.child)
                    self.child.append({})
                    self.term.append(-1)
                at = self.child[at][c]
                path.append(at)
            self.term[at] = i
            self.paths.append(path)

    def near(self, word: str, errors: int, bounds: list[int] | None = None, among: list[int] | None = None) -> tuple[int, int]:
        """Term with the least edit distance to the word, at most ``errors`` and the term's own bound; (-1, 0) if there is none.

        With ``among``, only the branches of these terms are walked.
        """
        branches = None if among is None else {n for t in among for n in self.paths[t]}
        mask: dict[str, int] = {}
        for i, c in enumerate(word):
            mask[c] = mask.get(c, 0) | 1 << i
        accept, full = 1 << len(word), (1 << len(word) + 1) - 1
        best, found = errors + 1, -1
        state = [1]
        for _ in range(errors):
            state.append(state[-1] | state[-1] << 1 & full)
        stack = [(0, state)]
        while stack:
            node, state = stack.pop()
            t = self.term[node]
            if t >= 0:
                for e in range(min(best, (errors if bounds is None else min(errors, bounds[t])) + 1)):
                    if state[e] & accept:
                        best, found = e, t
                        break
            for c, child in self.child[node].items():
                if branches is not None and child not in branches:
                    continue
                hit = mask.get(c, 0)
                row = (state[0] & hit) << 1
                new, some = [row], row
                for e in range(1, errors + 1):
                    before = state[e - 1]
                    row = (state[e] & hit) << 1 | before | before << 1 & full | row << 1 & full
                    new.append(row)
                    some |= row
                if some:
                    stack.append((child, new))
        return found, best if found >= 0 else 0


@dataclass
class Lexicon:
    """Terms with weights: whole words, and stems (marked by a hyphen at the end)."""

    terms: list[str]
    weights: list[float]
    innocent: frozenset[str] = frozenset()

    def __post_init__(self) -> None:
        self.memo: dict[str, tuple[int, int] | None] = {}
        self.parts: dict[str, tuple[int, int] | None] = {}
        self.words = {t: i for i, t in enumerate(self.terms) if t[-1] != "-"}
        self.stems = {t[:-1]: i for i, t in enumerate(self.terms) if t[-1] == "-"}
        self.lengths = sorted({len(t) for t in self.stems})
        self.number = list(self.words.values())
        self.trie = Trie(list(self.words))
        self.bounds = [allowed_errors(len(t)) for t in self.words]
        self.letters = [letters_of(t) for t in self.words]
        self.parts_of: dict[int, dict[str, list[tuple[int, int, int, int]]]] = {}
        for i, (t, b) in enumerate(zip(self.words, self.bounds, strict=True)):
            cuts = [len(t) * k // (b + 1) for k in range(b + 2)] if b else []
            for x, y in zip(cuts, cuts[1:], strict=False):
                self.parts_of.setdefault(y - x, {}).setdefault(t[x:y], []).append((i, x, len(t), b))

    def __getstate__(self) -> tuple:
        return self.terms, self.weights, self.innocent

    def __setstate__(self, state: tuple) -> None:
        self.terms, self.weights, self.innocent = state
        self.__post_init__()

    def exact(self, word: str) -> int | None:
        found = self.words.get(word)
        if found is not None:
            return found
        for n in self.lengths:
            found = self.stems.get(word[:n])
            if found is not None:
                return found
        return None

    def possible(self, word: str) -> list[int]:
        """The terms that the word's parts and letters don't rule out.

        Of a term in one part more than it may have errors, a word that is near enough
        holds one part as it is, moved by no more places than there are errors.
        """
        n, found = len(word), set()
        for size, table in self.parts_of.items():
            for i in range(n - size + 1):
                for t, at, length, b in table.get(word[i : i + size], ()):
                    if abs(at - i) <= b and abs(length - n) <= b:
                        found.add(t)
        if not found:
            return []
        own = letters_of(word)
        return [t for t in sorted(found) if (self.letters[t] & ~own).bit_count() <= self.bounds[t] - max(0, n - len(self.trie.paths[t])) and (own & ~self.letters[t]).bit_count() <= self.bounds[t] - max(0, len(self.trie.paths[t]) - n)]

    def match(self, chunk: str) -> tuple[int, int] | None:
        """Term and edit distance for a chunk between white space."""
        low = _EDGE.sub("", chunk.lower())
        if not low:
            return None
        for part in (low,) if low.isalnum() else (low, *_INNER.findall(low)):
            found = self.exact(part)
            if found is not None:
                return found, 0
        if not self.words:
            return None
        for part in (low,) if low.isalnum() else (low, *_INNER.findall(low)):
            found = self.misspelled(part)
            if found is not None:
                return found
        return None

    def misspelled(self, low: str) -> tuple[int, int] | None:
        """The nearest term of a word; the same for all chunks that hold the word."""
        try:
            return self.parts[low]
        except KeyError:
            if len(self.parts) >= MEMO_ENTRIES:
                self.parts.clear()
            found = self.parts[low] = self.nearest(low)
            return found

    def nearest(self, low: str) -> tuple[int, int] | None:
        if low in self.innocent:
            return None
        plain = low.translate(LOOKALIKES)
        if not plain.isalpha():
            plain = "".join(c for c in plain if c.isalnum() or c == "*")
        if plain in self.words:
            return self.words[plain], 1
        some = self.possible(plain)
        if some:
            t, e = self.trie.near(plain, max(self.bounds[i] for i in some), self.bounds, some)
            if t >= 0:
                return self.number[t], e
        return None

    def hits(self, chunks: list[str]) -> list[tuple[int, int, int]]:
        """Position, term and distance of every hit."""
        memo, out = self.memo, []
        for i, c in enumerate(chunks):
            try:
                m = memo[c]
            except KeyError:
                m = self.match(c)
                if len(memo) >= MEMO_ENTRIES:
                    memo.clear()
                memo[c] = m
            if m is not None:
                out.append((i, *m))
        return out


def quotation(chunks: list[str], i: int) -> float:
    """From 0 (abuse) to 1 (quotation) by the window around chunk i."""
    own = chunks[i]
    if own[0] in QUOTES and own.rstrip(".,;:!?")[-1] in QUOTES:
        return 1.0
    left, right = chunks[max(0, i - WINDOW) : i + 1], chunks[i : i + WINDOW + 1]
    opened = any(c[0] in QUOTES for c in left) and any(c.rstrip(".,;:!?")[-1:] in QUOTES and c.rstrip(".,;:!?")[-1:] for c in right)
    told = any(_EDGE.sub("", c.lower()) in REPORTING for c in left[:-1] + right[1:])
    return 0.5 * opened + 0.5 * told


N_FEATURES = 6


def features(text: str | None, lexicon: Lexicon) -> list[float]:
    chunks = (text or "").split()
    exact = fuzzy = quoted = top = 0.0
    hits = lexicon.hits(chunks)
    for i, t, e in hits:
        w, q = lexicon.weights[t], quotation(chunks, i)
        quoted += w * q
        if e == 0:
            exact += w * (1 - q)
            top = max(top, w * (1 - q))
        else:
            fuzzy += w * (1 - q) / e
    return [math.log1p(exact), math.log1p(fuzzy), math.log1p(quoted), top, min(1.0, 100 * len(hits) / (len(chunks) + 50)), 1.0]


@dataclass
class Model:
    lexicon: Lexicon
    beta: list[float]

    def score(self, text: str | None) -> float:
        z = sum(a * b for a, b in zip(features(text, self.lexicon), self.beta, strict=True))
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, z))))


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 50) -> np.ndarray:
    """Newton steps for ridge logistic regression; the last column is the constant."""
    beta = np.zeros(x.shape[1])
    pull = np.full(x.shape[1], ridge)
    pull[-1] = 1e-6
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -40, 40)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(pull * len(x) ** 0.5 + 1e-9), x.T @ (y - p) - pull * len(x) ** 0.5 * beta)
        beta += step * min(1.0, 5 / (1e-9 + np.abs(step).max()))
        if np.abs(step).max() < 1e-6:
            break
    return beta


def train_rows(docs: DataFrame, labels: DataFrame, label_col: str, max_train: int) -> DataFrame:
    """``text, y`` of at most ``max_train`` labelled documents outside the held-out part."""
    picked = labels.where((crc_mod("doc_id", 5) != 0) & F.col(label_col).isNotNull()).select(F.col("doc_id").alias("_id"), (F.col(label_col) > 0).cast("int").alias("y")).groupBy("_id").agg(F.max("y").alias("y"))
    picked = picked.orderBy(F.xxhash64("_id"), "_id").limit(max_train)
    return docs.select(F.col("doc_id").alias("_id"), "text").join(F.broadcast(picked), "_id").select("text", "y")  # max_train ids at most


def _units(word: str) -> list[str]:
    """What a word can be evidence for: itself and its stems."""
    return [word, *(word[:n] + "-" for n in STEMS if n < len(word))]


def _chosen(found: list, n_bad: int, n_good: int, good: dict[str, int], least_odds: float) -> tuple[list[str], list[float]]:
    """Terms from candidate rows (unit, docs, contexts): the shortest stems that do, or the one word behind a stem."""
    odds = {r.unit: math.log((r.docs + 0.5) / (n_bad + 1)) - math.log((good.get(r.unit, 0) + 0.5) / (n_good + 1)) for r in found}
    rows = {r.unit: r for r in found if odds[r.unit] >= least_odds and good.get(r.unit, 0) * 10 <= r.docs}
    taken: dict[str, float] = {}
    for u in sorted(rows, key=lambda u: (len(u.rstrip("-")), u)):
        if any(u.startswith(u[:n]) and u[:n] + "-" in taken for n in STEMS if n < len(u.rstrip("-"))):
            continue
        taken[u] = odds[u]
    for stem in [u for u in taken if u[-1] == "-"]:
        under = [u for u in rows if u[-1] != "-" and u.startswith(stem[:-1])]
        top = max(under, key=lambda u: (rows[u].contexts, u), default=None)
        if top is not None and rows[top].contexts >= 0.7 * rows[stem].contexts:
            del taken[stem]
            taken[top] = odds[top]
    order = sorted(taken, key=lambda u: (-rows[u].contexts, u))
    return order, [min(8.0, taken[u]) for u in order]


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "toxic", max_train: int = MAX_TRAIN, least_contexts: int = 8, least_odds: float = 2.5) -> Model:
    rows = train_rows(docs, labels, label_col, max_train).cache()  # max_train texts at most
    total = rows.groupBy("y").count().collect()
    n_bad, n_good = (sum(r["count"] for r in total if r["y"] == k) for k in (1, 0))
    if not n_bad or not n_good:
        rows.unpersist()
        share = n_bad / max(1, n_bad + n_good)
        return Model(Lexicon([], []), [0.0] * (N_FEATURES - 1) + [math.log((share + 1e-9) / (1 - share + 1e-9))])
    seen = pa.schema([("unit", pa.string()), ("context", pa.int64()), ("fresh", pa.int32())])

    def evidence(cols: dict[str, list]) -> dict[str, list]:
        from xxhash import xxh3_64_intdigest

        out: dict[str, list] = {"unit": [], "context": [], "fresh": []}
        for text in cols["text"]:
            words, own = ["", *_INNER.findall((text or "").lower()), ""], {}
            for before, w, after in zip(words, words[1:], words[2:], strict=False):
                if len(w) > 2:
                    c = xxh3_64_intdigest(f"{before} {after}") >> 1
                    for u in _units(w):
                        own.setdefault((u, c), None)
            fresh = set()
            for u, c in own:
                out["unit"].append(u)
                out["context"].append(c)
                out["fresh"].append(int(u not in fresh))
                fresh.add(u)
        return out

    bad = rows.where("y = 1").mapInArrow(arrow_rows(evidence, seen, 64), "unit string, context long, fresh int")
    bad = bad.groupBy("unit", "context").agg(F.sum("fresh").alias("fresh")).groupBy("unit").agg(F.sum("fresh").alias("docs"), F.count("*").alias("contexts"))
    found = bad.where(f"docs >= 4 and contexts >= {least_contexts} and contexts * 4 >= docs").collect()  # units that recur in max_train texts
    units = {r.unit for r in found}
    counted = pa.schema([("unit", pa.string())])

    def clean_units(cols: dict[str, list]) -> dict[str, list]:
        return {"unit": [u for t in cols["text"] for u in {u for w in set(_INNER.findall((t or "").lower())) for u in _units(w)} & units]}

    good = rows.where("y = 0").mapInArrow(arrow_rows(clean_units, counted), "unit string").groupBy("unit").count().collect()
    lexicon = Lexicon(*_chosen(found, n_bad, n_good, {r["unit"]: r["count"] for r in good}, least_odds))

    def neighbours(cols: dict[str, list]) -> dict[str, list]:
        out = set()
        for t in cols["text"]:
            chunks = (t or "").split()
            for i, _, e in lexicon.hits(chunks):
                if e:
                    low = _EDGE.sub("", chunks[i].lower())
                    out |= {low} if low.isalnum() else {low, *_INNER.findall(low)}
        return {"unit": list(out)}

    near = rows.where("y = 0").mapInArrow(arrow_rows(neighbours, counted), "unit string").distinct().collect()  # words of max_train texts
    lexicon.innocent = frozenset(r["unit"] for r in near)
    table = pa.schema([(f"f{i}", pa.float64()) for i in range(N_FEATURES)] + [("y", pa.int32())])

    def measure(cols: dict[str, list]) -> dict[str, list]:
        f = [features(t, lexicon) for t in cols["text"]]
        return {f"f{i}": [r[i] for r in f] for i in range(N_FEATURES)} | {"y": cols["y"]}

    got = np.array(rows.mapInArrow(arrow_rows(measure, table), ", ".join(f"f{i} double" for i in range(N_FEATURES)) + ", y int").collect(), float)
    rows.unpersist()
    beta = logistic(got[:, :-1], got[:, -1])
    beta[1] = max(beta[1], 0.8 * beta[0])  # clean texts hold no misspelled terms to learn from
    return Model(lexicon, beta.tolist())


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, score, predicted`` for every row."""
    schema = pa.schema([("doc_id", pa.int64()), ("score", pa.float64())])
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))

    def each(cols: dict[str, list]) -> dict[str, list]:
        return {"doc_id": cols["doc_id"], "score": [model.score(t) for t in cols["text"]]}

    return src.mapInArrow(arrow_rows(each, schema), "doc_id long, score double").withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def reject(docs: DataFrame, model: Model) -> DataFrame:
    """``docs`` without the rows that the model predicts toxic; columns as they are."""

    def clean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                yield part.filter(pa.array([model.score(t) < 0.5 for t in part.column("text").to_pylist()], pa.bool_()))
        model.lexicon.memo.clear()
        release()

    return docs.mapInArrow(clean, docs.schema)
