"""Repeated passages across documents by sparse suffix arrays.

A passage counts from ``length`` words on. Suffixes are kept only at minimiser
positions: the leftmost least hash among the word ``gram``-grams of some window of
``length`` words. The window's content alone picks its position, so equal windows
hold equal suffixes at equal places, and a suffix stands for the run of windows that
picked it: it extends ``j`` words to the left for j in a range, and the rest right.

Suffixes with the whole context in common are one class, whatever their number: they
are merged by partial aggregation, so a passage in a third of all documents is one
entry. Classes whose gram no other class has need no comparison. All others are sorted
by gram and by the words after it. Neighbours in that order are compared word by word;
the lengths they have in common cut the order into runs, for every length that a window
needs to the right. Inside a run, the words to the left are compared, length by length.
So every class learns with which others it shares a window, and their least document.

A gram with so many classes that one task shouldn't hold them is dealt out by the whole
extended content instead, for every left length: equal content meets again in one
place, already merged on the way there. Grams and classes with many suffixes are found
by their counts; there are at most ``common.MOST_HOT`` of them by construction, so the rows of
these stay where they are and the rest is joined.

A window repeats if two documents hold it; its first document is the least id. Words
that a repeated window of another first document covers are redundant. A passage that
only one document repeats isn't one of these: inside a document, repetition is a matter
of its quality (``quality`` counts it), and cutting it would tear up refrains and tables.

Defined cases: null ids, null texts and texts of fewer words have no passages and
stay as they are; rows that share an id are one document; other columns are kept.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import Scratch, arrow_rows, hot_floor, lists_of, met, release, slices
from .minhash import mix

LENGTH, GRAM = 50, 10
#: Classes of a gram that one task sorts; a gram with more is dealt out by content.
SORTED_CLASSES = 2_000
_BASE = 0x9E3779B97F4A7C15 | 1
_BACK = pow(_BASE, -1, 2**64)
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[:1] = 1
    return np.multiply.accumulate(out)


class Ranges:
    """Hashes of any range of a text's words from running sums."""

    def __init__(self, text: str):
        from xxhash import xxh3_64_intdigest

        words = text.encode().split()
        self.n = n = len(words)
        self.words = w = mix(np.fromiter(map(xxh3_64_intdigest, words), np.uint64, n))
        self.sums = np.zeros(n + 1, np.uint64)
        np.add.accumulate(w * _powers(_BASE, n), out=self.sums[1:])
        self.back = _powers(_BACK, n + 1)

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.sums[end] - self.sums[start]) * self.back[start] + (end - start).astype(np.uint64))


def picked(grams: np.ndarray, wide: int) -> np.ndarray:
    """Position of the leftmost least value in every run of ``wide`` values."""
    at, span = np.arange(len(grams)), 1
    while 2 * span <= wide:
        left, right = at[:-span], at[span:]
        at = np.where(grams[right] < grams[left], right, left)
        span *= 2
    if span < wide:
        left, right = at[: len(at) - (wide - span)], at[wide - span :]
        at = np.where(grams[right] < grams[left], right, left)
    return at


def sparse_suffixes(text: str, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """Gram hash, context hash, position and the range of left lengths of every suffix kept."""
    r = Ranges(text)
    if r.n < length:
        return (np.empty(0, np.uint64), np.empty(0, np.uint64), *(np.empty(0, np.int64),) * 3)
    i = np.arange(r.n - gram + 1)
    grams = r.of(i, i + gram)
    place = picked(grams, length - gram + 1)
    first = np.flatnonzero(np.diff(place, prepend=-1))
    last = np.append(first[1:], len(place)) - 1
    p = place[first]
    return grams[p], r.of(first, last + length), p, p - last, p - first


def _suffix_table(docs: DataFrame, length: int, gram: int) -> DataFrame:
    schema = pa.schema([("h", pa.int64()), ("c", pa.int64()), ("doc_id", pa.int64()), ("p", pa.int32()), ("j_lo", pa.int16()), ("j_hi", pa.int16())])

    def each(cols: dict[str, list]) -> dict[str, list]:
        found = [sparse_suffixes(t, length, gram) for t in cols["text"]]
        h, c, p, lo, hi = (np.concatenate(x) for x in zip(*found, strict=True))
        ids = np.repeat(np.array(cols["doc_id"], np.int64), [len(f[0]) for f in found])
        return {"h": h.view(np.int64), "c": c.view(np.int64), "doc_id": ids, "p": p, "j_lo": lo, "j_hi": hi}

    return docs.mapInArrow(arrow_rows(each, schema), "h long, c long, doc_id long, p int, j_lo short, j_hi short")


def _extended(docs: DataFrame, classes: DataFrame, length: int, gram: int, whole: bool) -> DataFrame:
    """The content around the classes' first suffixes.

    ``whole``: ``w``, a hash of the window for every left length. Else ``words``, the
    hashes of the words after the gram as bytes whose order is theirs, and ``before``,
    a hash of the words to the left for every left length.
    """
    names = ("h", "c", "a", "b", "j_lo")
    fields = [("w", pa.list_(pa.int64()))] if whole else [("words", pa.binary()), ("before", pa.list_(pa.int64()))]
    schema = pa.schema([*((x, pa.int64()) for x in names), *fields])
    ddl = ", ".join(f"{x} long" for x in names) + (", w array<long>" if whole else ", words binary, before array<long>")
    spots = classes.groupBy(F.col("spot.doc_id").alias("doc_id")).agg(F.collect_list(F.struct("h", "c", "a", "b", F.col("spot.p").cast("long").alias("p"), F.col("spot.j_lo").cast("long").alias("j_lo"), F.col("spot.j_hi").cast("long").alias("j_hi"))).alias("spots"))

    def each(part: pa.RecordBatch) -> dict[str, list]:
        out: dict[str, list] = {f.name: [] for f in schema}
        at, h, c, a, b, p, lo, hi = lists_of(part.column("spots"), "h", "c", "a", "b", "p", "j_lo", "j_hi")
        for row, text in enumerate(part.column("text").to_pylist()):
            r = Ranges(text)
            for k in range(at[row], at[row + 1]):
                start = p[k] - np.arange(lo[k], hi[k] + 1)
                if start[-1] < 0 or start[0] + length > r.n or r.of(start[-1:], start[:1] + length).view(np.int64)[0] != c[k]:
                    continue  # another version under this id
                found = (h[k], c[k], a[k], b[k], lo[k])
                if whole:
                    found += (r.of(start, start + length).view(np.int64),)
                else:
                    ahead = np.zeros(length - gram, ">u8")  # zeros where the text ends
                    own = r.words[p[k] + gram : p[k] + length]
                    ahead[: len(own)] = own
                    found += (ahead.tobytes(), r.of(start, np.full(len(start), p[k])).view(np.int64))
                for name, x in zip(out, found, strict=True):
                    out[name].append(x)
        return out

    joined = docs.join(spots.hint("shuffle_hash"), "doc_id").select("text", "spots")
    return joined.mapInArrow(arrow_rows(each, schema, 128, raw=True), ddl)


def shared_windows(h: np.ndarray, words: np.ndarray, before: np.ndarray, lowest: np.ndarray, a: np.ndarray, b: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """Row, left length and first document of every window that two documents hold.

    Rows are suffixes in sorted order (by gram, then by ``words``, a row for each).
    ``before[i, k]`` is the hash of the ``lowest[i] + k`` words to the left, where it
    has one (``before`` is masked elsewhere).
    """
    n = len(h)
    same = np.zeros(n, np.int64)  # words after the gram that a suffix has in common with the one before it
    if n > 1:
        differ = words[1:] != words[:-1]
        same[1:] = np.where(differ.any(axis=1), differ.argmax(axis=1), words.shape[1])
        same[1:][h[1:] != h[:-1]] = -1
    out = []
    for j in range(length - gram + 1):
        k = j - lowest
        held = np.flatnonzero((k >= 0) & (k < before.shape[1]))
        held = held[~np.ma.getmaskarray(before)[held, k[held]]]
        if len(held) == 0:
            continue
        run = np.cumsum((same < length - gram - j) | (np.arange(n) == 0))[held]
        left = before.data[held, k[held]]
        order = np.lexsort((left, run))
        held, run, left = held[order], run[order], left[order]
        new = np.flatnonzero(np.append(True, (run[1:] != run[:-1]) | (left[1:] != left[:-1])))
        first, last = np.minimum.reduceat(a[held], new), np.maximum.reduceat(b[held], new)
        sizes = np.diff(np.append(new, len(held)))
        first, twice = np.repeat(first, sizes), np.repeat(first != last, sizes)
        out.append((held[twice], np.full(int(twice.sum()), j), first[twice]))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.empty(0, np.int64),) * 3


def _neighbours_compared(parts: DataFrame, length: int, gram: int) -> DataFrame:
    """``h, c, runs`` from classes in suffix order: Spark sorts, a task walks its part of the sorted array."""
    schema = pa.schema([("h", pa.int64()), ("c", pa.int64()), ("runs", pa.list_(pa.struct([("j", pa.int64()), ("k", pa.int64()), ("first", pa.int64())])))])

    def compare(rows: list[tuple]) -> pa.RecordBatch:
        h, c, a, b, lowest = (np.array(x, np.int64) for x in list(zip(*rows, strict=True))[:5])
        words = np.frombuffer(b"".join(r[5] for r in rows), ">u8").reshape(len(rows), -1) if length > gram else np.zeros((len(rows), 0), np.uint64)
        wide = max(len(r[6]) for r in rows)
        before = np.ma.masked_all((len(rows), wide), np.int64)
        for i, r in enumerate(rows):
            before[i, : len(r[6])] = r[6]
        at, j, first = shared_windows(h, words, before, lowest, a, b, length, gram)
        order = np.lexsort((j, at))
        at, j, first = at[order], j[order], first[order]
        runs: dict[int, list[dict]] = {}
        for i, x, f in zip(at.tolist(), j.tolist(), first.tolist(), strict=True):
            own = runs.setdefault(i, [])
            if own and own[-1]["k"] + 1 == x and own[-1]["first"] == f:
                own[-1]["k"] = x
            else:
                own.append({"j": x, "k": x, "first": f})
        found = list(runs)
        return pa.RecordBatch.from_arrays([pa.array(h[found], pa.int64()), pa.array(c[found], pa.int64()), pa.array(list(runs.values()), schema.field("runs").type)], schema=schema)

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for batch in batches:
            for row in zip(*(batch.column(x).to_pylist() for x in ("h", "c", "a", "b", "j_lo", "words", "before")), strict=True):
                if len(held) >= 4096 and held[-1][0] != row[0]:  # cut between grams
                    yield compare(held)
                    held = []
                held.append(row)
        if held:
            yield compare(held)
        release()

    return parts.repartition("h").sortWithinPartitions("h", "words").mapInArrow(walk, "h long, c long, runs array<struct<j: long, k: long, first: long>>")


def _in_runs(by_j: str) -> Column:
    """Left lengths (j, first) in order as runs (j, k, first) of one first document each; there are ``length`` at most."""
    kind = "array<struct<j:bigint,k:bigint,first:bigint>>"

    def step(acc: Column, x: Column) -> Column:
        last = F.get(acc, F.size(acc) - 1)
        longer = F.struct(last["j"].alias("j"), x["j"].alias("k"), x["first"].alias("first"))
        new = F.struct(x["j"].alias("j"), x["j"].alias("k"), x["first"].alias("first"))
        follows = (F.size(acc) > 0) & (last["k"] + 1 == x["j"]) & (last["first"] == x["first"])
        return F.when(F.coalesce(follows, F.lit(False)), F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(longer))).otherwise(F.array_append(acc, new))

    return F.aggregate(F.array_sort(by_j), F.array().cast(kind), step)


def _by_content(classes: DataFrame, src: DataFrame, length: int, gram: int) -> DataFrame:
    """``h, c, runs`` of classes whose grams have too many: windows of every left length meet by their content."""
    parts = _extended(src, classes, length, gram, True)
    each = parts.select("h", "c", "a", "b", "j_lo", F.posexplode("w").alias("k", "w")).select("h", "c", "a", "b", (F.col("j_lo") + F.col("k")).alias("j"), "w")
    same = each.groupBy("h", "j", "w").agg(F.min("a").alias("first"), F.max("b").alias("last")).where("first <> last").select("h", "j", "w", "first")
    return each.select("h", "c", "j", "w").join(same, ["h", "j", "w"]).groupBy("h", "c").agg(F.collect_set(F.struct("j", "first")).alias("by_j")).select("h", "c", _in_runs("by_j").alias("runs"))


def repeated_windows(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, lo, hi, first``: runs of window starts that repeat, by first document."""
    scratch = Scratch(docs.sparkSession, "suffixes")
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).where("doc_id is not null and text is not null")
    suffixes = scratch.keep(_suffix_table(src, length, gram), "all")
    floor = hot_floor(suffixes.count())
    several = suffixes.groupBy("h").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b"), F.count("*").alias("n")).where("a <> b").select("h", "n")
    several = scratch.keep(several, "several")
    suffixes = scratch.keep(met(suffixes, several, ["h"], F.col("n") > floor).drop("n"), "shared")
    scratch.drop("all", "several")
    classes = suffixes.groupBy("h", "c").agg(F.min("doc_id").alias("a"), F.max("doc_id").alias("b"), F.count("*").alias("n"), F.min(F.struct("doc_id", "p", "j_lo", "j_hi")).alias("spot"))
    classes = scratch.keep(classes, "classes")
    mixed = scratch.keep(classes.groupBy("h").agg(F.count("*").alias("k")), "grams")
    placed = scratch.keep(met(classes, mixed, ["h"], F.col("k") > floor), "placed")
    alone = placed.where("k = 1 and a <> b").select("h", "c", F.array(F.struct(F.col("spot.j_lo").cast("long").alias("j"), F.col("spot.j_hi").cast("long").alias("k"), F.col("a").alias("first"))).alias("runs"))
    # classes that share a gram with others are told apart by what stands around it
    found = alone.unionByName(_neighbours_compared(_extended(src, placed.where(f"k > 1 and k <= {SORTED_CLASSES}"), length, gram, False), length, gram))
    large = placed.where(f"k > {SORTED_CLASSES}")
    if not large.isEmpty():
        found = found.unionByName(_by_content(large, src, length, gram))
    found = scratch.keep(found, "found")
    counted = classes.where(F.col("n") > floor).select("h", "c", "n")
    found = found.join(F.broadcast(counted), ["h", "c"], "left")  # MOST_HOT classes at most
    found = scratch.keep(found, "counted")
    runs = met(suffixes, found, ["h", "c"], F.col("n").isNotNull()).select("doc_id", "p", F.explode("runs").alias("x"))
    return scratch.last(runs.select("doc_id", (F.col("p") - F.col("x.k")).alias("lo"), (F.col("p") - F.col("x.j")).alias("hi"), F.col("x.first").alias("first")), "windows")


def _runs(starts: np.ndarray, ends: np.ndarray) -> list[tuple[int, int]]:
    """Union of half-open ranges, as ranges that don't touch."""
    order = np.argsort(starts, kind="stable")
    out: list[tuple[int, int]] = []
    for s, e in zip(starts[order].tolist(), ends[order].tolist(), strict=True):
        if out and s <= out[-1][1]:
            out[-1] = (out[-1][0], max(e, out[-1][1]))
        else:
            out.append((s, e))
    return out


def repeated_passages(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per maximal repeated passage of a document.

    ``doc_id, start_word, end_word`` (exclusive), ``first_doc_id`` (the least id that
    holds part of it), ``n_redundant`` words, and ``redundant``: their word ranges.
    """
    windows = repeated_windows(docs, length, gram, id_col, text_col)
    schema = pa.schema([("doc_id", pa.int64()), *((c, pa.int64()) for c in ("start_word", "end_word", "first_doc_id", "n_redundant")), ("redundant", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))])

    def each(part: pa.RecordBatch) -> dict[str, list]:
        out: dict[str, list] = {f.name: [] for f in schema}
        at, lows, highs, firsts = lists_of(part.column("windows"), "lo", "hi", "first")
        for row, doc in enumerate(part.column("doc_id").to_pylist()):
            cut = slice(at[row], at[row + 1])
            lo, hi, first = lows[cut], highs[cut], firsts[cut]
            again = first < doc
            gone = _runs(lo[again], hi[again] + length)
            for s, e in _runs(lo, hi + length):
                inside = [{"start": a, "end": b} for a, b in gone if s <= a < e]
                own = (lo >= s) & (lo < e)
                for name, x in zip(out, (doc, s, e, int(first[own].min()), sum(g["end"] - g["start"] for g in inside), inside), strict=True):
                    out[name].append(x)
        return out

    grouped = windows.groupBy("doc_id").agg(F.collect_list(F.struct("lo", "hi", "first")).alias("windows"))
    return grouped.mapInArrow(arrow_rows(each, schema, raw=True), "doc_id long, start_word long, end_word long, first_doc_id long, n_redundant long, redundant array<struct<start: long, end: long>>")


def without_words(text: str, ranges: list[tuple[int, int]]) -> str:
    """The text without the words of the ranges; what stands around them stays."""
    if not ranges:
        return text
    at = [(m.start(), m.end()) for m in WORD.finditer(text)]
    out, begin = [], 0
    for s, e in ranges:
        if s >= len(at):
            break
        out.append(text[begin : at[s][0]])
        begin = at[min(e, len(at)) - 1][1]
    return "".join([*out, text[begin:]])


def drop_redundant(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """``docs`` with redundant words cut from ``text``; rows of which nothing is left go."""
    found = repeated_passages(docs, length, gram).where("n_redundant > 0").groupBy(F.col("doc_id").alias("_doc")).agg(F.flatten(F.collect_list("redundant")).alias("_cut"))
    found = Scratch(docs.sparkSession, "redundant").keep(found, "ranges")
    joined = docs.join(found.hint("shuffle_hash"), F.col("doc_id") == F.col("_doc"), "left").drop("_doc")
    names = docs.columns

    def rewrite(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch):
                k, cuts = part.schema.get_field_index("text"), part.column("_cut")
                if cuts.null_count < part.num_rows:
                    texts = part.column(k).to_pylist()
                    for i in np.flatnonzero(cuts.is_valid().to_numpy(zero_copy_only=False)):
                        texts[i] = without_words(texts[i], sorted((r["start"], r["end"]) for r in cuts[int(i)].as_py()))
                    left = [cut is None or WORD.search(t) is not None for t, cut in zip(texts, cuts.to_pylist(), strict=True)]
                    part = part.set_column(k, part.schema.field(k), pa.array(texts, part.schema.field(k).type)).filter(pa.array(left))
                yield part.select(names)
        release()

    return joined.mapInArrow(rewrite, docs.schema)
