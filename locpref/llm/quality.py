"""Quality rules as a learned decision list over text statistics.

Only DataFrame functions touch the data. Statistics are expressions over a document's
words and lines. Windows of five words are compared by hash: a text whose hashes are
all different has no repeated window; only others are sorted to find the positions.

A list is learned from the statistics of a bounded sample of labelled rows by
sequential covering: a rule is a conjunction of thresholds, grown on two thirds of the
rows by information gain, pruned on the rest from its last condition backwards, kept
if it beats the default there, and the rows it covers are set aside. The list becomes
one ordered ``CASE`` expression.

Defined cases: a null text has no words and fails the base rule; repeated rows are
judged each on its own; a null id is kept as it is; without labelled rows of both
kinds the list is empty and its default keeps.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Labelled documents whose statistics a list is learned from at most.
MAX_TRAIN = 6_000
SPAN = 5
_SPACE = r"[\x20\x09-\x0D]+"
_SYMBOLS = r"[^#*$%&|<>]+"

#: Statistics that rules may test, as expressions over the counted columns.
TESTS = {
    "symbol_share": "n_symbols / greatest(1, word_chars)",
    "dup_line_share": "n_dup_lines / greatest(1, n_lines)",
    "repeat_share": "n_repeat_words / greatest(1, n_words)",
    "word_length": "word_chars / greatest(1, n_words)",
    "upper_share": "n_upper / greatest(1, word_chars)",
    "distinct_share": "n_distinct / greatest(1, n_words)",
    "line_words": "n_words / greatest(1, n_lines)",
    "marks_share": "n_marks / greatest(1, n_words)",
    "n_words": "cast(n_words AS double)",
}


def counted(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of counts per document."""
    src = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    words = F.filter(F.split("text", _SPACE, -1), lambda w: w != "")
    lines = F.filter(F.split("text", "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    cut = src.select("doc_id", "text", words.alias("words"), lines.alias("lines"))
    solid = F.array_join("words", "")
    cut = cut.select(
        "doc_id",
        F.size("words").cast("long").alias("n_words"),
        F.length(solid).cast("long").alias("word_chars"),
        F.length(F.regexp_replace("text", _SYMBOLS, "")).cast("long").alias("n_symbols"),
        F.length(F.regexp_replace("text", r"[^\p{Lu}]+", "")).cast("long").alias("n_upper"),
        F.length(F.regexp_replace("text", r"[^!?]+", "")).cast("long").alias("n_marks"),
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.transform("words", lambda w: F.xxhash64(w)).alias("hashes"),
    )
    window = F.when(F.size("hashes") >= SPAN, F.transform(F.sequence(F.lit(0), F.size("hashes") - SPAN), lambda i: F.xxhash64(*(F.get("hashes", i + k) for k in range(SPAN))))).otherwise(F.array().cast("array<bigint>"))
    cut = cut.withColumns({"windows": window, "n_distinct": F.size(F.array_distinct("hashes")).cast("long")}).drop("hashes")
    order = F.when(F.size(F.array_distinct("windows")) < F.size("windows"), F.array_sort(F.transform("windows", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))).otherwise(F.array().cast("array<struct<h:bigint,i:int>>"))
    cut = cut.withColumn("ordered", order).drop("windows")
    # in order of hash, equal windows stand beside each other
    pairs = F.arrays_zip(F.col("ordered").alias("x"), F.concat(F.array(F.lit(None).cast("struct<h:bigint,i:int>")), "ordered").alias("before"), F.slice("ordered", 2, F.greatest(F.size("ordered"), F.lit(1))).alias("after"))
    twice = F.filter(pairs, lambda p: p["x"].isNotNull() & (F.coalesce(p["x"]["h"] == p["before"]["h"], F.lit(False)) | F.coalesce(p["x"]["h"] == p["after"]["h"], F.lit(False))))
    places = F.array_sort(F.transform(twice, lambda p: p["x"]["i"]))
    state = F.struct(F.lit(-SPAN).alias("last"), F.lit(0).cast("long").alias("n"))
    covered = F.aggregate(places, state, lambda a, i: F.struct(i.alias("last"), (a["n"] + F.least(F.lit(SPAN), i - a["last"])).cast("long").alias("n")), lambda a: a["n"])
    return cut.withColumn("n_repeat_words", F.when(F.size("ordered") > 0, covered).otherwise(F.lit(0).cast("long"))).drop("ordered")


@dataclass(frozen=True)
class Rule:
    """If all conditions (test, above?, threshold) hold, the verdict is ``keep``."""

    conditions: tuple[tuple[str, bool, float], ...]
    keep: bool

    def covers(self, row: dict[str, float]) -> bool:
        return all((row[t] > x) == above for t, above, x in self.conditions)

    def column(self) -> Column:
        out = F.lit(True)
        for t, above, x in self.conditions:
            out = out & ((F.expr(TESTS[t]) > x) if above else (F.expr(TESTS[t]) <= x))
        return out


@dataclass(frozen=True)
class DecisionList:
    rules: tuple[Rule, ...]
    default: bool = True

    def column(self) -> Column:
        out = F.lit(self.default)
        for r in reversed(self.rules):
            out = F.when(r.column(), F.lit(r.keep)).otherwise(out)
        return out

    def verdict(self, row: dict[str, float]) -> bool:
        return next((r.keep for r in self.rules if r.covers(row)), self.default)


Rows = list[tuple[dict[str, float], bool]]


def _gain(p: int, n: int, p0: int, n0: int) -> float:
    """Information gained on the rows wanted when p0, n0 shrink to p, n."""
    return p * (math.log2((p + 1e-9) / (p + n + 1e-9)) - math.log2((p0 + 1e-9) / (p0 + n0 + 1e-9))) if p else -1.0


def _grown(rows: Rows, want: bool, most: int) -> list[tuple[str, bool, float]]:
    conditions: list[tuple[str, bool, float]] = []
    inside = rows
    while len(conditions) < most:
        p0 = sum(y == want for _, y in inside)
        n0 = len(inside) - p0
        if not n0 or not p0:
            break
        best = (0.0, None)
        for t in TESTS:
            order = sorted((r[t], y == want) for r, y in inside)
            p = n = 0
            for (v, good), (nxt, _) in zip(order, order[1:], strict=False):
                p, n = p + good, n + (not good)
                if v == nxt:
                    continue
                x = (v + nxt) / 2
                for g, c in ((_gain(p, n, p0, n0), (t, False, x)), (_gain(p0 - p, n0 - n, p0, n0), (t, True, x))):
                    if g > best[0] + 1e-9:
                        best = (g, c)
        if best[1] is None:
            break
        conditions.append(best[1])
        t, above, x = best[1]
        inside = [(r, y) for r, y in inside if (r[t] > x) == above]
    return conditions


def _worth(conditions: list, rows: Rows, want: bool) -> tuple[float, int]:
    """(right - wrong) / covered on rows held back, and how many it covers."""
    rule = Rule(tuple(conditions), want)
    held = [y == want for r, y in rows if rule.covers(r)]
    return ((2 * sum(held) - len(held)) / len(held) if held else -1.0), len(held)


def learn(rows: Rows, default: bool = True, most_rules: int = 12, most_conditions: int = 4, least_worth: float = 0.8, least_covered: int = 3) -> DecisionList:
    """Sequential covering of the verdict that isn't the default."""
    want = not default
    grow, prune = [r for i, r in enumerate(rows) if i % 3], rows[::3]
    rules: list[Rule] = []
    while len(rules) < most_rules and any(y == want for _, y in grow):
        conditions = _grown(grow, want, most_conditions)
        while len(conditions) > 1 and _worth(conditions[:-1], prune, want)[0] >= _worth(conditions, prune, want)[0]:
            conditions = conditions[:-1]
        worth, covered = _worth(conditions, prune, want) if conditions else (-1.0, 0)
        if worth < least_worth or covered < least_covered:
            break
        rules.append(Rule(tuple(conditions), want))
        grow, prune = ([x for x in part if not rules[-1].covers(x[0])] for part in (grow, prune))
    return DecisionList(tuple(rules), default)


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "quality", max_train: int = MAX_TRAIN) -> DecisionList:
    """Learn from at most ``max_train`` labelled rows, picked by hash of the id."""
    picked = labels.where(F.col("doc_id").isNotNull() & F.col(label_col).isNotNull()).groupBy("doc_id").agg(F.min(label_col).alias("good")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_train)
    some = docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id")  # max_train ids at most
    stats = counted(some).join(F.broadcast(picked), "doc_id").select("doc_id", "good", *(F.expr(e).cast("double").alias(t) for t, e in TESTS.items())).orderBy(F.xxhash64("doc_id"), "doc_id").collect()
    rows = [({t: r[t] for t in TESTS}, bool(r.good)) for r in stats]
    return learn(rows) if {y for _, y in rows} == {True, False} else DecisionList(())


def judge(docs: DataFrame, rules: DecisionList, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Counts, ``base_failed`` and ``kept`` for every row."""
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return counted(docs, id_col, text_col).withColumn("base_failed", failed).withColumn("kept", F.when(F.col("base_failed"), F.lit(False)).otherwise(rules.column()))
