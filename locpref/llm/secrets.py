"""Secret scans: fixed patterns, and strings of high entropy in a sliding window.

Only DataFrame functions, and none whose work grows with the square of a text: a
pattern's matches and the text between them give all positions by running sums, which
are made in doubling steps (each adds the array to itself, moved by a power of two).

Entropy: candidates are long runs of token characters with a digit. A window slides
over each. Counts of the window's characters sit in the bit fields of a few numbers:
one field goes up by one for the character that comes in, one goes down for the one
that goes out, and the sum of c*log2(c) follows both by a table, so each step costs the
same. The highest window entropy is held against the threshold of the candidate's class
(hex digits, one case with digits, or the 64-letter alphabet). Candidates on the
allow-list (placeholders, identifiers of well-known form, paths whose segments all look
like words) and those that touch a pattern's span are left out.

Defined cases: null text counts as empty; a row per input row, repeated rows too; ids
may be null; other columns stay out of it.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Kinds in the order in which spans at one start are listed.
KINDS = ("assign", "access", "hex", "entropy")
# The patterns of the contract. ``hex`` and ``access`` carry their least
# length; a short ``assign`` match is dropped after it has used up its text.
ASSIGN = r"""([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
WINDOW = 20
ALPHABET = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_-="
#: Least entropy of a window in bits, by class; no window of 20 has exactly these.
HEX_BITS, LOWER_BITS, UPPER_BITS, BASE64_BITS = 3.05, 3.66, 3.56, 3.95
#: In order, the first that fits: hex digits, lower case and digits, upper case and digits (base32 too, with its padding).
CLASSES = ((r"^[0-9a-fA-F]+$", HEX_BITS), (r"^[a-z0-9]+$", LOWER_BITS), (r"^[A-Z0-9]+=*$", UPPER_BITS))
#: In any order: digits, UUIDs, placeholders, runs, dates.
ALLOW = (
    r"^[0-9]+$",
    r"^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    r"[eE][xX][aA][mM][pP][lL][eE]|[sS][aA][mM][pP][lL][eE]|[dD][uU][mM][mM][yY]|[pP][lL][aA][cC][eE][hH][oO][lL][dD]",
    r"0123456789|abcdefgh|ABCDEFGH|xxxxx|XXXXX",
    r"^[0-9]{4}-[0-9]{2}-[0-9]{2}",
)
#: A path has this many slashes, and each part between separators is shorter than a window: digits, up to three words, digits.
PATH_SLASHES, PATH_CUT, PATH_PART = 3, "[/_-]", r"^[0-9]{0,8}(?:[A-Z]?[a-z]+|[A-Z]+){0,3}[0-9]{0,8}$"

_SPANS = "array<struct<start:bigint,kind:int,end:bigint,word:string>>"
#: Code points of a text's blocks; a position is looked up in its block, not from the start of the text.
BLOCK = 2048
#: Bits of one count in a window's bit fields, and counts in a number.
FIELD, FIELDS = 5, 12


def _bound(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is evaluated once; an expression that is named twice is evaluated twice."""
    return F.get(F.transform(F.array(value), use), F.lit(0))


def _running(values: Column, join: Callable[[Column, Column], Column]) -> Column:
    """Running sums (or maxima) of an array, itself included, in as many doubling steps as its length has bits."""

    def step(acc: Column, by: Column) -> Column:
        moved = F.zip_with(F.slice(acc, by + 1, F.size(acc) - by), F.slice(acc, F.lit(1), F.size(acc) - by), join)
        return F.concat(F.slice(acc, F.lit(1), by), moved)

    powers = F.array(*(F.lit(1 << k) for k in range(30)))
    return _bound(values, lambda v: F.aggregate(F.filter(powers, lambda by: by < F.size(v)), v, step))


def _matches(text: Column, pattern: str, kind: int, group: int = 0, least: int = 0) -> Column:
    """Spans of the leftmost matches that don't overlap, whose ``group`` has ``least`` characters."""
    whole = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    parts = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else whole
    gaps = F.transform(F.split(text, pattern, -1), lambda x: F.length(x).cast("bigint"))
    sizes = F.transform(whole, lambda x: F.length(x).cast("bigint"))

    def spans(x: Column) -> Column:
        one = lambda w, i: F.struct(F.get(x["at"], 2 * i).alias("start"), F.lit(kind).alias("kind"), F.get(x["at"], 2 * i + 1).alias("end"), w.alias("word"))
        return F.filter(F.transform(x["part"], one), lambda s: F.length(s["word"]) >= least)

    # lengths in turn of a gap and a match, the last gap without one; their sums are starts and ends
    at = _running(F.flatten(F.zip_with(gaps, sizes, lambda g, m: F.array(g, F.coalesce(m, F.lit(0).cast("bigint"))))), lambda a, b: a + b)
    return F.when(text.rlike(pattern), _bound(F.struct(at.alias("at"), parts.alias("part")), spans)).otherwise(F.array().cast(_SPANS))


def window_entropy(word: Column, window: int = WINDOW, alphabet: str = ALPHABET) -> Column:
    """Highest entropy in bits of ``window`` characters (31 at most) in a row; characters outside count as one."""
    if not 0 < window < 1 << FIELD:
        raise ValueError(f"a window has 1 to {(1 << FIELD) - 1} characters")
    words = len(alphabet) // FIELDS + 1
    clogc = F.array(*(F.lit(c * math.log2(c) if c else 0.0) for c in range(window + 2)))
    unit = F.array(*(F.lit(1 << FIELD * i).cast("bigint") for i in range(FIELDS)))
    zero = F.lit(0).cast("bigint")

    def placed(chars: Column) -> Column:
        """The number that holds a character's count, and one unit of that count."""
        at = F.transform(F.split(chars, ""), lambda c: F.instr(F.lit(alphabet), c))
        return F.transform(at, lambda i: F.struct(F.floor(i / FIELDS).cast("int").alias("k"), F.get(unit, i % FIELDS).alias("u")))

    kind = "struct<k:int,u:bigint>"
    left = placed(F.substring(word, F.lit(1), F.greatest(F.length(word) - window, F.lit(0))))
    steps = F.zip_with(placed(word), F.concat(F.array_repeat(F.lit(None).cast(kind), window), left), lambda new, old: F.struct(new.alias("new"), old.alias("old")))
    steps = F.slice(steps, F.lit(1), F.length(word))
    state = F.struct(F.array(*([zero] * words)).alias("w"), F.lit(0.0).alias("s"), F.lit(0).alias("n"), F.lit(0.0).alias("best"))

    def step(acc: Column, x: Column) -> Column:
        new, old = x["new"], x["old"]
        count = lambda c: F.floor(F.get(acc["w"], c["k"]) / c["u"]).cast("bigint").bitwiseAND(F.lit((1 << FIELD) - 1)).cast("int")
        w = F.transform(acc["w"], lambda v, i: v + F.when(i == new["k"], new["u"]).otherwise(zero) - F.when(i == old["k"], old["u"]).otherwise(zero))
        up = F.get(clogc, count(new) + 1) - F.get(clogc, count(new))
        down = F.coalesce(F.get(clogc, count(old) - 1) - F.get(clogc, count(old)), F.lit(0.0))
        s = acc["s"] + F.when(F.coalesce(new == old, F.lit(False)), 0.0).otherwise(up + down)
        n = acc["n"] + 1
        best = F.when(n >= window, F.greatest(acc["best"], F.lit(math.log2(window)) - s / window)).otherwise(acc["best"])
        return F.struct(w.alias("w"), s.alias("s"), n.alias("n"), best.alias("best"))

    return F.aggregate(steps, state, step, lambda a: a["best"])


def _random_looking(word: Column) -> Column:
    allowed = F.lit(False)
    for p in ALLOW:
        allowed = allowed | word.rlike(p)
    short = lambda x: F.when(F.length(x) < WINDOW, x.rlike(PATH_PART)).otherwise(False)
    path = (F.length(word) - F.length(F.replace(word, F.lit("/"))) >= PATH_SLASHES) & F.forall(F.split(word, PATH_CUT, -1), short) & ~word.rlike("[^A-Za-z0-9/_-]")
    bits = F.lit(BASE64_BITS)
    for p, least in reversed(CLASSES):
        bits = F.when(word.rlike(p), F.lit(least)).otherwise(bits)
    return word.rlike("[0-9]") & ~allowed & ~path & (window_entropy(word) >= bits)


def find_secrets(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, text, base, found``: spans (start, kind, end, word) of the patterns, and all spans."""
    src = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    text = F.col("text")
    base = F.concat(_matches(text, ASSIGN, 0, 2, 6), _matches(text, ACCESS, 1), _matches(text, HEX, 2))
    out = src.withColumn("base", F.array_sort(base)).withColumn("candidates", F.filter(_matches(text, CANDIDATE, 3), lambda s: s["word"].rlike("[0-9]")))
    extra = F.when(F.size("candidates") > 0, F.filter(_apart(F.array_sort(F.concat("base", "candidates"))), lambda s: _random_looking(s["word"]))).otherwise(F.col("candidates"))
    return out.withColumn("found", F.array_sort(F.concat("base", extra))).select("doc_id", "text", "base", "found")


def _apart(spans: Column) -> Column:
    """The candidates among spans in order of starts that no pattern's span overlaps.

    The patterns' spans before a candidate must end, and those after it must start, outside.
    """
    none, far = F.lit(0).cast("bigint"), F.lit(2**62).cast("bigint")
    ends = lambda v: _running(F.transform(v, lambda s: F.when(s["kind"] < 3, s["end"]).otherwise(none)), lambda a, b: F.greatest(a, b))
    starts = lambda v: F.reverse(_running(F.reverse(F.transform(v, lambda s: F.when(s["kind"] < 3, s["start"]).otherwise(far))), lambda a, b: F.least(a, b)))
    outside = lambda x: F.filter(x["v"], lambda s, i: (s["kind"] == 3) & (F.get(x["ends"], i) <= s["start"]) & (F.get(x["starts"], i) >= s["end"]))
    return _bound(spans, lambda v: _bound(F.struct(v.alias("v"), ends(v).alias("ends"), starts(v).alias("starts")), outside))


def listed(spans: str) -> Column:
    """Spans as ``kind:start:end``, joined by commas."""
    kinds = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.get(kinds, s["kind"]), s["start"], s["end"])), ",")


def count_kind(spans: str, kind: int) -> Column:
    return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long")


def _cut(blocks: Column, start: Column, end: Column) -> Column:
    """Code points start to end (exclusive) of a text in blocks."""
    first = F.floor(start / BLOCK).cast("int")
    held = F.array_join(F.slice(blocks, first + 1, F.floor(end / BLOCK).cast("int") - first + 1), "")
    return F.substring(held, (start - first * BLOCK + 1).cast("int"), F.greatest(end - start, F.lit(0)).cast("int"))


def redact(docs: DataFrame, mark: str = "[secret]") -> DataFrame:
    """``docs`` with every found span of ``text`` replaced by ``mark``, overlapping ones by one mark; null texts stay null."""
    named = docs.select(F.struct(*docs.columns).alias("row"), "text").select("row", F.col("row").getField("text").alias("text"))
    out = find_secrets(named, "row")
    ends = _running(F.transform("found", lambda s: s["end"]), lambda a, b: F.greatest(a, b))
    blocks = F.regexp_extract_all("text", F.lit(f"(?s).{{1,{BLOCK}}}"), F.lit(0))

    def clean(x: Column) -> Column:
        at = lambda i: F.coalesce(F.get(x["ends"], i - 1), F.lit(0).cast("bigint"))
        fresh = F.filter(F.transform(x["found"], lambda s, i: F.struct(at(i).alias("at"), s["start"].alias("start"))), lambda g: g["start"] >= g["at"])
        marked = F.array_join(F.transform(fresh, lambda g: F.concat(_cut(x["blocks"], g["at"], g["start"]), F.lit(mark))), "")
        return F.concat(marked, _cut(x["blocks"], F.element_at(x["ends"], -1), x["n"]))

    held = F.struct(F.col("found"), ends.alias("ends"), blocks.alias("blocks"), F.length("text").cast("bigint").alias("n"))
    out = out.withColumn("clean", F.when(F.size("found") > 0, _bound(held, clean)).otherwise(F.col("doc_id.text")))
    return out.select(*(F.col("clean").alias(c) if c == "text" else F.col("doc_id").getField(c).alias(c) for c in docs.columns))
