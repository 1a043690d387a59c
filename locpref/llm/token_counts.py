"""Token counts by section from one encoding of each whole document.

The document is encoded once. Token byte spans become character spans, which are
joined to the sections' character intervals by binary search. A token inside one
section counts there. A token that crosses a boundary is allocated by a rule:

``majority``  to the section with most of its characters, the earlier one on a tie;
``start``     to the section that holds its first character;
``fraction``  to every section it touches, by its share of the characters.

A token that is part of one character has the span of that character, so every
token has at least one character. Defined cases: a null or empty text has no
sections and no rows; each repeated row is counted on its own; other columns of the
input are ignored. Sections are lines by default: each ends after its line break.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_rows
from .vocab import byte_vocabulary

RULES = ("majority", "start", "fraction")


def line_starts(text: str) -> np.ndarray:
    """Character positions at which lines start."""
    starts, at = [0], text.find("\n")
    while 0 <= at < len(text) - 1:
        starts.append(at + 1)
        at = text.find("\n", at + 1)
    return np.array(starts, np.int64)


def token_spans(text: str, n_bytes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First character and character after the last of every token."""
    end = np.cumsum(n_bytes)
    start = end - n_bytes
    if len(text) == (end[-1] if len(end) else 0):
        return start, end
    raw = np.frombuffer(text.encode(), np.uint8)
    char = np.cumsum((raw & 0xC0) != 0x80) - 1
    return char[start], char[end - 1] + 1


def attribute(start: np.ndarray, end: np.ndarray, sections: np.ndarray, n_chars: int, rule: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Tokens allocated to, wholly inside and crossing the edges of every section."""
    n = len(sections)
    first = np.searchsorted(sections, start, "right") - 1
    last = np.searchsorted(sections, end - 1, "right") - 1
    whole = first == last
    inside = np.bincount(first[whole], minlength=n)
    share, crossing = inside.astype(np.float64), np.zeros(n, np.int64)
    edges = np.append(sections, n_chars)
    for t in np.flatnonzero(~whole):
        a, b = first[t], last[t]
        crossing[a : b + 1] += 1
        held = np.minimum(edges[a + 1 : b + 2], end[t]) - np.maximum(edges[a : b + 1], start[t])
        if rule == "fraction":
            share[a : b + 1] += held / held.sum()
        else:
            share[a + (int(held.argmax()) if rule == "majority" else 0)] += 1
    return share, inside, crossing


def count_tokens(
    docs: DataFrame, json_path: str, ranks_path: str, pattern: str, rule: str = "majority", sections: Callable[[str], np.ndarray] = line_starts, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """One row per section of every document with its token counts."""
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).where("text <> ''")
    schema = pa.schema([("doc_id", pa.int64()), *((c, pa.int64()) for c in ("section", "char_start", "char_end")), ("n_tokens", pa.float64()), *((c, pa.int64()) for c in ("n_inside", "n_crossing", "doc_tokens"))])

    def each(rows: dict[str, list]) -> dict[str, list]:
        v = byte_vocabulary(json_path, ranks_path, pattern)
        parts: list[tuple[np.ndarray, ...]] = []
        null = []
        for doc, text in zip(rows["doc_id"], rows["text"], strict=True):
            ids = v.ids(text)
            start, end = token_spans(text, v.n_bytes[ids])
            at = sections(text)
            n = len(at)
            null += [doc is None] * n
            parts.append((np.full(n, doc or 0), np.arange(n), at, np.append(at[1:], len(text)), *attribute(start, end, at, len(text), rule), np.full(n, len(ids))))
        cols = [np.concatenate(c) for c in zip(*parts, strict=True)]
        return {f.name: pa.array(c, f.type, mask=np.array(null) if f.name == "doc_id" else None) for f, c in zip(schema, cols, strict=True)}

    return src.mapInArrow(arrow_rows(each, schema), "doc_id long, section long, char_start long, char_end long, n_tokens double, n_inside long, n_crossing long, doc_tokens long")
