"""Byte-level BPE encoding and decoding with a hierarchical-bitmap rank queue.

A pre-token is a linked list of byte strings. Each neighbouring pair that a merge
rank exists for sits in the bucket of that rank; a bitmap of three levels marks the
buckets that aren't empty, so the next rank is three find-first-set steps away. An
entry whose pair has changed since is stale and skipped. Work is O(n) bucket entries
for n bytes, so one pre-token of megabytes is no problem.

Texts are cut by a pattern. Code points that the pattern's engine and the library's
engine class differently (newer tables of characters) are cut as the library does.

Defined cases: a null text counts as empty; an empty text gives zero ids; repeated
rows are encoded each on its own; extra columns aren't touched.
"""

from __future__ import annotations

import itertools
import sys
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_rows
from .vocab import ranks_of

#: Distinct pre-tokens that a worker remembers. A memo only: a full one starts anew.
MEMO_ENTRIES = 600_000
#: Characters of texts that are held in pieces at a time, or one text.
PART_CHARS = 1_500_000


class RankQueue:
    """Buckets of list positions by rank under a bitmap of three levels, 64 wide."""

    def __init__(self, n_ranks: int):
        self.buckets: dict[int, list[int]] = {}
        self.low = [0] * (n_ranks // 64 + 1)
        self.mid = [0] * (len(self.low) // 64 + 1)
        self.top = 0

    def push(self, rank: int, position: int) -> None:
        bucket = self.buckets.get(rank)
        if bucket is not None:
            bucket.append(position)
            return
        self.buckets[rank] = [position]
        a = rank >> 6
        if not self.low[a]:
            b = a >> 6
            if not self.mid[b]:
                self.top |= 1 << b
            self.mid[b] |= 1 << (a & 63)
        self.low[a] |= 1 << (rank & 63)

    def push_all(self, rank: int, positions: list[int]) -> None:
        self.push(rank, positions[0])
        self.buckets[rank] += positions[1:]

    def pop(self) -> tuple[int, list[int]]:
        """The least rank that has entries, and its positions from left to right."""
        b = (self.top & -self.top).bit_length() - 1
        word = self.mid[b]
        a = (b << 6) + (word & -word).bit_length() - 1
        word = self.low[a]
        rank = (a << 6) + (word & -word).bit_length() - 1
        self.low[a] = word = word & (word - 1)
        if not word:
            self.mid[b] &= ~(1 << (a & 63))
            if not self.mid[b]:
                self.top &= ~(1 << b)
        bucket = self.buckets.pop(rank)
        bucket.sort()
        return rank, bucket


#: Classes that pre-token patterns use, and a character that stands for each; the last for none.
STAND_INS = ((r"\p{L}", "\u02b0"), (r"\p{N}", "\u00bc"), (r"\s", "\u2003"), ("", "\u00a4"))


@lru_cache(maxsize=1)
def told_apart() -> dict[int, str]:
    """Code points whose class differs between the two regular expression engines, with a stand-in of the library's class.

    The engines follow different versions of the Unicode tables.
    """
    import regex
    import tiktoken

    every = "".join(map(chr, (*range(0xD800), *range(0xE000, sys.maxunicode + 1))))
    single = {bytes([b]): b for b in range(256)}
    ours, theirs = {}, {}
    for k, (name, _) in enumerate(STAND_INS[:-1]):
        ours |= dict.fromkeys(regex.findall(name, every), k)
        library = tiktoken.Encoding("class", pat_str=name, mergeable_ranks=single, special_tokens={})
        theirs |= dict.fromkeys(library.decode_bytes(library.encode_ordinary(every)).decode(), k)
    return {ord(c): STAND_INS[theirs.get(c, -1)][1] for c in ours.keys() | theirs.keys() if ours.get(c, -1) != theirs.get(c, -1)}


class Encoder:
    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks = ranks
        self.pattern = regex.compile(pattern)
        self.odd = frozenset(map(chr, told_apart()))
        self.queue = RankQueue(max(ranks.values(), default=0) + 1)
        self.byte_ids = np.array([ranks.get(bytes([b]), -1) for b in range(256)])
        #: Rank by the ids of a pair's tokens, and by two bytes for the first look.
        self.pairs = {ranks[t[:c]] << 16 | ranks[t[c:]]: i for t, i in ranks.items() for c in range(1, len(t)) if t[:c] in ranks and t[c:] in ranks}
        self.byte_pairs = np.array([ranks.get(bytes([b >> 8, b & 255]), -1) for b in range(65536)])
        self.memo: dict[str, bytes] = {}

    def split(self, text: str) -> list[str]:
        """Pre-tokens as the library would cut them."""
        if text.isascii() or self.odd.isdisjoint(set(text)):
            return self.pattern.findall(text)
        return [text[m.start() : m.end()] for m in self.pattern.finditer(text.translate(told_apart()))]

    def merge(self, pieces: list[bytes]) -> list[bytes]:
        """Ids of pre-tokens that aren't empty: in each the lowest rank first, the leftmost among equals.

        All of them share one queue: pairs never reach over the end of a pre-token, so
        the order of ranks over all is the right order in each. A merged token's id is
        the rank that was popped, so ranks of pairs are looked up by two ids.
        """
        if not pieces:
            return []
        raw = np.frombuffer(b"".join(pieces), np.uint8).astype(np.int64)
        ends = np.cumsum(np.fromiter(map(len, pieces), np.int64, len(pieces)))
        starts = np.append(0, ends[:-1])
        n = len(raw)
        first = np.full(n, -1)
        first[:-1] = self.byte_pairs[raw[:-1] * 256 + raw[1:]]
        first[ends - 1] = -1
        after, before = np.arange(1, n + 1), np.arange(-1, n - 1)
        after[ends - 1] = before[starts] = -1
        part, pair, after, before = self.byte_ids[raw].tolist(), first.tolist(), after.tolist(), before.tolist()
        queue, rank_of = self.queue, self.pairs.get
        found = np.flatnonzero(first >= 0)
        found = found[np.argsort(first[found], kind="stable")]
        cuts = [*np.flatnonzero(np.diff(first[found], prepend=-1)).tolist(), len(found)]  # one edge alone where no pair has a rank
        for lo, hi in itertools.pairwise(cuts):
            queue.push_all(int(first[found[lo]]), found[lo:hi].tolist())
        buckets, push = queue.buckets, queue.push
        while queue.top:
            rank, bucket = queue.pop()
            above = rank << 16
            for k, i in enumerate(bucket):
                if pair[i] != rank:  # stale: the pair has changed or gone
                    continue
                j = after[i]
                part[i] = rank
                part[j] = pair[i] = pair[j] = -1
                nxt = after[i] = after[j]
                lower = False
                if nxt >= 0:
                    before[nxt] = i
                    r = rank_of(above | part[nxt])
                    if r is not None:
                        pair[i] = r
                        if r in buckets:
                            buckets[r].append(i)
                        else:
                            push(r, i)
                        lower = r < rank
                h = before[i]
                if h >= 0:
                    r = rank_of(part[h] << 16 | rank)
                    if r is None:
                        pair[h] = -1
                    else:
                        pair[h] = r
                        if r in buckets:
                            buckets[r].append(h)
                        else:
                            push(r, h)
                        lower = lower or r < rank
                if lower and k + 1 < len(bucket):
                    queue.push_all(rank, bucket[k + 1 :])
                    break
        left = np.array(part)
        alive = left >= 0
        data = left[alive].astype("<u4").tobytes()
        at = np.append(0, 4 * np.cumsum(np.add.reduceat(alive, starts, dtype=np.int64))).tolist()
        return [data[x:y] for x, y in zip(at, at[1:], strict=False)]

    def encode_all(self, texts: list[str]) -> list[bytes]:
        """Ids of texts as little-endian unsigned 32-bit integers."""
        out: list[bytes] = []
        at = 0
        while at < len(texts):
            cut, size = at, 0
            while cut < len(texts) and (cut == at or size + len(texts[cut]) <= PART_CHARS):
                size += len(texts[cut])
                cut += 1
            split = [self.split(t) for t in texts[at:cut]]
            out += self._joined(split)
            at = cut
        return out

    def _joined(self, split: list[list[str]]) -> list[bytes]:
        memo = self.memo
        wanted = set().union(*split)
        missing = wanted.difference(memo)
        if len(memo) + len(missing) > MEMO_ENTRIES:
            memo.clear()
            missing = wanted
        hard, raw = [], []
        for piece in missing:
            b = piece.encode()
            whole = self.ranks.get(b)
            if whole is None:
                hard.append(piece)
                raw.append(b)
            else:
                memo[piece] = whole.to_bytes(4, "little")
        for piece, ids in zip(hard, self.merge(raw), strict=True):
            memo[piece] = ids
        out = [b"".join(map(memo.__getitem__, pieces)) for pieces in split]
        for piece in hard:
            if len(piece) >= 200:
                del memo[piece]
        return out

    def encode(self, text: str) -> bytes:
        return self.encode_all([text])[0]


class Decoder:
    def __init__(self, ranks: dict[bytes, int]):
        self.token = [b""] * (max(ranks.values(), default=0) + 1)
        for t, i in ranks.items():
            self.token[i] = t

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.token.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@lru_cache(maxsize=2)
def encoder(path: str, pattern: str) -> Encoder:
    return Encoder(ranks_of(path), pattern)


@lru_cache(maxsize=2)
def decoder(path: str) -> Decoder:
    return Decoder(ranks_of(path))


def encode(docs: DataFrame, ranks_path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id``, ``ids`` (little-endian uint32) and ``n_tokens``."""
    src = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.binary())])

    def each(rows: dict[str, list]) -> dict[str, list]:
        return {"doc_id": rows["doc_id"], "ids": encoder(ranks_path, pattern).encode_all(rows["text"])}

    out = src.mapInArrow(arrow_rows(each, schema), "doc_id long, ids binary")
    return out.withColumn("n_tokens", (F.octet_length("ids") / 4).cast("long"))


def decode(encoded: DataFrame, ranks_path: str) -> DataFrame:
    """Adds ``decoded``, the bytes that the ids stand for, to what :func:`encode` returns."""
    kept = [f for f in encoded.schema.fields if f.name in ("doc_id", "ids", "n_tokens")]
    schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.binary()), ("n_tokens", pa.int64()), ("decoded", pa.binary())])

    def each(rows: dict[str, list]) -> dict[str, list]:
        back = decoder(ranks_path).decode
        return rows | {"decoded": [back(x) for x in rows["ids"]]}

    return encoded.select(*(f.name for f in kept)).mapInArrow(arrow_rows(each, schema), "doc_id long, ids binary, n_tokens long, decoded binary")
