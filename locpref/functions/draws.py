"""The draws of ``hashing`` for arrays in a Python task: the same keys give the same numbers.

A key is a prefix, a text of its own for each row, and a suffix. MD5 runs over all rows
at once, a step of it for a piece of them that stays in the cache.
"""

from __future__ import annotations

import math

import numpy as np

#: Rows that go through the steps of a hash together.
PIECE = 16384
_SHIFTS = [s for four in ((7, 12, 17, 22), (5, 9, 14, 20), (4, 11, 16, 23), (6, 10, 15, 21)) for s in four * 4]
# Arrays of no dimension: a call takes them as they are, a scalar it would have to convert.
_TURNS = [(np.array(s, np.uint32), np.array(32 - s, np.uint32)) for s in _SHIFTS]
_SINES = np.array([int(abs(math.sin(i + 1)) * 2**32) for i in range(64)], np.uint32)
_PLACES = [*range(16), *((5 * i + 1) % 16 for i in range(16)), *((3 * i + 5) % 16 for i in range(16)), *(7 * i % 16 for i in range(16))]
_START = (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476)


def _begun(words: list, fixed: np.ndarray) -> tuple[int, list[int]]:
    """The first steps of a first block, as far as all rows share the words: how many, and the four numbers after them."""
    a, b, c, d = _START
    n = 0
    while words[n] is None and n < 15:
        f = d ^ (b & (c ^ d))
        x = (a + f + int(_SINES[n]) + int(fixed[n])) & 0xFFFFFFFF
        s = _SHIFTS[n]
        a, b, c, d = d, (b + (x << s | x >> 32 - s)) & 0xFFFFFFFF, b, c
        n += 1
    return n, [a, b, c, d]


def _block(state: list, words: list[np.ndarray | None], fixed: np.ndarray, room: list[np.ndarray], first: bool, last: bool) -> list[np.ndarray]:
    """``state`` after one block of 16 words, of the last block its first half alone; a word is an array (or none) plus a number that all rows share."""
    xor, both, either, add, left, right, invert = np.bitwise_xor, np.bitwise_and, np.bitwise_or, np.add, np.left_shift, np.right_shift, np.invert
    done, begun = _begun(words, fixed) if first else (0, state)
    for now, old in zip(room, begun, strict=False):
        now[:] = old
    a, b, c, d, t, u, v = room
    sums = _SINES + fixed[_PLACES]
    each = [sums[i : i + 1].reshape(()) for i in range(64)]
    for i in range(done, 64):
        if i < 16:
            xor(c, d, t)
            both(t, b, t)
            xor(t, d, t)
        elif i < 32:
            xor(b, c, t)
            both(t, d, t)
            xor(t, c, t)
        elif i < 48:
            if i % 2:  # the other two are those of the step before
                xor(b, v, t)
            else:
                xor(b, c, v)
                xor(v, d, t)
        else:
            invert(d, t)
            either(t, b, t)
            xor(t, c, t)
        add(t, a, t)
        w = words[_PLACES[i]]
        if w is not None:
            add(t, w, t)
        add(t, each[i], t)
        s, back = _TURNS[i]
        left(t, s, u)
        right(t, back, t)
        either(t, u, t)
        add(t, b, t)
        a, b, c, d, t = d, t, b, c, a
    return [add(old, now) for old, now in zip(state[: 2 if last else 4], (a, b, c, d), strict=False)]


class Keys:
    """Texts of rows, hashed with prefixes and a suffix."""

    def __init__(self, texts: list[bytes]):
        self.length = np.fromiter(map(len, texts), np.int64, len(texts))
        width = max(1, int(self.length.max(initial=0)))
        self.bytes = np.array(texts, f"S{width}").view(np.uint8).reshape(len(texts), width)

    def bits(self, prefixes: list[bytes], suffix: bytes = b"") -> np.ndarray:
        """52 bits of every row for each prefix."""
        out = np.empty((len(prefixes), len(self.length)), np.uint64)
        for n, part, a, b in self._hashed(prefixes, suffix):
            out[n, part] = (a.astype(np.uint64) << np.uint64(20)) | (b >> 12)
        return out

    def uniform(self, prefixes: list[bytes], suffix: bytes = b"") -> np.ndarray:
        """Doubles in [0, 1)."""
        out = np.empty((len(prefixes), len(self.length)))
        for n, part, a, b in self._hashed(prefixes, suffix):
            out[n, part] = a * 2.0**-32 + (b >> 12) * 2.0**-52  # exact: 52 bits
        return out

    def uniform_at(self, prefixes: list[bytes], suffix: bytes, which: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """The same for some pairs of a prefix and a row, full pieces of them."""
        out, sizes = np.empty(len(rows)), np.array([len(x) for x in prefixes])
        for p in np.unique(sizes):
            same = np.nonzero(sizes[which] == p)[0]
            heads = np.frombuffer(b"".join(x.ljust(p) if len(x) < p else x[:p] for x in prefixes), np.uint8).reshape(-1, p)
            for _, part, a, b in self._hashed([bytes(p)], suffix, rows[same], heads, which[same]):
                out[same[part]] = a * 2.0**-32 + (b >> 12) * 2.0**-52
        return out

    def _hashed(self, prefixes: list[bytes], suffix: bytes, rows=None, heads=None, which=None):
        """Prefix, rows, and the first two numbers of their hashes."""
        length = self.length if rows is None else self.length[rows]
        end = np.frombuffer(suffix + b"\x80", np.uint8)
        for p in {len(x) for x in prefixes}:
            same = [n for n, x in enumerate(prefixes) if len(x) == p]
            blocks = (p + length + len(suffix) + 8) // 64 + 1
            for size in np.unique(blocks):
                of = np.nonzero(blocks == size)[0]
                for part in np.array_split(of, -(-len(of) // PIECE)):
                    text = self.bytes[part if rows is None else rows[part]]
                    found = self._piece(text, length[part], p, end, int(size), [prefixes[n] for n in same], None if heads is None else heads[which[part]])
                    at = slice(part[0], part[-1] + 1) if part[-1] - part[0] + 1 == len(part) else part
                    for n, (a, b) in zip(same, found, strict=True):
                        yield n, at, a, b

    def _piece(self, text, length, p, end, size, prefixes, heads):
        n, here = len(length), np.arange(len(length))
        room = np.zeros((n, size * 64), np.uint8)
        if heads is not None:
            room[:, :p] = heads
        wide = min(text.shape[1], size * 64 - p)
        room[:, p : p + wide] = text[:, :wide]
        for j, byte in enumerate(end):
            room[here, p + length + j] = byte
        words = room.view("<u4")
        words[:, -2] = 8 * (p + length + len(end) - 1)
        used = range(0 if heads is not None else p // 4, -(-(p + int(length.max()) + len(end)) // 4))
        some = [np.ascontiguousarray(words[:, i]) if i in used or i == size * 16 - 2 else None for i in range(size * 16)]
        steps = [np.empty(n, np.uint32) for _ in range(7)]
        for prefix in prefixes:
            fixed, state = np.zeros(size * 16, np.uint32), list(map(np.uint32, _START))
            fixed[: -(-p // 4)] = np.frombuffer(prefix + bytes(-p % 4), "<u4")
            for k in range(size):
                state = _block(state, some[16 * k : 16 * k + 16], fixed[16 * k : 16 * k + 16], steps, k == 0, k == size - 1)
            yield tuple(x.byteswap(inplace=True) for x in state)

    def gaussian(self, seed: int, purpose: str, suffix: bytes = b"") -> np.ndarray:
        """A standard normal draw of every row from two uniforms."""
        r, a = (self.uniform([f"{seed}:{purpose}_{x}:".encode()], suffix)[0] for x in "ra")
        return np.sqrt(-2.0 * np.log(1.0 - r)) * np.cos(2.0 * math.pi * a)


def laplace(u: np.ndarray, scale: float) -> np.ndarray:
    """As in ``privacy``: the inverse distribution function, u kept off 0 and 1."""
    v = np.clip(u, 2.0**-53, 1 - 2.0**-53)
    v -= 0.5
    w = np.abs(v)
    w *= 2.0
    np.subtract(1.0, w, w)
    np.log(w, w)
    w *= -scale
    return np.copysign(w, v, w)
