"""Public vocabularies by file path, held once per worker process."""

from __future__ import annotations

import base64
from functools import lru_cache

import numpy as np

#: A piece without white space of this many characters makes a plain pair scan quadratic.
LONG_PIECE = 3000


def ranks_of(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class ByteVocabulary:
    """Whole-document encoding with a byte-level vocabulary.

    ``json_path`` defines the ids (library ``tokenizers``). ``ranks_path`` is the
    same vocabulary as ranks: it encodes the ordinary texts several times faster.
    Texts with a special token's string, or with pieces so long that a pair scan
    would be quadratic, go to the defining library.
    """

    def __init__(self, json_path: str, ranks_path: str, pattern: str):
        import tiktoken
        from tokenizers import Tokenizer

        self.slow = Tokenizer.from_file(json_path)
        ranks = ranks_of(ranks_path)
        self.fast = tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.marks = [t.content for t in self.slow.get_added_tokens_decoder().values()]
        size = max([*ranks.values(), *self.slow.get_added_tokens_decoder()]) + 1
        self.n_bytes = np.ones(size, np.int64)
        for token, i in ranks.items():
            self.n_bytes[i] = len(token)
        for i, token in self.slow.get_added_tokens_decoder().items():
            self.n_bytes[i] = len(token.content.encode())

    def plain(self, text: str) -> bool:
        if any(m in text for m in self.marks):
            return False
        if len(text) < LONG_PIECE:
            return True
        words = text.split()
        inside = sum(map(len, words))
        return max(map(len, words), default=0) < LONG_PIECE and len(text) - inside - len(words) < LONG_PIECE

    def ids(self, text: str) -> np.ndarray:
        if self.plain(text):
            return self.fast.encode_to_numpy(text, disallowed_special=())
        return np.array(self.slow.encode(text, add_special_tokens=False).ids, np.uint32)


@lru_cache(maxsize=2)
def byte_vocabulary(json_path: str, ranks_path: str, pattern: str) -> ByteVocabulary:
    return ByteVocabulary(json_path, ranks_path, pattern)
