"""Texts as runs that a byte-level tokenizer's split pattern never joins."""

from __future__ import annotations

import re

#: White space as Unicode's property has it, for patterns that must agree with other engines.
SPACE = "\\t\\n\\x0b\\x0c\\r \\x85\\xa0\\u1680\\u2000-\\u200a\\u2028\\u2029\\u202f\\u205f\\u3000"
_MIXED = re.compile(r"\s ")


class WordCache(dict):
    """Encoded bytes of ``prefix + word``; emptied when it holds ``most`` words, which bounds a worker's memory."""

    def __init__(self, encode, prefix: str, most: int = 300_000):
        super().__init__()
        self.encode, self.prefix, self.most = encode, prefix, most

    def __missing__(self, word: str) -> bytes:
        if len(self) >= self.most:
            self.clear()
        got = self.encode(self.prefix + word)
        if len(word) <= 64:
            self[word] = got
        return got


class ChunkEncoder:
    """Ids of whole texts as little-endian unsigned 32-bit bytes.

    A split between a character that is no white space and a space never divides a match of the pattern, so such runs
    are encoded by themselves and remembered. Texts with white space before a space go to ``encode`` whole.
    """

    def __init__(self, encode):
        self.encode, self.first, self.rest = encode, WordCache(encode, "", 20_000), WordCache(encode, " ")

    def __call__(self, text: str) -> bytes:
        if not text:
            return b""
        if _MIXED.search(text):
            return self.encode(text)
        words = text.split(" ")
        first = self.first[words[0]] if words[0] else b""
        return first + b"".join(map(self.rest.__getitem__, words[1:]))
