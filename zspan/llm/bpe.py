"""Byte-level BPE by dynamic programming over prefixes.

Every prefix of a byte string has one encoding, so it has one last token. That token t is the only vocabulary entry
ending there for which (last token of the prefix before t, t) is a pair that merging would leave alone. The table of last
tokens is all the state there is: appending bytes only extends it, and after an edit it is recomputed from the edit
until it agrees with the old table for as many positions as the longest token has bytes.

Null text counts as empty (no ids). Any valid text round-trips. Repeated rows give repeated results.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from collections import defaultdict

import ahocorasick
import numpy as np
import regex
from pyspark.sql import DataFrame

from zspan.llm.chunks import SPACE, ChunkEncoder
from zspan.llm.common import map_batches, strings

_CODECS: dict[tuple[str, str], Codec] = {}


class Vocabulary:
    """Tokens by rank, and which pairs of neighbours an encoding can hold."""

    def __init__(self, ranks: dict[bytes, int], remembered: int = 1_000_000):
        self.ranks, self.longest = ranks, max(map(len, ranks), default=1)
        self.tokens = {i: t for t, i in ranks.items()}
        self._pairs: dict[int, bool] = {}
        self._alone: dict[int, bool] = {}
        self._remembered = remembered
        ends = ahocorasick.Automaton()
        for t, i in ranks.items():
            ends.add_word(t.decode("latin-1"), (i, len(t)))
        ends.make_automaton()
        self._ends = ends.iter

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        with open(path, "rb") as f:
            return cls({base64.b64decode(t): int(i) for t, i in (line.split() for line in f if line.strip())})

    def merged(self, data: bytes) -> list[int]:
        """The definition: always merge the neighbours that form the token of the lowest rank, the first of equals."""
        seq = [data[i : i + 1] for i in range(len(data))]
        while len(seq) > 1:
            rank, i = min((self.ranks.get(seq[i] + seq[i + 1], 1 << 60), i) for i in range(len(seq) - 1))
            if rank == 1 << 60:
                break
            seq[i : i + 2] = [seq[i] + seq[i + 1]]
        return [self.ranks[t] for t in seq]

    def stays(self, left: int | None, right: int) -> bool:
        """Whether ``right`` can be the last token after ``left``, or the only one."""
        if left is None:
            if right not in self._alone:
                self._alone[right] = self.merged(self.tokens[right]) == [right]
            return self._alone[right]
        key = left << 32 | right
        got = self._pairs.get(key)
        if got is None:
            if len(self._pairs) >= self._remembered:
                self._pairs.clear()
            got = self._pairs[key] = self.merged(self.tokens[left] + self.tokens[right]) == [left, right]
        return got

    def path(self, last: list[int]) -> list[int]:
        out, end, tokens = [], len(last), self.tokens
        while end:
            out.append(last[end - 1])
            end -= len(tokens[out[-1]])
        return out[::-1]

    def last_tokens(self, data: bytes) -> list[int]:
        """The last token of every prefix: an automaton names the tokens that end at each byte."""
        last, known, stays, done = [], self._pairs.get, self.stays, 0
        for at, (token, length) in self._ends(data.decode("latin-1")):
            if at < done:
                continue
            start = at + 1 - length
            if start:
                left = last[start - 1]
                good = known(left << 32 | token)
                if good is None:
                    good = stays(left, token)
            else:
                good = stays(None, token)
            if good:
                last.append(token)
                done += 1
        if done < len(data):
            raise ValueError("the vocabulary lacks a byte")
        return last


class PrefixEncoder:
    """The last token of every prefix of ``data``, kept under appends and edits."""

    def __init__(self, vocabulary: Vocabulary, data: bytes = b""):
        self.vocabulary, self.data, self.last = vocabulary, data, vocabulary.last_tokens(data)

    def _token_at(self, data: bytes, end: int, last: list[int]) -> int:
        v = self.vocabulary
        for start in range(max(0, end - v.longest), end):
            token = v.ranks.get(data[start:end])
            if token is not None and v.stays(last[start - 1] if start else None, token):
                return token
        raise ValueError("the vocabulary lacks a byte")

    def append(self, more: bytes) -> None:
        self.data += more
        for end in range(len(self.last) + 1, len(self.data) + 1):
            self.last.append(self._token_at(self.data, end, self.last))

    def splice(self, start: int, stop: int, new: bytes) -> int:
        """Replace bytes start..stop; returns how many prefixes were computed again."""
        data, old = self.data[:start] + new + self.data[stop:], self.last
        last, shift, same, done = old[:start], len(new) - (stop - start), 0, 0
        for end in range(start + 1, len(data) + 1):
            was = end - shift
            if end > start + len(new) and same >= self.vocabulary.longest:
                last += old[was - 1 :]
                break
            last.append(self._token_at(data, end, last))
            done += 1
            same = same + 1 if end > start + len(new) and last[-1] == old[was - 1] else 0
        self.data, self.last = data, last
        return done

    def ids(self) -> list[int]:
        return self.vocabulary.path(self.last)


class Codec:
    """Whole texts: the split pattern's matches one by one, each by the prefix table."""

    def __init__(self, vocabulary: Vocabulary, pattern: str, remembered: int = 500_000):
        self.vocabulary = vocabulary
        self.split = regex.compile(pattern.replace(r"[^\s", rf"[^{SPACE}").replace(r"\S", rf"[^{SPACE}]").replace(r"\s", rf"[{SPACE}]")).findall
        self.remembered = remembered
        self._known: dict[str, bytes] = {}
        self.encode_bytes = ChunkEncoder(self._encode)

    def _match(self, match: str) -> bytes:
        data = match.encode()
        whole = self.vocabulary.ranks.get(data)  # a match that is a token is that token
        ids = [whole] if whole is not None else self.vocabulary.path(self.vocabulary.last_tokens(data))
        got = array("I", ids).tobytes()
        if len(match) <= 64:
            if len(self._known) >= self.remembered:
                self._known.clear()
            self._known[match] = got
        return got

    def _encode(self, text: str) -> bytes:
        return b"".join([self._known.get(m) or self._match(m) for m in self.split(text)])

    def decode_bytes(self, ids: bytes) -> bytes:
        return b"".join(map(self.vocabulary.tokens.__getitem__, np.frombuffer(ids, "<u4").tolist()))


def codec(path: str, pattern: str) -> Codec:
    if (path, pattern) not in _CODECS:
        _CODECS[path, pattern] = Codec(Vocabulary.load(path), pattern)
    return _CODECS[path, pattern]


def encode(docs: DataFrame, vocabulary: str, pattern: str) -> DataFrame:
    """doc_id and the ids of each whole text, as little-endian unsigned 32-bit bytes."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        c = codec(vocabulary, pattern)
        for b in batches:
            yield {"doc_id": b.column("doc_id"), "ids": [c.encode_bytes(t) for t in strings(b, "text")]}

    return map_batches(docs.select("doc_id", "text"), run, f"doc_id {kind}, ids binary")


def decode(tokens: DataFrame, vocabulary: str, pattern: str) -> DataFrame:
    """doc_id, ids and the bytes that the ids stand for."""
    kind = tokens.schema["doc_id"].dataType.simpleString()

    def run(batches):
        c = codec(vocabulary, pattern)
        for b in batches:
            ids = [x or b"" for x in b.column("ids").to_pylist()]
            yield {"doc_id": b.column("doc_id"), "ids": ids, "decoded": [c.decode_bytes(x) for x in ids]}

    return map_batches(tokens.select("doc_id", "ids"), run, f"doc_id {kind}, ids binary, decoded binary")


def round_trip(docs: DataFrame, vocabulary: str, pattern: str) -> DataFrame:
    """Digests of each text's ids and of their decoding: doc_id, n_tokens, ids_sha256, decoded_sha256."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        c = codec(vocabulary, pattern)
        for b in batches:
            out = defaultdict(list)
            for t in strings(b, "text"):
                ids = c.encode_bytes(t)
                out["n_tokens"].append(len(ids) // 4)
                out["ids_sha256"].append(hashlib.sha256(ids).hexdigest())
                out["decoded_sha256"].append(hashlib.sha256(c.decode_bytes(ids)).hexdigest())
            yield {"doc_id": b.column("doc_id"), **{k: out[k] for k in ("n_tokens", "ids_sha256", "decoded_sha256")}}

    return map_batches(docs.select("doc_id", "text"), run, f"doc_id {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
