"""Removal of globally repeated runs of lines, cut where their content says.

A rolling hash over the hashes of the last two lines ends a chunk wherever it falls on one value in ``average``; so an
insertion moves only the boundaries beside it. A chunk counts if it has two lines with content or more, or as many words
as ``long_words``. Chunks are grouped by hash; in groups of two or more, bytes are compared, and every occurrence but
the first (by doc_id, then place) goes. All else stays byte for byte.

Chunks miss a passage whose neighbours move its boundaries. With ``passages``, each line's shortest runs of over
``long_words`` words, one from the line on and one up to it, are also looked up by half of their SHA-256, and every
occurrence but the first goes. Any repeated run of more words is made of such runs, so it goes as a whole, whatever
surrounds it; of a run that overlaps its own first occurrence, what lies beyond that goes.

Null texts stay null; empty texts stay empty. Rows that repeat a doc_id and text are each other's copies and keep the same
chunks; rows of one doc_id with different texts are told apart by their text's hash. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections import deque

import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from zspan.llm.common import map_batches, strings, written

AVERAGE, WINDOW, LONG_WORDS = 4, 2, 50
_BASE, _MASK = 0x100000001B3, (1 << 64) - 1


def lines_of(text: str) -> list[str]:
    """The lines with their ends; joined they give the text."""
    *lines, end = text.split("\n")
    return [x + "\n" for x in lines] + [end] * bool(end)


def chunks(text: str, average: int = AVERAGE, window: int = WINDOW) -> list[str]:
    """The text as chunks of whole lines, line ends included; joined they give the text."""
    lines = lines_of(text)
    out, start, rolling, seen, leaves = [], 0, 0, deque(), pow(_BASE, window, _MASK + 1)
    for i, line in enumerate(lines):
        h = xxhash.xxh3_64_intdigest(line.strip())
        seen.append(h)
        rolling = (rolling * _BASE + h) & _MASK
        if len(seen) > window:
            rolling = (rolling - seen.popleft() * leaves) & _MASK
        if ((rolling ^ (rolling >> 31)) * 0x9E3779B97F4A7C15 & _MASK) >> 40 & 0xFFFF < 0x10000 // average:
            out.append("".join(lines[start : i + 1]))
            start = i + 1
    if start < len(lines):
        out.append("".join(lines[start:]))
    return out


def counts_as_repeatable(chunk: str, long_words: int = LONG_WORDS) -> bool:
    return sum(1 for x in chunk.split("\n") if x.strip()) >= 2 or len(chunk.split(None, long_words)) > long_words


def passages_of(text: str, long_words: int = LONG_WORDS) -> list[tuple[int, int]]:
    """(first line, line behind) of the shortest runs of over ``long_words`` words from each line on and up to each line."""
    found, at, words = set(), [], [0]
    for i, line in enumerate(lines_of(text)):
        if n := len(line.split()):
            at.append(i)
            words.append(words[-1] + n)
    end = start = 0
    for k in range(len(at)):
        while end < len(at) and words[end] - words[k] <= long_words:
            end += 1
        if words[end] - words[k] > long_words:
            found.add((at[k], at[end - 1] + 1))
        while words[k + 1] - words[start + 1] > long_words:
            start += 1
        if words[k + 1] - words[start] > long_words:
            found.add((at[start], at[k] + 1))
    return sorted(found)


def repeated_passages(docs: DataFrame, long_words: int = LONG_WORDS) -> DataFrame:
    """(doc_id, text_hash, start, end): the lines of every passage that occurred before."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def digests(batches):
        for b in batches:
            out = {"doc_id": [], "text_hash": [], "start": [], "end": [], "high": [], "low": []}
            for i, t in zip(b.column("doc_id").to_pylist(), strings(b, "text"), strict=True):
                own, lines = xxhash.xxh3_64_intdigest(t) - (1 << 63), lines_of(t)
                for start, end in passages_of(t, long_words):
                    d = hashlib.sha256("".join(lines[start:end]).strip().encode()).digest()
                    out["doc_id"].append(i), out["text_hash"].append(own), out["start"].append(start), out["end"].append(end)
                    out["high"].append(int.from_bytes(d[:8], "big", signed=True)), out["low"].append(int.from_bytes(d[8:16], "big", signed=True))
            yield out

    found = written(map_batches(docs.select("doc_id", "text"), digests, f"doc_id {kind}, text_hash long, start int, end int, high long, low long"), "passages")
    place = F.struct("doc_id", "text_hash", "start", "end")
    first = written(found.groupBy("high", "low").agg(F.min(place).alias("first"), F.count("*").alias("n")).where("n > 1").drop("n"), "first")
    later = found.join(first.hint("merge"), ["high", "low"]).where(~place.eqNullSafe(F.col("first")))
    same = F.col("doc_id").eqNullSafe(F.col("first.doc_id")) & (F.col("text_hash") == F.col("first.text_hash"))
    return later.select("doc_id", "text_hash", F.when(same, F.greatest("start", "first.end")).otherwise(F.col("start")).alias("start"), "end").where("start < end")


def repeated(docs: DataFrame, average: int = AVERAGE, window: int = WINDOW, long_words: int = LONG_WORDS, passages: bool = False) -> DataFrame:
    """(doc_id, text_hash, drop): the runs of lines (start, end) to drop of each document that has some."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def hashes(batches):
        for b in batches:
            out = {"doc_id": [], "text_hash": [], "start": [], "end": [], "hash": [], "bytes": []}
            for i, t in zip(b.column("doc_id").to_pylist(), strings(b, "text"), strict=True):
                own = xxhash.xxh3_64_intdigest(t) - (1 << 63)
                end = 0
                for c in chunks(t, average, window):
                    start, end = end, end + len(lines_of(c))
                    if counts_as_repeatable(c, long_words):
                        data = c.strip().encode()
                        out["doc_id"].append(i), out["text_hash"].append(own), out["start"].append(start), out["end"].append(end)
                        out["hash"].append(xxhash.xxh3_64_intdigest(data) - (1 << 63)), out["bytes"].append(data)
            yield out

    found = map_batches(docs.select("doc_id", "text"), hashes, f"doc_id {kind}, text_hash long, start int, end int, hash long, bytes binary")
    # One narrow pass finds the hashes that occur twice; only their chunks travel for the comparison of bytes.
    keys = written(found.select("doc_id", "text_hash", "start", "hash"), "chunks")
    twice = written(keys.groupBy("hash").agg(F.count("*").alias("n")).where("n > 1").select("hash"), "twice")
    # the same plan at every size: whether the hashes would fit a broadcast depends on the data
    same = written(found.join(twice.hint("merge"), "hash", "left_semi"), "same")
    # written, so that both sides of the next join are dealt anew and a hot chunk's occurrences can be split
    first = written(same.groupBy("hash", "bytes").agg(F.min(F.struct("doc_id", "text_hash", "start")).alias("first"), F.count("*").alias("n")).where("n > 1"), "first")
    later = same.join(first.hint("merge"), ["hash", "bytes"]).where(~F.struct("doc_id", "text_hash", "start").eqNullSafe(F.col("first")))
    gone = later.select("doc_id", "text_hash", "start", "end")
    if passages:
        gone = gone.union(repeated_passages(docs, long_words))
    return gone.groupBy("doc_id", "text_hash").agg(F.collect_set(F.struct("start", "end")).alias("drop"))


def clean(docs: DataFrame, average: int = AVERAGE, window: int = WINDOW, long_words: int = LONG_WORDS, passages: bool = False) -> DataFrame:
    """The rows of ``docs`` with ``text`` after removal, and n_chunks and n_dropped in place of columns so named.

    n_dropped counts the chunks that lost a line.
    """
    names = docs.columns
    dropped = repeated(docs, average, window, long_words, passages)

    def hashed(batches):
        for b in batches:
            yield {"_hash": [xxhash.xxh3_64_intdigest(t) - (1 << 63) for t in strings(b, "_t")]} | {c: b.column(c) for c in ["_t", *rest]}

    rest = [f"_{k}" for k in range(len(names))]
    flat = docs.select(F.col("text").alias("_t"), *[(F.lit(None).cast("string") if c == "text" else F.col(f"`{c}`")).alias(r) for c, r in zip(names, rest, strict=True)])
    id_col = rest[names.index("doc_id")]
    keyed = map_batches(flat, hashed, T.StructType([T.StructField("_hash", T.LongType()), *flat.schema]))
    joined = keyed.join(dropped.withColumnsRenamed({"doc_id": "_id", "text_hash": "_h"}), F.col(id_col).eqNullSafe(F.col("_id")) & (F.col("_hash") == F.col("_h")), "left")

    def cut(batches):
        for b in batches:
            texts, n, gone = [], [], []
            for t, drop in zip(b.column("_t").to_pylist(), b.column("drop").to_pylist(), strict=True):
                if t is None or not t:
                    texts.append(t), n.append(0), gone.append(0)
                    continue
                found, lines, lost = chunks(t, average, window), lines_of(t), set()
                for d in drop or ():
                    lost.update(range(d["start"], d["end"]))
                texts.append("".join(x for k, x in enumerate(lines) if k not in lost) if lost else t)
                end, hit = 0, 0
                for c in found if lost else ():
                    start, end = end, end + len(lines_of(c))
                    hit += any(k in lost for k in range(start, end))
                n.append(len(found)), gone.append(hit)
            yield {c: b.column(c) for c in rest} | {"_t": texts, "n_chunks": n, "n_dropped": gone}

    counts = [T.StructField("n_chunks", T.IntegerType()), T.StructField("n_dropped", T.IntegerType())]
    out = map_batches(joined.select(*flat.columns, "drop"), cut, T.StructType([*flat.schema, *counts]))
    return out.select(*[(F.col("_t") if c == "text" else F.col(r)).alias(c) for c, r in zip(names, rest, strict=True) if c not in ("n_chunks", "n_dropped")], "n_chunks", "n_dropped")
