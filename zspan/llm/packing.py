"""Best-fit packing of tokenised documents, planned on counts of lengths.

The plan works on a histogram with one count for each length: lengths go from long to short, and each run of equal
pieces fills the tightest open bins. Its size depends on the sequence length only, not on the number of documents.
Documents take the planned slots by their rank within their length; a rank is a count within the task that tokenised
the document plus the counts of earlier tasks, so no length is ever sorted or gathered in one place.

Null text counts as empty: one end token. Repeated rows are packed once each. An empty table gives no rows.
"""

from __future__ import annotations

import json
import re
import zlib
from array import array
from collections import Counter, defaultdict
from collections.abc import Callable

import tiktoken
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql import Window as W

from zspan.llm.chunks import ChunkEncoder
from zspan.llm.common import map_batches, strings, written

SEQUENCE = 2048
#: The split of byte-level vocabularies of this family.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
_ENCODERS: dict[str, Callable[[str], bytes]] = {}


def _byte_of_char() -> dict[str, int]:
    """The printable stand-ins that vocabulary files use for bytes."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    other = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(other)}


def encoder(path: str) -> Callable[[str], bytes]:
    """Encodes as ``tokenizers`` does with this byte-level vocabulary file; its added tokens' strings give their ids."""
    if path not in _ENCODERS:
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        if any(t[k] for t in spec["added_tokens"] for k in ("lstrip", "rstrip", "single_word")):
            raise ValueError("added tokens that take in their surroundings are not supported")
        back, special = _byte_of_char(), {t["content"] for t in spec["added_tokens"] if t["special"]}
        ranks = {bytes(back[c] for c in token): i for token, i in spec["model"]["vocab"].items() if token not in special}
        bpe = tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens={})
        plain = ChunkEncoder(lambda s: array("I", bpe.encode_ordinary(s)).tobytes())
        added = {t["content"]: array("I", [t["id"]]).tobytes() for t in spec["added_tokens"]}
        split = re.compile("(" + "|".join(map(re.escape, sorted(added, key=len, reverse=True))) + ")") if added else None

        def encode(text: str) -> bytes:
            return b"".join(added[p] if k % 2 else plain(p) for k, p in enumerate(split.split(text) if split else [text]))

        _ENCODERS[path] = encode
    return _ENCODERS[path]


def pieces(docs: DataFrame, vocabulary: str, sequence: int = SEQUENCE, end_id: int = 0) -> DataFrame:
    """Each document's ids and an end token as pieces of at most ``sequence`` ids; only the first may be shorter."""
    end = array("I", [end_id]).tobytes()

    def cut(batches):
        encode, seen, task = encoder(vocabulary), Counter(), TaskContext.get().partitionId()
        for batch in batches:
            out = defaultdict(list)
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), strings(batch, "text"), strict=True):
                ids = encode(text) + end
                n = len(ids) // 4
                starts = [0, *range(n % sequence or sequence, n, sequence)]
                for k, (a, b) in enumerate(zip(starts, [*starts[1:], n], strict=True)):
                    row = (doc_id, k, a, b - a, zlib.crc32(ids[4 * a : 4 * b]), task, seen[b - a])
                    seen[b - a] += 1
                    for name, x in zip(("doc_id", "piece", "start", "length", "ids_crc32", "task", "nth"), row, strict=True):
                        out[name].append(x)
            if out:
                yield out

    kind = docs.schema["doc_id"].dataType.simpleString()
    return map_batches(docs.select("doc_id", "text"), cut, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long, task int, nth long")


def plan(counts: dict[int, int], sequence: int = SEQUENCE) -> list[tuple[int, int, int, int, int]]:
    """Best fit over counts, long pieces first: (length, first rank, pieces a bin, first bin, offset) by rank.

    Pieces of one length from the first rank on fill bins in turn, so many to each, from the offset on.
    """
    room: dict[int, list[tuple[int, int]]] = defaultdict(list)  # free ids -> runs of bins (first, number)
    slots, bins = [], 0
    for length in sorted(counts, reverse=True):
        left, rank = counts[length], 0
        while left:
            free = min((r for r in room if r >= length and room[r]), default=sequence)
            each = free // length
            if not room[free]:
                room[free].append((bins, -(-left // each)))
                bins += room[free][-1][1]
            first, number = room[free].pop()
            whole = min(number, left // each)
            if whole < number:
                room[free].append((first + whole, number - whole))
            if whole:
                slots.append((length, rank, each, first, sequence - free))
                room[free - each * length].append((first, whole))
                rank, left = rank + whole * each, left - whole * each
            else:  # the last few share one bin
                room[free].pop()
                if number > 1:
                    room[free].append((first + 1, number - 1))
                slots.append((length, rank, left, first, sequence - free))
                room[free - left * length].append((first, 1))
                rank, left = rank + left, 0
    return slots


def pack(docs: DataFrame, vocabulary: str, sequence: int = SEQUENCE, end_id: int = 0) -> DataFrame:
    """Every piece of every document with its place: sequence_id and the gapless offset there."""
    spark = docs.sparkSession
    cut = written(pieces(docs, vocabulary, sequence, end_id), "pieces")
    counts = cut.groupBy("task", "length").agg(F.count("*").alias("n"))
    before = W.partitionBy("length").orderBy("task").rowsBetween(W.unboundedPreceding, -1)
    counts = counts.withColumn("before", F.coalesce(F.sum("n").over(before), F.lit(0)))
    total = {r["length"]: r["n"] for r in cut.groupBy("length").agg(F.count("*").alias("n")).collect()}  # one row a length at most
    by_length = defaultdict(list)
    for length, *slot in plan(total, sequence):
        by_length[length].append(tuple(slot))
    slot_type = T.ArrayType(T.StructType([T.StructField(x, T.LongType()) for x in ("rank", "each", "bin", "at")]))
    slots = spark.createDataFrame(list(by_length.items()), T.StructType([T.StructField("length", T.LongType()), T.StructField("slots", slot_type)]))
    ranked = cut.join(counts.drop("n"), ["task", "length"]).withColumn("r", F.col("nth") + F.col("before"))
    placed = ranked.join(F.broadcast(slots), "length").withColumn("s", F.element_at(F.filter("slots", lambda s: s["rank"] <= F.col("r")), -1))
    nth = F.col("r") - F.col("s.rank")
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("s.bin") + F.floor(nth / F.col("s.each"))).cast("long").alias("sequence_id"), (F.col("s.at") + nth % F.col("s.each") * F.col("length")).cast("long").alias("offset"))
