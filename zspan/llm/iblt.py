"""Document fingerprints as invertible Bloom lookup tables of paragraph digests.

A paragraph is a line, or a sentence of it. Its 64-bit digest, with the number of earlier equal paragraphs mixed in,
enters three cells, one in each third of the table; a cell keeps a count, the exclusive-or of digests and that of
check hashes. Two tables subtract cell by cell; peeling cells that hold one digest recovers the paragraphs in which the
versions differ. Where peeling gets stuck, both versions are put into tables of twice the size, until it succeeds.

Null text counts as empty: no paragraph. Equal texts have equal fingerprints, and likeness 1. Repeated rows and ids are
ordered by text. An empty table gives no rows. Null ids come last, as the smallest.
"""

from __future__ import annotations

import base64
import hashlib
import re

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zspan.llm.common import map_batches, parts, strings

#: Cells of a stored fingerprint.
CELLS = 24
_SENTENCE = re.compile(r"(?<=[.!?]) +|\n+")
_M1, _M2 = np.uint64(0xFF51AFD7ED558CCD), np.uint64(0xC4CEB9FE1A85EC53)


def digests(text: str) -> np.ndarray:
    """A 64-bit digest of each paragraph; repeats differ by their number."""
    found = [xxhash.xxh3_64_intdigest(p) for p in _SENTENCE.split(text) if p]
    out = np.array(found, np.uint64)
    if len(set(found)) < len(found):
        seen: dict[int, int] = {}
        for i, d in enumerate(found):
            k = seen[d] = seen.get(d, -1) + 1
            if k:
                out[i] = xxhash.xxh3_64_intdigest(f"{d}/{k}")
    return out


def _mix(d: np.ndarray, salt: int) -> np.ndarray:
    d = (d ^ (d >> np.uint64(33)) ^ np.uint64(salt)) * _M1
    d = (d ^ (d >> np.uint64(29))) * _M2
    return d ^ (d >> np.uint64(32))


def tables(lists: list[np.ndarray], cells: int) -> np.ndarray:
    """One table for each list: [list, cell, (count, digests, checks)] as unsigned 64-bit."""
    out = np.zeros((len(lists), cells, 3), np.uint64)
    if not lists:
        return out
    d, row, third = np.concatenate(lists), np.repeat(np.arange(len(lists)), [len(x) for x in lists]), cells // 3
    check = _mix(d, 99) & np.uint64(0xFFFFFFFF)
    for k in range(3):
        at = row * cells + k * third + (_mix(d, k + 1) % np.uint64(third)).astype(np.int64)
        order = np.argsort(at, kind="stable")
        at, own, chk = at[order], d[order], check[order]
        first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]]) if len(at) else np.empty(0, np.int64)
        flat = out.reshape(-1, 3)
        if len(first):
            flat[at[first], 0] = np.diff(np.r_[first, len(at)]).astype(np.uint64)
            flat[at[first], 1] = np.bitwise_xor.reduceat(own, first)
            flat[at[first], 2] = np.bitwise_xor.reduceat(chk, first)
    return out


def peel(diff: np.ndarray) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
    """Of each subtracted table the digests only in the first and only in the second, and whether it came out empty."""
    diff = diff.copy()
    n, cells, _ = diff.shape
    third, got = cells // 3, []
    live = np.arange(n)
    while len(live):
        part = diff[live]
        count = part[..., 0].view(np.int64)
        row, col = np.nonzero((np.abs(count) == 1) & ((_mix(part[..., 1], 99) & np.uint64(0xFFFFFFFF)) == part[..., 2]))
        fits = (_mix(part[row, col, 1], 1) % np.uint64(third)).astype(np.int64), (_mix(part[row, col, 1], 2) % np.uint64(third)).astype(np.int64), (_mix(part[row, col, 1], 3) % np.uint64(third)).astype(np.int64)
        own = np.choose(col // third, fits) == col % third if len(col) else np.empty(0, bool)
        row, col = row[own], col[own]
        if not len(row):
            break
        d, sign, row = part[row, col, 1], count[row, col], live[row]
        _, first = np.unique(np.stack([row.astype(np.uint64), d]), axis=1, return_index=True)
        d, sign, row = d[first], sign[first], row[first]
        got.append((row, d, sign))
        check = _mix(d, 99) & np.uint64(0xFFFFFFFF)
        for k in range(3):
            at = k * third + (_mix(d, k + 1) % np.uint64(third)).astype(np.int64)
            np.subtract.at(diff[..., 0].view(np.int64), (row, at), sign)
            np.bitwise_xor.at(diff[..., 1], (row, at), d)
            np.bitwise_xor.at(diff[..., 2], (row, at), check)
        live = np.unique(row)
    empty = ~diff.any((1, 2))
    rows = np.concatenate([g[0] for g in got]) if got else np.empty(0, np.int64)
    ds = np.concatenate([g[1] for g in got]) if got else np.empty(0, np.uint64)
    signs = np.concatenate([g[2] for g in got]) if got else np.empty(0, np.int64)
    order = np.argsort(rows, kind="stable")
    rows, ds, signs = rows[order], ds[order], signs[order]
    cuts = np.searchsorted(rows, np.arange(n + 1))
    spans = [(ds[a:b], signs[a:b]) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
    return [(x[s > 0], x[s < 0]) for x, s in spans], empty


def differences(left: list[np.ndarray], right: list[np.ndarray], cells: int = CELLS) -> list[tuple[np.ndarray, np.ndarray]]:
    """The digests in which each pair of versions differs, from tables as large as peeling needs."""
    out: list = [None] * len(left)
    todo = np.arange(len(left))
    while len(todo):
        step, later = max(1, 2_000_000 // cells), []
        for a in range(0, len(todo), step):
            some = todo[a : a + step]
            x, y = tables([left[i] for i in some], cells), tables([right[i] for i in some], cells)
            diff = x ^ y
            diff[..., 0] = x[..., 0] - y[..., 0]
            found, empty = peel(diff)
            for i, f, ok in zip(some, found, empty, strict=True):
                if ok:
                    out[i] = f
                else:
                    later.append(i)
        todo, cells = np.array(later, np.int64), cells * 2
    return out


def likeness(n_left: int, n_right: int, only_left: int, only_right: int) -> float:
    """Shared paragraphs over all paragraphs of the two versions; 1 for two empty ones."""
    shared = n_left - only_left
    union = shared + only_left + only_right
    return shared / union if union else 1.0


def _text_of(table: np.ndarray, digest_count: int, rest: np.ndarray) -> str:
    return f"{digest_count}:" + base64.b64encode(table.tobytes()).decode() + f":{int(np.bitwise_xor.reduce(rest)) if len(rest) else 0:016x}"


def fingerprints(lists: list[np.ndarray], cells: int = CELLS) -> list[str]:
    return [_text_of(t, len(d), d) for t, d in zip(tables(lists, cells), lists, strict=True)]


def with_next(docs: DataFrame) -> DataFrame:
    """Rows (doc_id, text, bucket, order, own) such that within a bucket each own row is followed by its next document.

    Buckets are ranges of ids; the first row of each is copied behind the rows of the one before, that of the first
    bucket (the greatest id) behind the last. So texts move once, and only one row a bucket moves twice.
    """
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"))
    wanted = 4 * parts(docs.sparkSession)
    cuts = np.unique(np.array(ids.agg(F.percentile_approx("doc_id", F.lit([i / wanted for i in range(1, wanted)]) if wanted > 1 else F.lit([0.5]), 10_000)).first()[0] or [], np.int64))  # one number a bucket

    def bucket_of(values: pd.Series) -> np.ndarray:
        known = values.notna().to_numpy()
        return np.where(known, len(cuts) - np.searchsorted(cuts, values.fillna(0).to_numpy(np.int64), side="right"), len(cuts))

    @F.pandas_udf("int")
    def bucket(values: pd.Series) -> pd.Series:
        return pd.Series(bucket_of(values), dtype="int32")

    tops = {r["b"]: r["top"] for r in ids.withColumn("b", bucket("doc_id")).groupBy("b").agg(F.max("doc_id").alias("top")).collect()}  # one row a bucket
    used = sorted(tops)
    before = {tops[b]: used[k - 1] for k, b in enumerate(used)}  # the first row of a bucket also ends the one before

    @F.pandas_udf("array<int>")
    def places(values: pd.Series) -> pd.Series:
        also = [before.get(None if pd.isna(v) else int(v), -1) for v in values]
        return pd.Series([[b, o] if o >= 0 else [b] for b, o in zip(bucket_of(values).tolist(), also, strict=True)])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.select("doc_id", "text", F.posexplode(places("doc_id")).alias("pos", "bucket")).select("doc_id", "text", "bucket", (F.col("pos") == 0).alias("own"))


def versions(docs: DataFrame, cells: int = CELLS) -> DataFrame:
    """Fingerprints of every text and of its edit by the next document's start, and how alike they are."""
    kind = docs.schema["doc_id"].dataType.simpleString()
    n = parts(docs.sparkSession)
    rows = with_next(docs).repartition(n, "bucket").sortWithinPartitions("bucket", F.desc("own"), F.desc_nulls_last("doc_id"), "text")

    def pairs(batches):
        """Consecutive rows of a bucket as lists of (id, text, next text), a batch at a time."""
        last, out, size = None, [], 0
        for b in batches:
            for i, t, k, own in zip(*(b.column(c).to_pylist() for c in ("doc_id", "text", "bucket", "own")), strict=True):
                if last is not None and last[2] == k and last[3]:
                    out.append((last[0], last[1], t))
                    size += len(last[1]) + len(t)
                    if size > 3_000_000 or len(out) >= 1000:
                        yield out
                        out, size = [], 0
                last = (i, t, k, own)
        if out:
            yield out

    def run(batches):
        for group in pairs(batches):
            texts, following = [g[1] for g in group], [g[2] for g in group]
            edited = [t[: len(t) - len(t) // 3] + f[: len(t) // 3] for t, f in zip(texts, following, strict=True)]
            own, new, after = ([digests(t) for t in x] for x in (texts, edited, following))
            near = [[likeness(len(a), len(b), len(x), len(y)) for a, b, (x, y) in zip(own, other, differences(own, other, cells), strict=True)] for other in (new, after)]
            yield {
                "doc_id": [g[0] for g in group],
                "n_chars": [len(t) for t in texts],
                "edited_sha256": [hashlib.sha256(t.encode()).hexdigest() for t in edited],
                "fingerprint": fingerprints(own, cells),
                "edited_fingerprint": fingerprints(new, cells),
                "near_edited": near[0],
                "near_next": near[1],
            }

    out = map_batches(rows, run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")
    return out.withColumn("doc_id", F.col("doc_id").cast(kind))
