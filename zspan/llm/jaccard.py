"""Jaccard similarity join on word shingles by chosen paths, with the links of every document counted exactly.

1. A document's set holds the hashes of its runs of five words (lower case, letters and digits); fewer words make one
   run. Documents with equal sets are one class, represented by the least doc_id.
2. A set becomes a vector of minwise tokens. Each of several runs splits all sets on one sampled token; a bucket that
   is still large is split again on tokens sampled for its own path, one more at each level, for as long as that lowers
   the number of comparisons; what no longer shrinks is alike throughout and passes whole. Buckets with the same members
   count once. Small buckets are compared by brute force on the vectors, with a bar far below the threshold. Runs are as
   many as the target recall asks for.
3. What passes joins into groups of candidates. A group of more than one block is cut first, without losing a link: two
   sets at the threshold share one of the rarest shingles of each, so many that the rest alone cannot hold the common
   ones; sets join by these alone, and a passage that many of them quote no longer holds them together.
4. In a group all sets are compared exactly, block against block, by counting common shingles in a matrix product. A
   block is bounded in shingles and in members, so a large group makes many tasks of bounded memory. Links are counted
   once, and pairs are never listed: each task returns counts and a spanning forest.
5. Components of the verified links are the classes.

Null and empty texts and texts without a word link to nothing. Repeated rows are copies of each other and give one row;
a doc_id with several texts counts with the one of the least set hash. Null ids link to nothing. Ids are whole numbers, as
numbers or as text; any other text raises an error.
"""

from __future__ import annotations

import itertools
import math
import re
from collections import defaultdict
from itertools import chain

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from zspan.llm.common import forget, map_batches, parts, strings, text_slices, written
from zspan.llm.components import components
from zspan.plans import small as small_table

WORDS, THRESHOLD, RECALL = 5, 0.8, 0.999999
TOKENS, SMALL, FAN = 64, 256, 3
#: Shingles and members in a block of the exact comparison, about.
BLOCK_SHINGLES, BLOCK_MEMBERS = 250_000, 512
#: Bits of the map by which unasked documents are left out before a shuffle, and counters by which shingles are ranked.
MAP_BITS, COUNTERS = 1 << 25, 1 << 16
_WORD = re.compile(r"[^\W_]+")
_RNG = np.random.default_rng(20)
_MIX_A = _RNG.integers(1, 2**63, TOKENS, dtype=np.uint64) | np.uint64(1)
_MIX_B = _RNG.integers(1, 2**63, TOKENS, dtype=np.uint64)


def shingles(texts: list[str], words: int = WORDS) -> list[np.ndarray]:
    """The sorted distinct 64-bit shingle hashes of each text."""
    lists = [_WORD.findall(t.lower()) for t in texts]
    counts = np.array([len(x) for x in lists])
    if not counts.sum():
        return [np.empty(0, np.uint64)] * len(texts)
    code, uniques = pd.factorize(np.array(list(chain.from_iterable(lists)), dtype=object))
    table = np.array([xxhash.xxh64_intdigest(w) for w in uniques.tolist()], np.uint64)
    h, mul = table[code], np.uint64(0x9E3779B97F4A7C15)
    out, at = [], 0
    for n in counts.tolist():
        own, at = h[at : at + n], at + n
        width = min(words, n)
        if not n:
            out.append(own)
            continue
        s = np.zeros(n - width + 1, np.uint64)
        for k in range(width):
            s = (s ^ own[k : n - width + 1 + k]) * mul
            s ^= s >> np.uint64(29)
        out.append(np.unique(s))
    return out


def minwise(s: np.ndarray) -> np.ndarray:
    """One 32-bit token for each of the fixed hash functions."""
    best = np.full(TOKENS, np.iinfo(np.uint64).max, np.uint64)
    for a in range(0, len(s), 2048):
        np.minimum(best, (s[None, a : a + 2048] * _MIX_A[:, None] + _MIX_B[:, None]).min(1), out=best)
    return (best >> np.uint64(32)).astype(np.uint32)


def sets(docs: DataFrame, words: int = WORDS) -> DataFrame:
    """(doc_id, set_hash, n, tokens) of each row; n = 0 and null hash and tokens where there is no word."""

    def run(batches):
        for b in batches:
            texts = strings(b, "text")
            found = [s for a, z in text_slices(texts) for s in shingles(texts[a:z], words)]
            out = {"doc_id": b.column("doc_id"), "n": [len(s) for s in found]}
            out["set_hash"] = [xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None for s in found]
            out["tokens"] = [minwise(s).tobytes() if len(s) else None for s in found]
            yield out

    return map_batches(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, "doc_id long, set_hash binary, n int, tokens binary")


def runs_for(recall: float, threshold: float, fan: int = FAN) -> int:
    """Runs after which a pair at the threshold has met with this probability, however deep its buckets are split.

    At level k a pair stays together unless it differs on all ``fan`` + k - 1 tokens; the product converges.
    """
    meets = threshold * math.prod(1 - (1 - threshold) ** (fan + k) for k in range(60))
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - meets)))


def _keys(level: int, fan: int):
    """(doc_id, tokens, path) -> the buckets below: the path mixed with each of ``fan`` tokens sampled for it."""

    def run(batches):
        for b in batches:
            ids, path = b.column("doc_id").to_pylist(), b.column("path").to_numpy(zero_copy_only=False).view(np.uint64)
            tokens = np.frombuffer(b"".join(b.column("tokens").to_pylist()), np.uint32).reshape(-1, TOKENS)
            pick = (path + np.uint64(level)) * np.uint64(0xD6E8FEB86659FD93)
            pick ^= pick >> np.uint64(32)
            out = {"doc_id": [], "bucket": [], "above": []}
            for k in range(fan):  # an odd step, so no token is sampled twice
                which = ((pick + np.uint64(k) * ((pick >> np.uint64(8)) | np.uint64(1))) % np.uint64(TOKENS)).astype(np.int64)
                key = (path * np.uint64(0xBF58476D1CE4E5B9)) ^ tokens[np.arange(len(ids)), which].astype(np.uint64) ^ (which.astype(np.uint64) << np.uint64(32)) ^ np.uint64(level << 40)
                key *= np.uint64(0x94D049BB133111EB)
                key ^= key >> np.uint64(31)
                out["doc_id"] += ids
                out["bucket"] += key.view(np.int64).tolist()
                out["above"] += b.column("above").to_pylist()
            yield out

    return run


def _buckets(level: int, nodes: DataFrame, fan: int) -> tuple[DataFrame, DataFrame]:
    """(bucket, doc_id) of all buckets of a level, and the size and a digest of the members of those with two or more."""
    members = written(map_batches(nodes, _keys(level, fan), "doc_id long, bucket long, above long"), f"members{level}")
    hashed = F.xxhash64("doc_id")
    digest = F.struct(F.bit_xor(hashed), F.sum(hashed.bitwiseAND(F.lit((1 << 40) - 1))))
    return members, members.groupBy("bucket").agg(F.count("*").alias("size"), digest.alias("digest")).where("size > 1")


def _near(bar: float):
    """Runs of equal buckets, whole: a star for each part of the bucket that the vectors hold together."""

    def edges(ids: list[int], tokens: list[bytes]):
        m, t = len(ids), np.frombuffer(b"".join(tokens), np.uint32).reshape(-1, TOKENS)
        root = np.arange(m)
        for i in range(m - 1):
            close = np.nonzero((t[i + 1 :] == t[i]).sum(1) >= bar * TOKENS)[0] + i + 1
            if len(close):
                joined = np.unique(root[np.append(close, i)])
                root[np.isin(root, joined)] = joined[0]
        for i in range(m):
            if root[i] != i:
                yield ids[i], ids[root[i]]

    def run(batches):
        key, ids, tokens = None, [], []
        for b in batches:
            out = {"u": [], "v": []}
            for bucket, i, t in zip(*(b.column(c).to_pylist() for c in ("bucket", "doc_id", "tokens")), strict=True):
                if bucket != key:
                    for u, v in edges(ids, tokens) if len(ids) > 1 else ():
                        out["u"].append(u), out["v"].append(v)
                    key, ids, tokens = bucket, [], []
                ids.append(i), tokens.append(t)
            if out["u"]:
                yield out
        if len(ids) > 1:
            pairs = list(edges(ids, tokens))
            yield {"u": [u for u, _ in pairs], "v": [v for _, v in pairs]}

    return run


def candidates(reps: DataFrame, threshold: float = THRESHOLD, recall: float = RECALL, small: int = SMALL, fan: int = FAN) -> DataFrame:
    """Edges (u, v) whose components hold every pair that the runs find; reps is (doc_id, tokens)."""
    runs = min(TOKENS, runs_for(recall, threshold, fan))
    nodes = reps.withColumns({"path": F.lit(0).cast("long"), "above": F.lit(None).cast("long")})
    found: DataFrame | None = None
    bar = max(0.0, threshold - 6 * math.sqrt(threshold * (1 - threshold) / TOKENS))
    for level in itertools.count():
        split = runs if level == 0 else min(TOKENS, fan + level - 1)
        members, sizes = _buckets(level, nodes, split)
        once = sizes.groupBy("size", "digest").agg(F.min("bucket").alias("bucket"))
        one = written(members.join(once, "bucket").join(reps, "doc_id"), f"level{level}")
        deal = one.where(F.col("size") <= small).repartition(parts(reps.sparkSession), "bucket").sortWithinPartitions("bucket", "doc_id")
        edges = map_batches(deal.select("bucket", "doc_id", "tokens"), _near(bar), "u long, v long").distinct()
        # all parts of a bucket cost less than the bucket only while each is this much smaller
        size = F.col("size").cast("double")
        alike = F.coalesce(split * size * size >= F.col("above").cast("double") * F.col("above"), F.lit(False))
        whole = one.where((F.col("size") > small) & alike)
        edges = edges.unionByName(whole.join(whole.groupBy("bucket").agg(F.min("doc_id").alias("v")), "bucket").select(F.col("doc_id").alias("u"), "v"))
        found = edges if found is None else found.unionByName(edges)
        nodes = one.where((F.col("size") > small) & ~alike).select("doc_id", "tokens", F.col("bucket").alias("path"), F.col("size").alias("above"))
        if not nodes.limit(1).count():
            return found


def _pairs_of_blocks(threshold: float):
    """Tasks (group, a, b) as runs of rows: per member the links with the other block, and a forest of them."""

    def compare(rows: list[tuple[int, int, bytes]], a: int, b: int):
        ids = np.array([r[0] for r in rows])
        block = np.array([r[1] for r in rows])
        members = [np.frombuffer(r[2], np.uint64) for r in rows]
        size = np.array([len(s) for s in members])
        owner = np.repeat(np.arange(len(rows)), size)
        _, code = np.unique(np.concatenate(members), return_inverse=True)
        order = np.argsort(code, kind="stable")
        owner, code = owner[order], code[order]
        starts = np.flatnonzero(np.r_[True, code[1:] != code[:-1]])
        lists = np.split(owner, starts[1:])
        left = np.flatnonzero(block == a)
        right = np.flatnonzero(block == b)
        place = np.full(len(rows), -1)
        place[left] = np.arange(len(left))
        spot = np.full(len(rows), -1)
        spot[right] = np.arange(len(right))
        common = np.zeros((len(left), len(right)), np.float32)
        lists = [x for x in lists if len(x) > 1]
        for k in range(0, len(lists), 4096):  # shingles in slices, each a product of two small 0/1 matrices
            part = lists[k : k + 4096]
            rows_of, cols = np.concatenate(part), np.repeat(np.arange(len(part)), [len(x) for x in part])
            m = np.zeros((len(rows), len(part)), np.float32)
            m[rows_of, cols] = 1
            common += m[left] @ m[right].T
        link = common >= threshold * (size[left][:, None] + size[right][None, :] - common) - 1e-4
        link &= ids[left][:, None] != ids[right][None, :]
        degree = np.zeros(len(rows), np.int64)
        degree[left] += link.sum(1)
        if a != b:
            degree[right] += link.sum(0)
        root = np.arange(len(rows))
        for i in np.flatnonzero(link.any(1)):
            joined = np.unique(root[np.append(right[link[i]], left[i])])
            if len(joined) > 1:
                root[np.isin(root, joined)] = joined[0]
        for i in np.flatnonzero(degree):
            yield int(ids[i]), int(ids[root[i]]), int(degree[i])

    def run(batches):
        key, rows = None, []

        def flush():
            got = list(compare(rows, key[1], key[2])) if len(rows) > 1 else []
            return {"u": [x[0] for x in got], "v": [x[1] for x in got], "links": [x[2] for x in got]}

        for batch in batches:
            cols = [batch.column(c).to_pylist() for c in ("grp", "a", "b", "doc_id", "block", "members")]
            for g, a, b, i, block, m in zip(*cols, strict=True):
                if (g, a, b) != key:
                    if rows:
                        yield flush()
                    key, rows = (g, a, b), []
                if not rows or rows[-1][0] != i:  # a repeated row comes twice
                    rows.append((i, block, m))
        if rows:
            yield flush()

    return run


def _place() -> F.Column:
    return F.pmod(F.xxhash64("doc_id"), F.lit(MAP_BITS))


def _marked(ids: DataFrame) -> np.ndarray:
    """A map with the bits of these doc_ids set; its size is bounded, whatever their number."""
    bit = F.expr("shiftleft(1L, cast(at & 63 as int))")
    got = ids.select(_place().alias("at")).groupBy(F.shiftright("at", 6).alias("word")).agg(F.bit_or(bit).alias("bits")).toArrow()
    out = np.zeros(MAP_BITS // 64, np.uint64)
    out[got.column("word").to_numpy()] = got.column("bits").to_numpy().view(np.uint64)
    return out


def _members(docs: DataFrame, ids: DataFrame, words: int) -> DataFrame:
    """(doc_id, set_hash, members) of the rows whose doc_id is in ``ids``, and of a few others."""
    marks = docs.sparkSession.sparkContext.broadcast(_marked(ids))

    def run(batches):
        for b in batches:
            at = b.column("at").to_numpy()
            b = b.filter(pa.array((marks.value[at >> 6] >> (at & 63).astype(np.uint64)) & np.uint64(1) == 1))
            texts = strings(b, "text")
            sets = [s.tobytes() for a, z in text_slices(texts) for s in shingles(texts[a:z], words)]
            yield {"doc_id": b.column("doc_id"), "set_hash": [xxhash.xxh3_128_digest(m) for m in sets], "members": sets}

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").withColumn("at", _place())
    return map_batches(rows, run, "doc_id long, set_hash binary, members binary")


def _counter(s: np.ndarray) -> np.ndarray:
    return ((s * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(48)).astype(np.int64) % COUNTERS


def cut(held: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(node, root) of the parts of the groups in ``held`` (doc_id, grp, members) that no link leaves; lone sets drop out.

    Shingles have one order, by counters that many share and then by value. Sets at the threshold have at least this share
    of each in common, so they meet in the first shingles of each that are one more than the others may be.
    """

    def count(batches):
        total = np.zeros(COUNTERS, np.int64)
        for b in batches:
            for m in b.column("members").to_pylist():
                total += np.bincount(_counter(np.frombuffer(m, np.uint64)), minlength=COUNTERS)
        used = np.flatnonzero(total)
        yield {"counter": used, "n": total[used]}

    got = map_batches(held.select("members"), count, "counter int, n long").groupBy("counter").agg(F.sum("n").alias("n")).toArrow()
    often = np.zeros(COUNTERS, np.int64)
    often[got.column("counter").to_numpy()] = got.column("n").to_numpy()

    def rarest(batches):
        for b in batches:
            out = {"grp": [], "shingle": [], "doc_id": []}
            for g, i, m in zip(*(b.column(c).to_pylist() for c in ("grp", "doc_id", "members")), strict=True):
                s = np.frombuffer(m, np.uint64)
                first = len(s) - math.ceil(threshold * len(s) - 1e-3) + 1
                own = s[np.lexsort((s, often[_counter(s)]))[:first]].view(np.int64).tolist()
                out["shingle"] += own
                out["grp"] += [g] * len(own)
                out["doc_id"] += [i] * len(own)
            yield out

    def stars(batches):
        key = first = None
        for b in batches:
            out = {"u": [], "v": []}
            for g, s, i in zip(*(b.column(c).to_pylist() for c in ("grp", "shingle", "doc_id")), strict=True):
                if (g, s) != key:
                    key, first = (g, s), i
                elif i != first:
                    out["u"].append(i), out["v"].append(first)
            yield out

    spots = map_batches(held.select("grp", "doc_id", "members"), rarest, "grp long, shingle long, doc_id long")
    spots = spots.repartition(parts(held.sparkSession), "grp", "shingle").sortWithinPartitions("grp", "shingle", "doc_id")
    return components(map_batches(spots, stars, "u long, v long"))


def _blocked(asked: DataFrame, block_shingles: int, block_members: int) -> DataFrame:
    """``asked`` (doc_id, grp, n) with the number of blocks of its group and its own block."""
    total = asked.groupBy("grp").agg(F.greatest(F.ceil(F.sum("n") / block_shingles), F.ceil(F.count("*") / block_members)).cast("int").alias("blocks"))
    return asked.join(total, "grp").withColumn("block", F.pmod(F.xxhash64("doc_id"), F.col("blocks")).cast("int"))


def classes(docs: DataFrame, threshold: float = THRESHOLD, words: int = WORDS, recall: float = RECALL, small: int = SMALL, block_shingles: int = BLOCK_SHINGLES, block_members: int = BLOCK_MEMBERS) -> DataFrame:
    """One row a doc_id: doc_id, class_id (least doc_id of its component), n_links, n_copies.

    n_links counts the other distinct sets of at least this similarity, n_copies the other rows of the same set.
    """
    spark = docs.sparkSession
    kind = docs.schema["doc_id"].dataType.simpleString()
    found = sets(docs, words).groupBy("doc_id").agg(F.min(F.struct("set_hash", "n", "tokens")).alias("s"), F.count("*").alias("rows"))
    own = written(found.select("doc_id", "s.*", "rows"), "sets")
    own_sets = own.where("n > 0 and doc_id is not null").groupBy("set_hash")
    reps = written(own_sets.agg(F.min_by(F.struct("doc_id", "n", "tokens"), "doc_id").alias("r"), F.sum("rows").alias("copies")).select("set_hash", "r.*", "copies"), "reps")
    groups = written(components(candidates(reps.select("doc_id", "tokens"), threshold, recall, small)), "groups")
    asked = groups.join(reps, groups["node"] == reps["doc_id"]).select("doc_id", "set_hash", F.col("root").alias("grp"), "n")
    asked = written(_blocked(asked, block_shingles, block_members), "asked")
    held = written(_members(docs, asked, words).join(asked, ["doc_id", "set_hash"]).select("doc_id", "grp", "n", "blocks", "block", "members"), "held")
    kept, large = held.where("blocks = 1"), held.where("blocks > 1")
    if large.limit(1).count():
        parted = written(cut(large, threshold).withColumnsRenamed({"node": "doc_id", "root": "grp"}), "parted")
        placed = _blocked(parted.join(asked.select("doc_id", "n"), "doc_id"), block_shingles, block_members).drop("n")
        kept = kept.unionByName(large.select("doc_id", "n", "members").join(placed, "doc_id"))
    other = F.sequence(F.lit(0), F.col("blocks") - 1)
    tasks = kept.withColumn("o", F.explode(other)).select("grp", F.least("block", "o").alias("a"), F.greatest("block", "o").alias("b"), "doc_id", "block", "members")
    tasks = tasks.repartition(parts(spark), "grp", "a", "b").sortWithinPartitions("grp", "a", "b", "doc_id")
    linked = written(map_batches(tasks, _pairs_of_blocks(threshold), "u long, v long, links long"), "linked")
    forget(held)
    degree = linked.groupBy("u").agg(F.sum("links").alias("n_links"))
    roots = written(components(linked.select("u", "v")), "classes")
    by_set = reps.join(degree, reps["doc_id"] == degree["u"], "left").join(roots, reps["doc_id"] == roots["node"], "left")
    by_set = by_set.select("set_hash", F.coalesce("root", "doc_id").alias("class_id"), F.coalesce("n_links", F.lit(0)).alias("n_links"), (F.col("copies") - 1).alias("n_copies"))
    out = own.join(by_set, "set_hash", "left").select("doc_id", F.coalesce("class_id", "doc_id").alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("n_copies", F.col("rows") - 1).cast("long").alias("n_copies"))
    return out.withColumns({c: F.col(c).cast(kind) for c in ("doc_id", "class_id")})


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """The rows of one document of each class, the one with the least doc_id; rows that repeat it stay once.

    Only what has a copy or leaves its class to another document is looked up, so that the other texts stay out of shuffles.
    """
    found = classes(docs, **options).where("doc_id <> class_id or n_copies > 0")
    unsure = written(found.select(F.col("doc_id").cast("long").alias("_id"), (F.col("doc_id") == F.col("class_id")).alias("_first")), "unsure")
    rows = docs.withColumn("_id", F.col("doc_id").cast("long"))
    sole = rows.join(small_table(unsure), "_id", "left_anti")
    again = rows.join(small_table(unsure.where("_first")), "_id", "left_semi").dropDuplicates(["_id"])
    return sole.select(docs.columns).unionByName(again.select(docs.columns))
