"""Secrets in texts: wide candidate patterns, then a random forest that throws out false positives.

A candidate is a long run of key characters with a digit or a known prefix, or what is assigned to a name like password.
The forest sees its length, shares and changes of character classes, how its letter pairs and dictionary words resemble
prose, path marks, and the words beside it. It is trained from labelled findings (before, value, after, label): a given
table, or generated ones after public formats of credentials and of things that look like them.

Null and empty texts have no findings. Spans are code points of the whole text. Repeated rows repeat their findings.
"""

from __future__ import annotations

import hashlib
import json
import math
import random
import re
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from zspan.llm.common import map_batches, strings

TREES, DEPTH, LEAF, GENERATED, NEAR = 20, 8, 4, 3000, 40
# Names that hold secrets, words beside things that are none, public credential prefixes.
SECRET_WORDS = ("password", "passwd", "pwd", "secret", "token", "apikey", "api_key", "key", "auth", "bearer", "credential", "private")
PLAIN_WORDS = ("commit", "sha", "sha1", "sha256", "md5", "checksum", "digest", "uuid", "guid", "revision", "version", "build", "id", "isbn", "phone", "card", "order", "file", "path", "image", "url", "http", "https", "www", "example", "etag", "hash")
PREFIXES = ("AKIA", "ASIA", "ghp_", "gho_", "sk-", "sk_live_", "xoxb-", "AIza", "eyJ", "glpat-")
_RUN = re.compile(r"(?<![A-Za-z0-9+/_\-])(?=[A-Za-z+/_\-]*[0-9]|AKIA|ASIA)[A-Za-z0-9+/_\-]{12,}={0,2}")
_NAMED = re.compile(r"(?i)\b(?:password|passwd|pwd|secret|token|api[_-]?key|auth)[\"']?\s{0,3}[:=]\s{0,3}[\"']?([^\s\"',;<>]{6,})")
_UUID = re.compile(r"(?i)^[0-9a-f]{8}(-[0-9a-f]{4}){3}-[0-9a-f]{12}$")
_WORDS: dict[str, frozenset[str]] = {}


def dictionary(path: str) -> frozenset[str]:
    """Lower-case words of four letters or more among a tokenizer file's tokens."""
    if path not in _WORDS:
        with open(path, encoding="utf-8") as f:
            tokens = json.load(f)["model"]["vocab"]
        _WORDS[path] = frozenset(w for w in (t.lstrip("Ġ").lower() for t in tokens) if len(w) >= 4 and w.isascii() and w.isalpha())
    return _WORDS[path]


def candidates_in(text: str) -> list[tuple[int, int, list[tuple[int, int]]]]:
    """(start, end, members) in order; candidates that overlap are one, so that no part of a value is left or cut twice."""
    out: list[tuple[int, int, list[tuple[int, int]]]] = []
    for a, b in sorted({*(m.span() for m in _RUN.finditer(text)), *(m.span(1) for m in _NAMED.finditer(text))}):
        if out and a < out[-1][1]:
            out[-1] = out[-1][0], max(b, out[-1][1]), [*out[-1][2], (a, b)]
        else:
            out.append((a, b, [(a, b)]))
    return out


def measures(before: str, value: str, after: str, words: frozenset[str]) -> list[float]:
    """What the forest sees of a finding."""
    n = max(len(value), 1)
    kinds = ["d" if c.isdigit() else "u" if c.isupper() else "l" if c.islower() else "s" for c in value]
    low, covered, i = value.lower(), 0, 0
    while i < n - 3:
        size = next((k for k in range(min(12, n - i), 3, -1) if low[i : i + k] in words), 0)
        covered, i = covered + size, i + max(size, 1)
    letters = [low[k : k + 2] for k in range(n - 1) if low[k].isalpha() and low[k + 1].isalpha()]
    vowel = sum((a in "aeiou") != (b in "aeiou") for a, b in letters) / max(len(letters), 1)
    beside = re.findall(r"[a-z][a-z0-9_]*", before.lower())[-3:]
    behind = re.findall(r"[a-z][a-z0-9_]*", after.lower())[:1]
    return [
        n,
        kinds.count("d") / n,
        kinds.count("u") / n,
        kinds.count("l") / n,
        sum(a != b for a, b in zip(kinds, kinds[1:], strict=False)) / max(n - 1, 1),
        float(all(c in "0123456789abcdef" for c in low)),
        -sum(k / n * math.log2(k / n) for k in Counter(value).values()),
        covered / n,
        vowel,
        value.count("/") + value.count("\\"),
        value.count("-") + value.count("_"),
        float("." in value[-5:]),
        float(value.isdigit()),
        float(bool(_UUID.match(value))),
        float(value.startswith(PREFIXES)),
        float(before.rstrip(" \"'")[-1:] in ("=", ":")),
        float(any(w in SECRET_WORDS or w.endswith(("key", "token", "password", "secret")) for w in beside)),
        float(any(w in PLAIN_WORDS for w in beside[-2:] + behind)),
        len(set(value)) / n,
    ]


def generated_findings(n: int = GENERATED, seed: int = 11) -> list[tuple[str, str, str, int]]:
    """Labelled findings after public formats: half credentials, half hashes, ids, paths, numbers, words, placeholders."""
    r = random.Random(seed)
    hexes, caps, mixed = "0123456789abcdef", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567890", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"
    syllables = ["ing", "tion", "the", "and", "er", "ou", "la", "re", "ment", "que", "sch", "ein", "lich", "con", "data", "user", "file"]
    run = lambda abc, k: "".join(r.choice(abc) for _ in range(k))
    word = lambda k=3: "".join(r.choice(syllables) for _ in range(r.randint(1, k)))
    prose = lambda: " ".join(word() for _ in range(4))
    out = []
    for i in range(n):
        if i % 2:
            kind = r.randrange(6)
            name = r.choice(["password", "token", "secret", "api_key", "API_KEY", "passwd", "auth_token", "secret_key", "pwd"])
            value = [f"AKIA{run(caps, 16)}", run(hexes, r.choice([16, 18, 20, 24, 32, 40, 64])), "ghp_" + run(mixed, 36), run(mixed + "+/", 40), "sk-" + run(mixed, 48), word() + run("0123456789!#", 4) + run(mixed, 6)][kind]
            named = f"{prose()} {name}{r.choice(['=', ': ', ' = ', ' = ' + chr(34), '=' + chr(34)])}"
            before = named if kind in (1, 3, 5) or r.random() < 0.4 else prose() + " "
            out.append((before, value, r.choice(["", " ", '" ']) + prose(), 1))
        else:
            kind = r.randrange(9)
            named = r.choice(PLAIN_WORDS)
            value = [
                run(hexes, r.choice([32, 40, 64])), f"{run(hexes, 8)}-{run(hexes, 4)}-{run(hexes, 4)}-{run(hexes, 4)}-{run(hexes, 12)}", "/".join(word() for _ in range(4)) + f"/{r.randint(1, 99)}", run("0123456789", r.randint(12, 18)),
                word(6) + str(r.randint(1, 2030)), f"{word()}-{word()}-{r.randint(1, 12)}-{word()}", r.choice(["your_api_key_here", "xxxxxxxxxxxx", "changeme123456", "YOUR-TOKEN-123", "example12345678"]), f"{r.randint(1990, 2030)}-{r.randint(10, 12)}-{r.randint(10, 28)}T{run('0123456789', 6)}", f"{r.randint(100, 999)}-{r.randint(100, 999)}-{r.randint(1000, 9999)}",
            ][kind]
            before = f"{prose()} {named} " if kind in (0, 1) or r.random() < 0.5 else prose() + " "
            if kind == 6:
                before = f"{prose()} {r.choice(['token', 'password', 'api_key'])}="
            out.append((before, value, " " + prose(), 0))
    return out


class Forest:
    """Trees as arrays: feature (-1 at a leaf), threshold, left and right child, share of secrets."""

    def __init__(self, trees: list[list[np.ndarray]]):
        self.trees = trees

    @classmethod
    def fit(cls, x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, seed: int = 3) -> Forest:
        rng, out = np.random.default_rng(seed), []
        for _ in range(trees):
            nodes: list[list[float]] = []

            def grow(rows: np.ndarray, level: int, nodes=nodes) -> int:
                me, share = len(nodes), float(y[rows].mean())
                nodes.append([-1, 0.0, 0, 0, share])
                if level == depth or len(rows) < 2 * LEAF or share in (0.0, 1.0):
                    return me
                best = None
                for f in rng.choice(x.shape[1], max(1, int(x.shape[1] ** 0.5) + 1), replace=False):
                    order = np.argsort(x[rows, f], kind="stable")
                    v, up = x[rows, f][order], np.cumsum(y[rows][order])
                    cut = np.flatnonzero(v[1:] > v[:-1]) + 1
                    cut = cut[(cut >= LEAF) & (cut <= len(rows) - LEAF)]
                    if not len(cut):
                        continue
                    a, b = up[cut - 1], up[-1] - up[cut - 1]
                    impurity = a * (1 - a / cut) + b * (1 - b / (len(rows) - cut))
                    k = int(impurity.argmin())
                    if best is None or impurity[k] < best[0]:
                        best = impurity[k], int(f), float(v[cut[k] - 1] + v[cut[k]]) / 2
                if best is not None:
                    left = x[rows, best[1]] <= best[2]
                    a, b = grow(rows[left], level + 1), grow(rows[~left], level + 1)
                    nodes[me][:4] = [best[1], best[2], a, b]
                return me

            grow(rng.integers(0, len(y), len(y)), 0)
            out.append([np.array(c) for c in zip(*nodes, strict=True)])
        return cls(out)

    def predict(self, x: np.ndarray) -> np.ndarray:
        total = np.zeros(len(x))
        for feature, threshold, left, right, share in self.trees:
            at = np.zeros(len(x), int)
            while (inner := feature[at] >= 0).any():
                i = np.flatnonzero(inner)
                f = feature[at[i]].astype(int)
                at[i] = np.where(x[i, f] <= threshold[at[i]], left[at[i]], right[at[i]]).astype(int)
            total += share[at]
        return total / max(len(self.trees), 1)


def train(vocabulary: str, findings: list[tuple[str, str, str, int]] | None = None) -> Forest:
    """A forest from labelled findings (a bounded list), by default the generated ones."""
    rows, words = findings or generated_findings(), dictionary(vocabulary)
    return Forest.fit(np.array([measures(b, v, a, words) for b, v, a, _ in rows]), np.array([x[3] for x in rows], float))


def scan(texts: list[str], forest: Forest, words: frozenset[str]) -> list[list[tuple[int, int, float]]]:
    """(start, end, score) of every candidate of each text; overlapping ones score as the best of them and their union."""
    spans = [[(a, b, sorted({(a, b), *members})) for a, b, members in candidates_in(t)] for t in texts]
    x = [measures(t[max(0, a - NEAR) : a], t[a:b], t[b : b + NEAR], words) for t, found in zip(texts, spans, strict=True) for _, _, members in found for a, b in members]
    score = iter(forest.predict(np.array(x)).tolist() if x else [])
    return [[(a, b, max([next(score) for _ in members])) for a, b, members in found] for found in spans]


def findings(docs: DataFrame, forest: Forest, vocabulary: str, bar: float = 0.5) -> DataFrame:
    """Every candidate: doc_id, start, end, value_sha256, score, is_secret."""
    shared = docs.sparkSession.sparkContext.broadcast(forest)  # trees of a bounded depth
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        words = dictionary(vocabulary)
        for b in batches:
            texts = strings(b, "text")
            rows = [(i, s, e, hashlib.sha256(t[s:e].encode()).hexdigest(), p, p >= bar) for i, t, found in zip(b.column("doc_id").to_pylist(), texts, scan(texts, shared.value, words), strict=True) for s, e, p in found]
            if rows:
                yield dict(zip(("doc_id", "start", "end", "value_sha256", "score", "is_secret"), zip(*rows, strict=True), strict=True))

    return map_batches(docs.select("doc_id", "text"), run, f"doc_id {kind}, start long, end long, value_sha256 string, score double, is_secret boolean")


def masked(text: str | None, spans: list[tuple[int, int]], mark: str) -> str | None:
    """The text with each of the ordered, disjoint spans replaced, in one pass."""
    if not spans:
        return text
    ends = [0, *(e for _, e in spans)]
    return mark.join(text[a:b] for a, b in zip(ends, [*(s for s, _ in spans), len(text)], strict=True))


def redact(docs: DataFrame, forest: Forest, vocabulary: str, bar: float = 0.5, mark: str = "[secret]") -> DataFrame:
    """The rows with each secret replaced by ``mark``; n_chars, if there, follows the text."""
    shared = docs.sparkSession.sparkContext.broadcast(forest)
    names = docs.columns
    flat = docs.toDF(*[f"_{k}" for k in range(len(names))])
    text, chars = f"_{names.index('text')}", f"_{names.index('n_chars')}" if "n_chars" in names else None
    long = chars and isinstance(docs.schema["n_chars"].dataType, (T.LongType, T.IntegerType))

    def run(batches):
        words = dictionary(vocabulary)
        for b in batches:
            out = []
            for t, found in zip(b.column(text).to_pylist(), scan(strings(b, text), shared.value, words), strict=True):
                out.append(masked(t, [(s, e) for s, e, p in found if p >= bar], mark))
            cols = {f: b.column(f) for f in b.schema.names} | {text: out}
            if long:
                cols[chars] = [n if new == old else len(new) for n, new, old in zip(b.column(chars).to_pylist(), out, b.column(text).to_pylist(), strict=True)]
            yield cols

    return map_batches(flat, run, flat.schema).toDF(*names)
