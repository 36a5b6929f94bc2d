"""Document quality from a linear-chain conditional random field over lines.

Each line is good or bad. Its evidence is a few measures of its own bytes (shares of letters, capitals, digits and marks,
mean word length, repeated bytes and words, length) and the same measures of the lines before and after; neighbouring labels are
tied by transition weights. Weights are learned on a bounded sample of labelled documents, every line taking its
document's label. A document's score is the mean of its lines' forward-backward marginals, weighted by line length.

Null and empty texts, and texts of line ends alone, score the share of good documents in the sample (0.5 when
nothing could be learned); a line of blanks is a line. Whole texts are read. Repeated rows get equal scores.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zspan.llm.common import map_batches, strings, text_slices, written

#: Labelled documents that are learned from, about, and their characters in all; lines after which a document goes on as
#: another chain there (and there only: scores walk whole documents).
SAMPLE, SAMPLE_CHARS, CHAIN_LINES = 3000, 40_000_000, 64
_KINDS = np.zeros((256, 8), np.float32)
for _b in range(256):
    _c = chr(_b)
    _KINDS[_b] = [_b >= 128 or _c.isalpha(), _b < 128 and _c.isupper(), _b < 128 and _c.isdigit(), _c in ".,;:'-", _c in "!?", _b < 128 and not _c.isalnum() and _c not in ".,;:'-!? \t\r\n", _c in " \t\r", _c in "|<>{}[]=\\/_#*%$&@~^"]
_N = _KINDS.shape[1]
_OWN = _N + 7
FEATURES = 3 * _OWN + 1
_SALT = np.random.default_rng(5).integers(1, 1 << 40, 256)


def lines_of(texts: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text number, length in bytes, own measures) of every line with content."""
    blob = "\n".join(t.replace("\n\n", "\n") if "\n\n" in t else t for t in texts) + "\n"
    counts = [t.replace("\n\n", "\n").count("\n") + 1 for t in texts]
    data = np.frombuffer(blob.encode("utf-8", "surrogatepass"), np.uint8)
    ends = np.flatnonzero(data == 10)
    starts = np.r_[0, ends[:-1] + 1]
    text = np.repeat(np.arange(len(texts)), counts)
    length = ends - starts
    keep = length > 0
    starts, length, text = starts[keep], length[keep], text[keep]
    if not len(starts):
        return text, length, np.zeros((0, _OWN), np.float32)
    tables = np.add.reduceat
    cut = np.stack([starts, starts + length], 1).ravel()
    flat = np.append(data, 10)

    def total(x: np.ndarray) -> np.ndarray:
        return tables(np.append(x, 0).astype(np.int64), cut)[::2]

    sums = np.stack([total(_KINDS[:, k][flat]) for k in range(_N)], 1).astype(np.float32)
    same = np.r_[False, data[1:] == data[:-1]]
    letter = _KINDS[:, 0][data] > 0
    begins = np.r_[letter[0], letter[1:] & ~letter[:-1]]
    words = total(np.append(begins, False))
    again = np.zeros(len(data), bool)  # words that the word before them in the line equals
    at = np.flatnonzero(begins)
    if len(at) > 1:
        sums_of = np.add.reduceat(np.where(letter, _SALT[data], 0), at)
        line = np.searchsorted(ends, at)
        again[at[1:]] = (sums_of[1:] == sums_of[:-1]) & (line[1:] == line[:-1])
    jumps = total(np.append(np.r_[letter[0], (letter[1:] != letter[:-1])], False))
    vowel = np.isin(data | 32, np.frombuffer(b"aeiou", np.uint8))
    n = length.astype(np.float32)
    more = np.stack([total(np.append(same, False)) / n, np.minimum(sums[:, 0] / np.maximum(words, 1), 30) / 10, jumps / n, total(np.append(vowel, False)) / np.maximum(sums[:, 0], 1), np.log1p(length) / 5, (data[starts + length - 1] == 46).astype(np.float32), total(np.append(again, False)) / np.maximum(words, 1)], 1)
    return text, length, np.concatenate([sums / n[:, None], more], 1).astype(np.float32)


def features(text: np.ndarray, own: np.ndarray) -> np.ndarray:
    """Own measures of a line, those of its neighbours in the text (zeros at the ends), and a constant."""
    before, after = np.zeros_like(own), np.zeros_like(own)
    if len(own) > 1:
        same = (text[1:] == text[:-1])[:, None]
        before[1:], after[:-1] = own[:-1] * same, own[1:] * same
    return np.concatenate([own, before, after, np.ones((len(own), 1), np.float32)], 1)


class Chain:
    """Weights ``w`` of the good label against the bad, and of the four transitions."""

    def __init__(self, w: np.ndarray, move: np.ndarray, prior: float):
        self.w, self.move, self.prior = w, move, prior

    def marginals(self, score: np.ndarray, text: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """P(good) of each line, the expected transitions and, by text, the log of all labellings' weights.

        All texts step through their lines together; at step k those with more than k lines are left.
        """
        starts = np.flatnonzero(np.r_[True, text[1:] != text[:-1]])
        n = np.diff(np.r_[starts, len(text)])
        order = np.argsort(-n, kind="stable")
        starts, n = starts[order], n[order]
        alive = np.searchsorted(-n, -np.arange(n[0] + 1), side="left")  # texts with more than k lines
        emit = np.stack([np.zeros_like(score), score], 1)
        ahead, back = np.zeros((len(score), 2)), np.zeros((len(score), 2))
        ahead[starts] = emit[starts]
        for k in range(1, n[0]):
            at = starts[: alive[k]] + k
            ahead[at] = np.logaddexp(ahead[at - 1, :1] + self.move[0], ahead[at - 1, 1:] + self.move[1]) + emit[at]
        for k in range(n[0] - 2, -1, -1):
            at = starts[: alive[k + 1]] + k
            x = back[at + 1] + emit[at + 1]
            back[at] = np.logaddexp(x[:, :1] + self.move[:, 0], x[:, 1:] + self.move[:, 1])
        both = ahead + back
        z = np.logaddexp(both[:, 0], both[:, 1])
        good = np.exp(both[:, 1] - z)
        inner = np.flatnonzero(np.r_[False, text[1:] == text[:-1]])
        pair = np.exp(ahead[inner - 1][:, :, None] + self.move + (back[inner] + emit[inner])[:, None, :] - z[inner][:, None, None])
        return good, pair.sum(0), z

    def scores(self, texts: list[str]) -> np.ndarray:
        out = np.full(len(texts), self.prior)
        text, length, own = lines_of(texts)
        if len(text):
            good, _, _ = self.marginals(features(text, own) @ self.w, text)
            weight = np.bincount(text, length, len(texts))
            some = weight > 0
            out[some] = np.bincount(text, length * good, len(texts))[some] / weight[some]
        return np.clip(np.round(out, 12), 0.0, 1.0)


def fit(texts: list[str], labels: np.ndarray, rounds: int = 100, rate: float = 0.1, decay: float = 1e-4) -> Chain:
    """Weights of highest penalised likelihood, by full-batch gradient steps with momentum and scaling."""
    if not len(texts) or not (0 < labels.mean() < 1):
        return Chain(np.zeros(FEATURES), np.zeros((2, 2)), float(labels.mean()) if len(texts) else 0.5)
    text, _, own = lines_of(texts)
    if not len(text):
        return Chain(np.zeros(FEATURES), np.zeros((2, 2)), float(labels.mean()))
    x, y = features(text, own).astype(np.float64), labels[text].astype(np.float64)
    first = np.flatnonzero(np.r_[True, text[1:] != text[:-1]])
    nth = np.arange(len(text)) - np.repeat(first, np.diff(np.r_[first, len(text)]))
    text = np.cumsum(nth % CHAIN_LINES == 0)
    scale = np.maximum(np.sqrt((x**2).mean(0)), 1e-3)
    x = x / scale
    inner = np.flatnonzero(np.r_[False, text[1:] == text[:-1]])
    seen = np.zeros((2, 2))
    np.add.at(seen, (y[inner - 1].astype(int), y[inner].astype(int)), 1)
    theta = np.zeros(FEATURES + 4)
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    for step in range(1, rounds + 1):
        chain = Chain(theta[:FEATURES], theta[FEATURES:].reshape(2, 2), 0.5)
        good, moves, _ = chain.marginals(x @ chain.w, text)
        grad = np.r_[x.T @ (y - good), (seen - moves).ravel()] / len(y) - decay * theta
        m, v = 0.9 * m + 0.1 * grad, 0.99 * v + 0.01 * grad**2
        theta += rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return Chain(theta[:FEATURES] / scale, theta[FEATURES:].reshape(2, 2), float(labels.mean()))


def learn(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, chars: int = SAMPLE_CHARS) -> Chain:
    """A chain from docs (doc_id, text) and labels (doc_id, quality); about ``sample`` documents of ``chars`` characters.

    A hash of the id picks them, and fewer of them where they are long; a text of more than ``chars`` is not learned from. Labels other than 0 and 1 are no labels; of several for one id the least counts.
    """
    labels = labels.where("quality in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.min("quality").cast("int").alias("quality"))
    sizes = {r["quality"]: r["n"] for r in labels.groupBy("quality").agg(F.count("*").alias("n")).collect()}  # two rows
    if not sizes:
        return Chain(np.zeros(FEATURES), np.zeros((2, 2)), 0.5)
    place, most = F.pmod(F.xxhash64(F.col("doc_id").cast("long")), F.lit(1_000_000)), min(1_000_000, -(-1_000_000 * sample // sum(sizes.values())))
    texts = docs.select("doc_id", "text").where((place < most) & (F.length("text") <= chars)).dropDuplicates(["doc_id"])
    picked = written(texts.join(labels.where(place < most), "doc_id"), "labelled")
    size = picked.agg(F.sum(F.length("text"))).first()[0] or 0
    rows = picked.where(place < most * min(1.0, chars / max(size, 1))).select("text", "quality").toPandas()  # the bounded sample
    return fit(rows["text"].tolist(), rows["quality"].to_numpy(int))


def score(spark: SparkSession, docs: DataFrame, chain: Chain) -> DataFrame:
    """doc_id and score of each whole text."""
    shared = spark.sparkContext.broadcast(chain)  # a few hundred numbers
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for b in batches:
            texts = strings(b, "text")
            found = [shared.value.scores(texts[a:z]) for a, z in text_slices(texts)]
            yield {"doc_id": b.column("doc_id"), "score": np.concatenate(found) if found else []}

    return map_batches(docs.select("doc_id", "text"), run, f"doc_id {kind}, score double")
