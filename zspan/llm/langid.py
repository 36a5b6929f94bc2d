"""Language proportions of each document by expectation-maximisation over character n-grams.

Learning counts hashed character trigrams per language on a bounded sample of labelled rows. A document is then seen as
a mixture of languages: expectation-maximisation finds the proportions under which its trigrams are likeliest. Languages
join the mixture one by one, starting with the likeliest single one, as long as each addition raises the log-likelihood
by more than its penalty (half the logarithm of the number of independent trigrams).

Text that is null or has no letter is ``und`` with score 0, as is any text when nothing could be learned. Digits, marks and
white space count as one space, and so do both ends of a text, so that a single letter makes a trigram. Whole texts are read. Repeated rows get equal results; an empty table gives none.
"""

from __future__ import annotations

import sys

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from zspan.llm.common import map_batches, row_slices, strings, text_slices

#: Hash buckets of trigrams; labelled documents of each language that are learned from, about.
BUCKETS, SAMPLE = 1 << 15, 4000
_LETTERS: list[np.ndarray] = []
#: Trigrams overlap, so a third of them counts as independent.
_OVERLAP = 3


def _letters() -> np.ndarray:
    if not _LETTERS:
        _LETTERS.append(np.fromiter((chr(c).isalpha() for c in range(sys.maxunicode + 1)), bool, sys.maxunicode + 1))
    return _LETTERS[0]


def trigram_counts(texts: list[str], buckets: int = BUCKETS) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, trigram bucket, count) of all texts, ordered by text; every text with a letter has one."""
    joined = " " + " \x00 ".join(t.replace("\x00", " ") for t in texts).lower() + " \x00"
    c = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
    end = c == 0
    c = np.where(_letters()[c], c, np.uint32(32))
    text = np.cumsum(end) - end
    keep = np.r_[True, (c[1:] != 32) | (c[:-1] != 32) | end[1:] | end[:-1]]
    c, end, text = c[keep], end[keep], text[keep]
    h = (c[:-2] * np.uint32(0x9E3779B1)) ^ (c[1:-1] * np.uint32(0x85EBCA77)) ^ (c[2:] * np.uint32(0xC2B2AE3D))
    h = ((h ^ (h >> np.uint32(15))) * np.uint32(0x2C1B3C6D)) >> np.uint32(32 - buckets.bit_length() + 1)
    inside = ~(end[:-2] | end[1:-1] | end[2:]) & ~((c[:-2] == 32) & (c[1:-1] == 32)) & ~((c[1:-1] == 32) & (c[2:] == 32))
    key = text[:-2][inside].astype(np.int64) * buckets + h[inside]
    key.sort()
    first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]]) if len(key) else np.empty(0, np.int64)
    count = np.diff(np.r_[first, len(key)])
    key = key[first]
    return key // buckets, key % buckets, count


class Model:
    """Trigram probabilities of each language: ``p[bucket, language]``."""

    def __init__(self, languages: list[str], counts: np.ndarray):
        self.languages = languages
        smooth = counts + 0.2
        self.p = (smooth / smooth.sum(0)).astype(np.float64)
        self.log = np.log(self.p)

    @staticmethod
    def _fit(p: np.ndarray, n: np.ndarray, starts: np.ndarray, docs: np.ndarray, mix: np.ndarray, rounds: int) -> tuple[np.ndarray, np.ndarray]:
        """Proportions after ``rounds`` of expectation-maximisation from ``mix``, and their log-likelihoods."""
        total = np.add.reduceat(n, starts)[:, None]
        for _ in range(rounds):
            share = n / np.maximum((p * mix[docs]).sum(1), 1e-300)
            mix = mix * np.add.reduceat(p * share[:, None], starts, axis=0) / total
        return mix, np.add.reduceat(n * np.log(np.maximum((p * mix[docs]).sum(1), 1e-300)), starts)

    def mixtures(self, texts: list[str]) -> np.ndarray:
        """Language proportions of each text; zeros where it has no letter."""
        return self.explain(texts)[0]

    def explain(self, texts: list[str], rounds: int = 6, more: int = 20) -> tuple[np.ndarray, np.ndarray]:
        """Language proportions of each text and the mean log-likelihood of its trigrams under them."""
        out, mean = np.zeros((len(texts), len(self.languages))), np.full(len(texts), -np.inf)
        text, gram, n = trigram_counts(texts)
        if not len(text) or not self.languages:
            return out, mean
        starts = np.flatnonzero(np.r_[True, text[1:] != text[:-1]])
        docs = np.cumsum(np.r_[0, text[1:] != text[:-1]])
        which, n = text[starts], n.astype(np.float64)
        p = self.p[gram]
        alone = np.add.reduceat(self.log[gram] * n[:, None], starts, axis=0)
        best = alone.argmax(1)
        chosen = np.zeros_like(alone, bool)
        chosen[np.arange(len(which)), best] = True
        mix, fit = chosen.astype(float), alone.max(1)
        cost = 0.5 * np.log(np.maximum(np.add.reduceat(n, starts) / _OVERLAP, 2)) * _OVERLAP
        live = np.arange(len(which))
        everything, _ = self._fit(p, n, starts, docs, np.full_like(alone, 1 / alone.shape[1]), rounds)
        while len(live):  # the strongest language of the full mixture that is not chosen yet is the next to try
            rest = np.where(chosen[live], -1, everything[live])
            live = live[rest.max(1) > 0.02]
            if not len(live):
                break
            trial = chosen[live].copy()
            trial[np.arange(len(live)), np.where(chosen[live], -1, everything[live]).argmax(1)] = True
            rows = np.isin(docs, live)
            sub = np.searchsorted(live, docs[rows])
            s = np.flatnonzero(np.r_[True, sub[1:] != sub[:-1]])
            new, better = self._fit(p[rows], n[rows], s, sub, trial / trial.sum(1, keepdims=True), more)
            won = better - fit[live] > cost[live]
            live, new, better, trial = live[won], new[won], better[won], trial[won]
            chosen[live], mix[live], fit[live] = trial, new, better
        out[which], mean[which] = mix, fit / np.add.reduceat(n, starts)
        return out, mean


def learn(labelled: DataFrame, sample: int = SAMPLE, buckets: int = BUCKETS) -> Model:
    """Trigram statistics of (doc_id, text, lang), from about ``sample`` documents of each language by a hash of the id."""
    labelled = labelled.where("lang is not null and text is not null")
    sizes = {r["lang"]: r["n"] for r in labelled.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # one row a language
    if not sizes:
        return Model([], np.zeros((buckets, 0)))
    languages = sorted(sizes)
    share = F.create_map([F.lit(x) for k in languages for x in (k, min(1_000_000, -(-1_000_000 * sample // sizes[k])))])
    picked = labelled.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < F.element_at(share, F.col("lang")))

    def count(batches):
        seen = {}
        for b in row_slices(batches):
            texts, lang = strings(b, "text"), np.array(b.column("lang").to_pylist(), object)
            for a, z in text_slices(texts):
                text, gram, n = trigram_counts(texts[a:z], buckets)
                for k in set(lang[a:z]):
                    own = lang[a:z][text] == k
                    seen[k] = seen.get(k, 0) + np.bincount(gram[own], n[own], buckets)
        for k, c in seen.items():
            at = np.flatnonzero(c)
            yield {"lang": [k] * len(at), "gram": at, "n": c[at].astype(np.int64)}

    rows = map_batches(picked.select("text", "lang"), count, "lang string, gram int, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n")).toPandas()  # languages x buckets rows at most
    counts = np.zeros((buckets, len(languages)))
    counts[rows["gram"].to_numpy(int), [languages.index(x) for x in rows["lang"]]] = rows["n"]
    return Model(languages, counts)


def _columns(m: Model, texts: list[str]) -> tuple[list[str], list[float], list[str]]:
    preds, scores, mixed = [], [], []
    for a, z in text_slices(texts):
        for row in m.mixtures(texts[a:z]):
            top = int(row.argmax()) if len(row) else 0
            known = len(row) and row[top] > 0
            preds.append(m.languages[top] if known else "und")
            scores.append(min(1.0, float(row[top])) if known else 0.0)
            mixed.append(" ".join(f"{m.languages[i]}:{row[i]:.3f}" for i in np.argsort(-row) if row[i] > 0.0005))
    return preds, scores, mixed


def predict(spark: SparkSession, docs: DataFrame, model: Model) -> DataFrame:
    """doc_id with lang_pred, score (its proportion) and mixture, a list like ``en:0.91 fr:0.09``."""
    shared = spark.sparkContext.broadcast(model)  # languages x buckets numbers
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for b in row_slices(batches):
            preds, scores, mixed = _columns(shared.value, strings(b, "text"))
            yield {"doc_id": b.column("doc_id"), "lang_pred": preds, "score": scores, "mixture": mixed}

    return map_batches(docs.select("doc_id", "text"), run, f"doc_id {kind}, lang_pred string, score double, mixture string")


def accepted(spark: SparkSession, docs: DataFrame, model: Model) -> DataFrame:
    """The rows of ``docs`` that the learned languages explain, alone or mixed, better than even chances would.

    Texts without a letter and texts in other languages or of noise go; mixtures of learned languages stay.
    """
    shared, names = spark.sparkContext.broadcast(model), docs.columns
    flat = docs.toDF(*[f"_{k}" for k in range(len(names))])
    text, least = f"_{names.index('text')}", -float(np.log(len(model.p)))

    def run(batches):
        for b in row_slices(batches):
            texts = strings(b, text)
            fits = [x > least for a, z in text_slices(texts) for x in shared.value.explain(texts[a:z])[1]]
            b = b.filter(pa.array(fits, pa.bool_()))
            yield {f: b.column(f) for f in b.schema.names}

    return map_batches(flat, run, flat.schema).toDF(*names)
