"""Toxicity by class-conditional Kneser-Ney bigram models.

One model for toxic and one for ordinary texts, each with absolute discount
and continuation counts.  Rare counts go whole to the lower order, and the lowest
is the continuation counts that both classes share, so a rare expression says
nothing while one that is frequent in a single class says much.  The
score is a logistic of the length-normalised log-likelihood difference and of how
much of it comes from strong words, fitted on labelled texts that the models have not seen.

Fitting takes a bounded sample: at most ``per_class`` labelled texts of a class
and ``max_bytes`` bytes of whole texts a class, in hash order; a text that no longer
fits is passed over.  Ordinary texts are not cut down to the number of toxic ones: the
more of them, the better the ordinary words of smaller languages are known.  Scoring covers all
rows and whole texts.  Null and empty texts score the logistic's value at no
evidence, at most 0.5.  Without labels of both classes every score is 0.  Very long
texts are scored whole; rows with null or repeated ids row by row; an empty table
gives none.  Other columns stay as they are and are never inputs.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import _WORDS, as_bytes, fold, fresh, lean, ship

STRONG = 4.0
_START = np.uint64(1)


_TOKEN = re.compile(rb"[a-z0-9\x80-\xff]+")


def tokens(text: bytes | None) -> np.ndarray:
    """Hashes of the runs of letters and digits, A-Z lower-cased; marks about a word don't hide it."""
    return _WORDS.of(_TOKEN.findall(text.lower())) if text else np.empty(0, np.uint64)


@dataclass
class Bigrams:
    """Sorted tables from which the difference toxic - ordinary of each word's log probability follows."""

    words: np.ndarray  # vocabulary, by hash
    pairs: np.ndarray  # keys of seen bigrams
    pair_diff: np.ndarray
    left_diff: np.ndarray  # difference of log backoff weights, by left word; last: unknown
    word_diff: np.ndarray  # difference of log lower-order probabilities, by word; last: unknown
    weights: tuple[float, ...]

    def ids(self, h: np.ndarray) -> np.ndarray:
        i = np.minimum(np.searchsorted(self.words, h), len(self.words) - 1)
        return np.where(self.words[i] == h, i, len(self.words))

    def features(self, text: bytes | None) -> tuple[float, float, float]:
        """Mean log-likelihood difference a word; and of what words say beyond ``STRONG``, by the root of the length and in all.

        A text's language and subject move all its words a little one way; toxic
        expressions are the few words that are far off, so they get features of their own.
        These look at continuation counts alone: copied passages bring many words, but
        each in one context.
        """
        h = tokens(text)
        if not len(h):
            return 0.0, 0.0, 0.0
        w = self.ids(h)
        v = np.r_[self.ids(np.array([_START])), w[:-1]]
        key = v.astype(np.int64) * (len(self.words) + 1) + w
        i = np.minimum(np.searchsorted(self.pairs, key), len(self.pairs) - 1)
        diff = np.where(self.pairs[i] == key, self.pair_diff[i], self.left_diff[v] + self.word_diff[w])
        strong = float(np.maximum(self.word_diff[w] - STRONG, 0).sum())
        return float(diff.mean()), strong / np.sqrt(len(h)), np.log1p(strong)

    def score(self, text: bytes | None) -> float:
        *weights, z = self.weights
        z += sum(a * x for a, x in zip(weights, self.features(text), strict=True))
        if not text or not text.strip():
            z = min(z, 0.0)
        return float(1 / (1 + np.exp(-np.clip(z, -50, 50))))


RARE = 2  # counts up to this one go to the lower order whole


def discounts(counts: np.ndarray) -> np.ndarray:
    """Rare counts whole, else the absolute discount that counts of 1 to 4 suggest (Kneser-Ney with cut-off)."""
    n = [max(int((counts == i).sum()), 1) for i in range(1, 5)]
    y = n[0] / (n[0] + 2 * n[1])
    return np.where(counts <= RARE, counts, min(max(3 - 4 * y * n[3] / n[2], 0.5), 2.5))


def _fit(ordinary: list[bytes], toxic: list[bytes]) -> Bigrams:
    seq = [[np.r_[_START, h] for t in texts if len(h := tokens(t))] for texts in (ordinary, toxic)]
    words = np.unique(np.concatenate([_START[None], *(x for s in seq for x in s)]))
    n = len(words)
    sides = []
    for s in seq:
        left = np.concatenate([x[:-1] for x in s] or [words[:0]])
        right = np.concatenate([x[1:] for x in s] or [words[:0]])
        sides.append(np.unique(np.searchsorted(words, left).astype(np.int64) * (n + 1) + np.searchsorted(words, right), return_counts=True))
    shared = np.unique(np.concatenate([k for k, _ in sides]))

    def lower(cont: np.ndarray, back) -> np.ndarray:
        total, off = max(cont.sum(), 1.0), discounts(cont)
        return (cont - off) / total + (off.sum() / total if cont.any() else 1.0) * back

    conts = [np.bincount(key % (n + 1), minlength=n + 1).astype(float) for key, _ in sides]
    base = lower(np.minimum(*conts), 1 / (n + 1))  # what both classes share
    log_lam, log_uni, pair = [], [], []
    for (key, c), cont in zip(sides, conts, strict=True):
        v = key // (n + 1)
        off = discounts(c)
        total = np.bincount(v, c, n + 1)
        lam = np.where(total > 0, np.bincount(v, off, n + 1) / np.maximum(total, 1), 1.0)
        uni = lower(cont, base)
        own = np.zeros(len(shared))
        own[np.searchsorted(shared, key)] = (c - off) / total[v]
        pair.append(np.log(own + lam[shared // (n + 1)] * uni[shared % (n + 1)]))
        log_lam.append(np.log(lam))
        log_uni.append(np.log(uni))
    return Bigrams(words, shared, pair[1] - pair[0], log_lam[1] - log_lam[0], log_uni[1] - log_uni[0], (0.0,) * 4)


def _logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1e-2, rounds: int = 50) -> np.ndarray:
    """Newton steps on scaled features."""
    scale = np.abs(x).mean(0) + 1e-9
    z = np.c_[x / scale, np.ones(len(x))]
    w = np.zeros(z.shape[1])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        h = (z * (p * (1 - p) + 1e-9)[:, None]).T @ z + ridge * np.eye(len(w))
        w += np.clip(np.linalg.solve(h, z.T @ (y - p) - ridge * w), -5, 5)
    return np.r_[w[:-1] / scale, w[-1]]


def train(docs: DataFrame, labels: DataFrame, per_class: int = 2000, max_bytes: int = 6_000_000) -> Bigrams | None:
    """Fit on at most ``per_class`` labelled texts a class; a third of them, by hash, only for the logistic."""
    chosen, found = [], []
    known = labels.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    for c in (0, 1):
        ids = known.where(F.col("toxic") == c).orderBy(F.xxhash64(F.lit(5), "doc_id"), "doc_id").limit(per_class).select("doc_id")
        sizes = docs.join(F.broadcast(ids), "doc_id").groupBy("doc_id").agg(F.max(F.octet_length("text")).alias("size")).orderBy(F.xxhash64(F.lit(5), "doc_id"), "doc_id").collect()
        found.append([(doc, size or 0) for doc, size in sizes])  # at most per_class rows
    for c, sizes in enumerate(found):
        room = max_bytes
        for doc, size in sizes:
            if size <= room:
                chosen.append((doc, c))
                room -= size
    if len({c for _, c in chosen}) < 2:
        return None
    spark = docs.sparkSession
    picked = spark.createDataFrame(chosen, "doc_id long, c int")
    rows = docs.join(F.broadcast(picked), "doc_id").groupBy("doc_id", "c").agg(F.max("text").alias("text")).orderBy("doc_id").select(F.expr("pmod(xxhash64(17, doc_id), 3) = 0"), "c", "text").collect()
    part = lambda held, c: [(t or "").encode() for h, k, t in rows if h == held and k == c]
    model = _fit(part(False, 0), part(False, 1))
    cal = [(model.features(t), c) for c in (0, 1) for t in part(True, c)]
    if len({c for _, c in cal}) == 2:
        model.weights = tuple(_logistic(np.array([f for f, _ in cal]), np.array([float(c) for _, c in cal])))
    else:
        model.weights = (4.0, 1.0, 0.0, -1.0)
    return model


def _scores(model, names: list[str], text_at: int):
    def run(batches):
        m = model.value if model is not None else None
        for b in batches:
            score = [m.score(t) if m else 0.0 for t in as_bytes(b.column(text_at))]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(score, pa.float64())], names=names)

    return lean(run)


def score(docs: DataFrame, model: Bigrams | None, text_col: str = "text", name: str = "score") -> DataFrame:
    """``docs`` with one more column ``name``, which replaces one of that name."""
    spark = docs.sparkSession
    ship(spark)
    docs = docs.drop(name)
    sent = spark.sparkContext.broadcast(model) if model is not None else None
    out = docs.withColumn(name, F.lit(0.0)).schema
    return docs.mapInArrow(_scores(sent, out.names, docs.columns.index(text_col)), out)


def toxicity(docs: DataFrame, labels: DataFrame, mod: int = 3, rest: int = 1, cut: float = 0.7) -> DataFrame:
    """docs(doc_id, text) -> doc_id, held_out, score, predicted; learns where crc32 of the id modulo ``mod`` is not ``rest``."""
    held = fold("doc_id", mod) == rest
    docs = docs.select("doc_id", "text")
    model = train(docs.where(~held).where("doc_id IS NOT NULL"), labels.where(fold("doc_id", mod) != rest))
    out = score(docs, model)
    return out.select("doc_id", held.alias("held_out"), "score", F.when(F.col("score") >= cut, 1).otherwise(0).alias("predicted"))


def keep_clean(docs: DataFrame, labels: DataFrame, cut: float = 0.7) -> DataFrame:
    """Rows of ``docs`` whose score stays below ``cut``, columns as they were; learns from all labels."""
    model = train(docs.where("doc_id IS NOT NULL").select("doc_id", "text"), labels)
    mark = fresh(docs, "__score")
    return score(docs, model, name=mark).where(F.col(mark) < cut).drop(mark)
