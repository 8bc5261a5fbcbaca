"""Quality rules and line labelling by a linear-chain conditional random field.

Each line gets binary features of its shape; Viterbi decoding of the field marks
it content or boilerplate; a text stays if content lines hold a large enough
share of its letters and the base rules do not fail it.  The field is trained by
gradient ascent on the conditional likelihood of a bounded sample of labelled
texts: ``n_train`` in hash order, and whole texts up to ``max_bytes`` bytes; one
that no longer fits is passed over.  Only texts carry labels, so the lines' are
latent: lines of texts with quality 1 are content, those of texts with quality 0
start as boilerplate and are decoded anew by each field fitted, the likeliest
boilerplate line of such a text staying one.

Null text has no word and no line with a word: it fails the base rules.  Null
and repeated ids are judged row by row; very long texts go whole; an empty table
gives none; other columns are not read.  Without labels a fixed prior field is used.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, plain, runs, window_hashes

SYMBOLS = "#*$%&|<>"
_SYMBOL = re.compile("[#*$%&|<>]")
_SPLIT = re.compile(r"[^\x20\x09-\x0D]+")
FEATURES = ("bias", "many symbols", "few letters", "all capitals", "shouting", "repeated line", "one word over and over", "short without stop", "link or code")
#: Weight of each feature for boilerplate before training.
PRIOR = (-3.0, 5.0, 4.0, 3.0, 3.0, 3.0, 4.0, 0.5, 2.0)


def base_measures(text: str | None) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    if not text:
        return 0, 0, 0, 0, 0
    words = _SPLIT.findall(text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        if _SPLIT.search(line):
            dup += line in seen
            seen.add(line)
    repeat = 0
    if len(words) >= 5:
        h = window_hashes(_exact(words), 5)
        order = np.argsort(h, kind="stable")
        _, size = runs(h[order])
        again = np.empty(len(h), bool)
        again[order] = np.repeat(size > 1, size)
        edge = np.zeros(len(words) + 1, np.int64)
        np.add.at(edge, np.flatnonzero(again), 1)
        np.add.at(edge, np.flatnonzero(again) + 5, -1)
        repeat = int((np.cumsum(edge[:-1]) > 0).sum())
    return len(words), sum(map(len, words)), len(_SYMBOL.findall(text)), dup, repeat


def _exact(words: list[str]) -> np.ndarray:
    """Hashes of words as they are, case kept."""
    from .common import _WORDS

    return _WORDS.of([w.encode("utf-8", "surrogatepass") for w in words])


def line_features(text: str) -> tuple[np.ndarray, np.ndarray]:
    """A row of 0/1 features for each line with a word, and the line's letters."""
    rows, letters, seen = [], [], set()
    for line in text.split("\n"):
        words = _SPLIT.findall(line)
        if not words:
            continue
        chars = sum(map(len, words))
        symbols = len(_SYMBOL.findall(line))
        alpha = sum(map(str.isalpha, line))
        cased = line.upper() != line.lower()
        rows.append((
            1,
            symbols * 10 > chars,
            alpha * 2 < chars,
            cased and len(words) > 2 and line == line.upper(),
            line.count("!!") * 4 > len(words),
            line in seen,
            len(words) > 5 and len(set(words)) * 4 < len(words),
            len(words) < 3 and line.rstrip()[-1:] not in ".!?:",
            "://" in line or "{" in line or "</" in line,
        ))
        letters.append(max(alpha, 1))
        seen.add(line)
    return np.array(rows, float).reshape(-1, len(FEATURES)), np.array(letters, float)


class LineField:
    """Two labels, 0 content and 1 boilerplate: feature weights for label 1 and a 2 x 2 transition."""

    def __init__(self, weights=PRIOR, moves=((0.5, -0.5), (-0.5, 0.5))):
        self.w, self.t = np.array(weights, float), np.array(moves, float)

    def decode(self, x: np.ndarray) -> np.ndarray:
        """Viterbi: the best label of each line."""
        score = (x @ self.w).tolist()
        (t00, t01), (t10, t11) = self.t.tolist()
        a, b, back = 0.0, score[0] if score else 0.0, []
        for s in score[1:]:
            p, q = a + t00 >= b + t10, a + t01 >= b + t11
            back.append((0 if p else 1, 0 if q else 1))
            a, b = (a + t00 if p else b + t10), (a + t01 if q else b + t11) + s
        out = [int(b > a)] if score else []
        for p in reversed(back):
            out.append(p[out[-1]])
        return np.array(out[::-1], int)

    def gradient(self, x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Observed less expected counts, by forward and backward sums in log space."""
        n = len(x)
        node = np.c_[np.zeros(n), x @ self.w]
        f, b = np.zeros((n, 2)), np.zeros((n, 2))
        f[0] = node[0]
        for i in range(1, n):
            f[i] = np.logaddexp(f[i - 1, 0] + self.t[0], f[i - 1, 1] + self.t[1]) + node[i]
        for i in range(n - 2, -1, -1):
            z = self.t + node[i + 1] + b[i + 1]
            b[i] = np.logaddexp(z[:, 0], z[:, 1])
        total = np.logaddexp(*f[-1])
        p = np.exp(f + b - total)[:, 1]
        gw, gt = x.T @ (y - p), np.zeros((2, 2))
        if n > 1:
            e = np.exp(f[:-1, :, None] + self.t + (node + b)[1:, None, :] - total)
            gt = -e.sum(0)
            np.add.at(gt, (y[:-1], y[1:]), 1)
        return gw, gt

    def fit(self, data: list[tuple[np.ndarray, np.ndarray]], rounds: int = 8, rate: float = 0.2, pull: float = 0.01) -> LineField:
        for r in range(rounds):
            for x, y in data:
                gw, gt = self.gradient(x, y)
                step = rate / (1 + r) / np.sqrt(len(x))
                self.w += step * (gw - pull * (self.w - PRIOR))
                self.t += step * (gt - pull * self.t)
        return self


def train(docs: DataFrame, labels: DataFrame, n_train: int = 400, max_bytes: int = 4_000_000, most_lines: int = 200, passes: int = 3) -> LineField:
    """Fit the field on ``n_train`` labelled texts, half of each quality; from a text the whole, in runs of ``most_lines`` lines."""
    known = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").groupBy("doc_id").agg(F.min("quality").alias("quality"))
    some = [known.where(F.col("quality") == q).orderBy(F.xxhash64(F.lit(3), "doc_id"), "doc_id").limit(n_train // 2) for q in (0, 1)]
    named = docs.where("text IS NOT NULL").join(F.broadcast(some[0].union(some[1])), "doc_id")  # at most n_train ids
    sizes = named.groupBy("doc_id").agg(F.max(F.octet_length("text")).alias("size")).orderBy(F.xxhash64("doc_id"), "doc_id").collect()
    chosen, room = [], max_bytes
    for doc, size in sizes:
        if size <= room:
            chosen.append((doc,))
            room -= size
    if not chosen:
        return LineField()
    picked = docs.sparkSession.createDataFrame(chosen, "doc_id long")
    rows = named.join(F.broadcast(picked), "doc_id").groupBy("doc_id", "quality").agg(F.max("text").alias("text")).orderBy(F.xxhash64("doc_id"), "doc_id").collect()
    texts = [(quality, x) for _, quality, text in rows if len(x := line_features(text)[0])]
    field = LineField()
    for turn in range(passes):
        data = []
        for quality, x in texts:
            y = np.full(len(x), int(quality == 0))
            if quality == 0 and turn:
                y = field.decode(x)
                y[int((x @ field.w).argmax())] = 1
            data += [(x[i : i + most_lines], y[i : i + most_lines]) for i in range(0, len(x), most_lines)]
        field = LineField().fit(data)
    return field


def _judge(field: LineField, least_share: float):
    def run(batches):
        for b in batches:
            out = []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                m = base_measures(text)
                failed = m[0] < 10 or 100 * m[4] > 20 * m[0]
                x, letters = line_features(text or "")
                share = float(letters[field.decode(x) == 0].sum() / letters.sum()) if len(x) else 0.0
                out.append((doc, *m, failed, share, not failed and share >= least_share))
            kinds = [pa.int64()] * 6 + [pa.bool_(), pa.float64(), pa.bool_()]
            names = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "content_share", "kept"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*out, strict=True) if out else [[]] * 9, kinds, strict=True)], names=names)

    return lean(run)


def quality(docs: DataFrame, labels: DataFrame, least_share: float = 0.5, **kw) -> DataFrame:
    """docs(doc_id, text) -> the base measures, base_failed, content_share, kept."""
    docs = plain(docs, doc_id="doc_id", text="text")
    field = train(docs, labels, **kw)
    kind = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, content_share double, kept boolean"
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_judge(field, least_share), kind)
