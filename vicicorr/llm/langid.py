"""Language identification: multinomial naive Bayes over hashed character n-grams.

Counts are gathered by the executors from a sample of labelled rows of bounded
size for each language, chosen by hash; the log-probability matrix (languages x
buckets) is broadcast; texts are scored whole, a few at a time, as sparse rows of
n-gram counts times that matrix.

The model is bounded: it learns the ``most_langs`` commonest languages (ties by
name), ``per_lang`` rows of each, so it never outgrows a broadcast.

Null text or text without a letter gives ``und`` and score 0; so does an empty
training set.  Ties go to the first language by name.  Rows with null or repeated
ids are scored row by row; an empty table gives none; other columns are not read.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch, fold, lean, plain
from .ngram_join import ddl

ORDERS, BUCKETS, PIECE = (1, 2, 3), 1 << 15, 1 << 18
_LETTER = re.compile(r"[^\W\d_]")
_COUNT = pa.schema([("lang", pa.string()), ("bucket", pa.int64()), ("c", pa.int64())])


def ngram_buckets(text: str):
    """Buckets of all n-grams of the lower-cased text, piece by piece; pieces overlap so that none is lost."""
    codes = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    longest = max(ORDERS)
    for at in range(0, len(codes), PIECE):
        x = codes[max(0, at - longest + 1) : at + PIECE]
        fresh = min(at, longest - 1)  # the first ``fresh`` places belong to the piece before
        for n in ORDERS:
            if len(x) < n:
                continue
            h = x[: len(x) - n + 1] * np.uint32(0x9E3779B1)
            for i in range(1, n):
                h = (h ^ x[i : len(x) - n + 1 + i]) * np.uint32(0x85EBCA6B)
                h ^= h >> np.uint32(15)
            h = ((h + np.uint32(n)) * np.uint32(0xC2B2AE35)) >> np.uint32(17)
            yield h[max(0, fresh - n + 1) :]


def _count(batches):
    sums: dict[str, np.ndarray] = {}
    for b in batches:
        for lang, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
            mine = sums.setdefault(lang, np.zeros(BUCKETS, np.int64))
            for h in ngram_buckets(text):
                mine += np.bincount(h, minlength=BUCKETS)
    for lang, c in sums.items():
        at = np.flatnonzero(c)
        yield batch(_COUNT, [lang] * len(at), at, c[at])


def train(docs: DataFrame, per_lang: int = 2000, most_langs: int = 1000, smooth: float = 0.5) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(languages, log probabilities buckets x languages, log priors) from about ``per_lang`` rows a language.

    docs(lang, text, key): the sample takes the rows whose hash of ``key`` falls
    in the share that makes ``per_lang`` rows.  The model has at most
    ``most_langs`` x buckets numbers, for the commonest languages.
    """
    rows = docs.where("lang IS NOT NULL AND text IS NOT NULL")
    sizes = {r[0]: r[1] for r in rows.groupBy("lang").count().orderBy(F.desc("count"), "lang").limit(most_langs).collect()}
    if not sizes:
        return [], np.zeros((BUCKETS, 0), np.float32), np.zeros(0)
    share = F.create_map(*(F.lit(x) for k, n in sizes.items() for x in (k, int(1e6 * min(1.0, per_lang / n)))))
    some = rows.where(F.col("lang").isin(list(sizes)) & (F.pmod(F.xxhash64(F.lit(11), "key"), F.lit(1_000_000)) < share[F.col("lang")]))
    counts = some.select("lang", "text").mapInArrow(_count, ddl(_COUNT)).groupBy("lang", "bucket").agg(F.sum("c").alias("c")).collect()
    langs = sorted(sizes)
    m = np.full((BUCKETS, len(langs)), smooth)
    at = {k: i for i, k in enumerate(langs)}
    for k, b, c in counts:
        m[b, at[k]] += c
    total = np.array([sizes[k] for k in langs], float)
    return langs, np.log(m / m.sum(0)).astype(np.float32), np.log(total / total.sum())


def sparse_scores(texts: list[str], logp: np.ndarray, prior: np.ndarray) -> np.ndarray:
    """Log joint probability of each text and language: rows of counts, zeros left out, times the matrix."""
    counts = np.zeros((len(texts), BUCKETS), np.int64)
    for mine, text in zip(counts, texts, strict=True):
        for h in ngram_buckets(text):
            mine += np.bincount(h, minlength=BUCKETS)
    row, bucket = np.nonzero(counts)
    out = np.repeat(prior[None], len(texts), 0)
    if len(row):
        head = np.flatnonzero(np.r_[True, row[1:] != row[:-1]])
        out[row[head]] += np.add.reduceat(counts[row, bucket][:, None] * logp[bucket].astype(np.float64), head, axis=0)
    return out


def _predict(sent, group: int = 32):
    def run(batches):
        langs, logp, prior = sent.value
        for b in batches:
            texts = b.column(b.num_columns - 1).to_pylist()
            pred, score = ["und"] * len(texts), [0.0] * len(texts)
            known = [i for i, t in enumerate(texts) if langs and t is not None and _LETTER.search(t)]
            for at in range(0, len(known), group):
                some = known[at : at + group]
                s = sparse_scores([texts[i] for i in some], logp, prior)
                e = np.exp(s - s.max(1, keepdims=True))
                for i, best, p in zip(some, s.argmax(1), e.max(1) / e.sum(1), strict=True):
                    pred[i], score[i] = langs[best], float(p)
            cols = [b.column(i) for i in range(b.num_columns - 1)]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(pred, pa.string()), pa.array(score, pa.float64())], names=["doc_id", "held_out", "lang_pred", "score"])

    return lean(run)


def identify(docs: DataFrame, mod: int = 4, rest: int = 2, **kw) -> DataFrame:
    """docs(doc_id, text, lang) -> doc_id, held_out, lang_pred, score; learns where crc32 of the id modulo ``mod`` is not ``rest``."""
    docs = plain(docs, doc_id="doc_id", text="text", lang="lang")
    held = fold("doc_id", mod) == rest
    model = docs.sparkSession.sparkContext.broadcast(train(docs.where(~held).select("lang", "text", F.col("doc_id").alias("key")), **kw))
    return docs.select(F.col("doc_id").cast("long"), held.alias("held_out"), "text").mapInArrow(_predict(model), "doc_id long, held_out boolean, lang_pred string, score double")
