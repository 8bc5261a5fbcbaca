"""Pairs of documents that share a rare run of words, from packed blocks of hashes.

A task turns its texts into sorted 64-bit hashes of their runs and sends them by ranges of the
hash, instead of a row a run: six bytes of difference, ten in small packs, and two to eight for
the document, as its ids lie near or far.  A range is sorted in one task, and runs held by few documents give their pairs.
"""

from __future__ import annotations

from collections.abc import Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Runs packed at once; number that stands for a null document.
RUNS, NULL_DOC = 1 << 20, -(2**63)
_ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)]
_LETTERS = bytes(c if 97 <= c <= 122 else 32 for c in range(256))
_PACK = pa.schema([("grp", pa.int64()), ("base", pa.int64()), ("wide", pa.int64()), *((c, pa.binary()) for c in ("hi", "lo", "off"))])
_SET = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("docs", pa.binary())])
_PAIR = pa.schema([("x", pa.int64()), ("y", pa.int64())])


class _Words(dict):
    """word -> 64-bit hash, of up to ``most`` words."""

    def __init__(self, most: int = 120_000):
        self.most = most

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        self[word] = value = int.from_bytes(blake2b(word, digest_size=8).digest(), "little")
        return value


def run_hashes(text: bytes, k: int, words: dict) -> np.ndarray:
    """Distinct hashes of the runs of ``k`` words of letters a-z, sorted; none with fewer words."""
    got = text.translate(_LETTERS).split()
    n = len(got) - k + 1
    if n < 1:
        return np.empty(0, np.uint64)
    w = np.fromiter(map(words.__getitem__, got), np.uint64, len(got))
    h = w[:n].copy()
    for i in range(1, k):
        h ^= h >> np.uint64(29)
        h *= _ODD[0]
        h += w[i : n + i]
    h ^= h >> np.uint64(31)
    h *= _ODD[1]
    h ^= h >> np.uint64(32)
    return np.unique(h)


def _packs(k: int, bits: int):
    """(doc, text) -> packs of (hash, doc), one for each range of hashes."""

    def pack(keys: list[np.ndarray], docs: list[int]) -> pa.RecordBatch:
        ids = np.array(docs, np.int64)
        base = ids.min()
        off = np.repeat(ids.view(np.uint64) - base.astype(np.int64).view(np.uint64), [len(x) for x in keys])
        key = np.concatenate(keys)
        order = np.argsort(key, kind="stable")
        key, off = key[order], off[order]
        off = off.astype(next(t for t in (np.uint16, np.uint32, np.uint64) if off.max() <= np.iinfo(t).max))
        grp = key >> np.uint64(64 - bits)
        start = np.flatnonzero(np.r_[True, grp[1:] != grp[:-1]])
        rows = []
        for a, b in zip(start.tolist(), np.r_[start[1:], len(key)].tolist(), strict=True):
            step = np.diff(key[a:b], prepend=grp[a] << np.uint64(64 - bits))
            wide = int(step.max() >> np.uint64(48) > 0)
            hi = (step >> np.uint64(16)).astype(np.uint64 if wide else np.uint32)
            rows.append((int(grp[a]), int(base), wide, hi.tobytes(), step.astype(np.uint16).tobytes(), off[a:b].tobytes()))
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), _PACK, strict=True)], schema=_PACK)

    def run(batches):
        words, keys, docs, held = _Words(), [], [], 0
        for b in batches:
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist(), strict=True):
                if text and len(h := run_hashes(text, k, words)):
                    keys.append(h)
                    docs.append(NULL_DOC if doc is None else doc)
                    held += len(h)
                if held >= RUNS:
                    yield pack(keys, docs)
                    keys, docs, held = [], [], 0
        if held:
            yield pack(keys, docs)

    return run


def _held(rng: int, packs: pa.Table, bits: int) -> tuple[np.ndarray, np.ndarray]:
    """(hashes, documents) of a range, sorted and distinct, without runs met once."""
    keys, docs, first = [], [], np.uint64(rng) << np.uint64(64 - bits)
    for base, wide, hi, lo, off in zip(*(packs.column(c).to_pylist() for c in ("base", "wide", "hi", "lo", "off")), strict=True):
        step = (np.frombuffer(hi, np.uint64 if wide else np.uint32).astype(np.uint64) << np.uint64(16)) | np.frombuffer(lo, np.uint16)
        keys.append(np.cumsum(step, dtype=np.uint64) + first)
        docs.append((np.frombuffer(off, f"u{len(off) // len(step)}").astype(np.uint64) + np.int64(base).view(np.uint64)).view(np.int64))
    h, d = np.concatenate(keys), np.concatenate(docs)
    del keys, docs
    order = np.argsort(h, kind="stable")
    h, d = h[order], d[order]
    new = np.r_[True, h[1:] != h[:-1]]
    some = ~(new & np.r_[new[1:], True])  # runs met once pair nothing
    h, d = h[some], d[some]
    order = np.lexsort((d, h))
    h, d = h[order], d[order]
    if len(h):  # rows that repeat an id are one document
        some = np.r_[True, (h[1:] != h[:-1]) | (d[1:] != d[:-1])]
        h, d = h[some], d[some]
    return h, d


def _distinct(x: np.ndarray, y: np.ndarray) -> pa.RecordBatch:
    order = np.lexsort((y, x))
    x, y = x[order], y[order]
    if len(x):
        some = np.r_[True, (x[1:] != x[:-1]) | (y[1:] != y[:-1])]
        x, y = x[some], y[some]
    return pa.RecordBatch.from_arrays([pa.array(x), pa.array(y)], schema=_PAIR)


def _pairs(most: int, bits: int):
    """Distinct pairs of documents that share a run held by 2 to ``most`` documents of a range."""

    def run(key: tuple[pa.Scalar, ...], tbl: pa.Table) -> pa.Table:
        h, d = _held(key[0].as_py(), tbl, bits)
        start = np.flatnonzero(np.r_[True, h[1:] != h[:-1]]) if len(h) else np.empty(0, np.int64)
        size = np.diff(np.r_[start, len(h)])
        x, y = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        for n in range(2, most + 1):
            own = d[start[size == n][:, None] + np.arange(n)]
            i, j = np.triu_indices(n, 1)
            x.append(own[:, i].ravel())
            y.append(own[:, j].ravel())
        x, y = np.concatenate(x), np.concatenate(y)
        return pa.Table.from_batches([_distinct(x[x != NULL_DOC], y[x != NULL_DOC])])

    return run


def _sets(bits: int):
    """The distinct sets of two documents and more that hold a run of a range: (a, b, docs), with two hashes of the set."""

    def run(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        h, d = _held(key[0].as_py(), pa.Table.from_batches(batches), bits)
        h, d = h[d != NULL_DOC], d[d != NULL_DOC]
        if not len(h):
            return
        start = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
        size = np.diff(np.r_[start, len(h)])
        del h
        names = []
        for odd in _ODD:
            x = (d.view(np.uint64) + odd) * _ODD[0]
            x ^= x >> np.uint64(29)
            x *= odd
            x ^= x >> np.uint64(32)
            names.append(np.add.reduceat(x * _ODD[1], start))
        order = np.lexsort((names[1], names[0], size))
        a, b, n = names[0][order], names[1][order], size[order]
        order = order[(n > 1) & np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1]) | (n[1:] != n[:-1])]]
        sent = np.cumsum(size[order]) // RUNS
        for some in np.split(order, np.flatnonzero(np.diff(sent)) + 1):
            if len(some):
                yield pa.RecordBatch.from_arrays([pa.array(names[0][some].view(np.int64)), pa.array(names[1][some].view(np.int64)), pa.array([d[x : x + n].tobytes() for x, n in zip(start[some].tolist(), size[some].tolist(), strict=True)], pa.binary())], schema=_SET)

    return run


def _set_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """All pairs of each set, about RUNS at a time, repeats among these dropped."""
    held, n = [], 0
    for b in batches:
        for docs in b.column(0):
            d = np.frombuffer(docs.as_buffer(), np.int64)
            own = np.arange(len(d) - 1, -1, -1)  # documents that come after each
            sent = np.cumsum(own) // RUNS
            for some in np.split(np.arange(len(d)), np.flatnonzero(np.diff(sent)) + 1):
                m = own[some]
                at = np.arange(m.sum()) - np.repeat(np.cumsum(m) - m, m) + np.repeat(some + 1, m)
                held.append((np.repeat(d[some], m), d[at]))
                n += len(at)
                if n >= RUNS:
                    yield _distinct(*(np.concatenate(c) for c in zip(*held, strict=True)))
                    held, n = [], 0
    if n:
        yield _distinct(*(np.concatenate(c) for c in zip(*held, strict=True)))


def _ranges(docs: DataFrame, k: int) -> tuple[DataFrame, int]:
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    bits = min(16, max(8, (16 * parts - 1).bit_length()))
    rows = docs.select(F.col("doc_id").cast("long"), F.lower("text")).mapInArrow(_packs(k, bits), "grp long, base long, wide long, hi binary, lo binary, off binary")
    return rows, bits


def rare_run_pairs(docs: DataFrame, k: int = 4, most: int = 20) -> DataFrame:
    """docs(doc_id, text) -> (x, y), x < y: documents that share a run of ``k`` words a-z held by 2 to ``most`` documents; a pair may come from several ranges."""
    rows, bits = _ranges(docs, k)
    return rows.groupBy("grp").applyInArrow(_pairs(most, bits), "x long, y long")


def run_pairs(docs: DataFrame, k: int = 4) -> DataFrame:
    """docs(doc_id, text) -> (x, y), x < y: documents that share a run of ``k`` words a-z, however many hold it; a pair may come several times.

    Runs held by the same documents, as those of a copied passage are, pair them once."""
    rows, bits = _ranges(docs, k)
    sets = rows.groupBy("grp").applyInArrow(_sets(bits), "a long, b long, docs binary").dropDuplicates(["a", "b"])
    return sets.select("docs").mapInArrow(_set_pairs, "x long, y long")
