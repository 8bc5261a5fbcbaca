"""Subword encoding with seeded merge-dropout, and decoding without loss.

A merge-type vocabulary joins neighbouring symbols in order of score.  Dropout
skips a candidate merge when a hash of (seed, variant, chunk, place of the pair)
falls below the rate, so a text's segmentation varies with the seed and with the
document's variant, yet comes out the same on every run and retry.  The agenda
runs for many chunks at a time: each round takes every chunk's best candidate
that was not skipped, leftmost first among equals.  Chunks (a run of spaces and
the word after it) can't be joined by any piece, so each is encoded once a
variant and kept.

Spaces are the word mark; a literal word mark, line ends and characters without
a piece are spelt in bytes, so decoding gives back every text exactly.  Null
text is empty and has no ids.
"""

from __future__ import annotations

import re
import zlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes
from .lattice_lm import MARK, load_vocabulary

_CHUNK = re.compile(r"\n| *[^ \n]+| +")
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


class MergeDropout:
    def __init__(self, model_path: str, rate: float = 0.1, seed: int = 13, variants: int = 4, most: int = 1_200_000):
        pieces, scores, self.byte_ids = load_vocabulary(model_path)
        self.size, self.variants, self.most = len(pieces), variants, most
        self.cut = np.uint64(int(rate * (2**64 - 1)))
        self.seed = seed
        byte = set(self.byte_ids.tolist())
        number = {p: i for i, p in enumerate(pieces) if p and i not in byte}
        self.char = {(" " if p == MARK else p): i for p, i in number.items() if len(p) == 1}
        self.raw = [b"" if not p else bytes([int(p[3:5], 16)]) if i in byte else p.replace(MARK, " ").encode() for i, p in enumerate(pieces)]
        left, right, out = [], [], []
        for p, i in number.items():
            for k in range(1, len(p)):
                a, b = number.get(p[:k]), number.get(p[k:])
                if a is not None and b is not None:
                    left.append(a)
                    right.append(b)
                    out.append(i)
        key = np.array(left, np.int64) * self.size + np.array(right, np.int64)
        order = np.argsort(key)
        self.pair, self.joined = key[order], np.array(out, np.int64)[order]
        self.rank = np.argsort(np.argsort(-scores, kind="stable"), kind="stable").astype(np.int64)
        self.kept: list[dict[str, bytes]] = [{} for _ in range(variants)]

    def symbols(self, chunk: str) -> list[int]:
        out = []
        for c in chunk:
            i = self.char.get(c)
            out += [i] if i is not None else self.byte_ids[list(c.encode("utf-8", "surrogatepass"))].tolist()
        return out

    def _candidates(self, sym, start, stop, own, key, i):
        """Rank of joining the symbols at ``i`` with their right neighbours; the largest number if none or skipped."""
        none = np.iinfo(np.int64).max
        j = np.minimum(i + 1, len(sym) - 1)
        pair = sym[i] * self.size + sym[j]
        at = np.minimum(np.searchsorted(self.pair, pair), len(self.pair) - 1)
        ok = (self.pair[at] == pair) & (own[i] == own[j]) & (i != j)
        h = mix(key[own[i]] + (start[i].astype(np.uint64) << np.uint64(42)) + (start[j].astype(np.uint64) << np.uint64(21)) + stop[j].astype(np.uint64))
        ok &= h >= self.cut
        return np.where(ok, self.rank[self.joined[at]], none), np.where(ok, self.joined[at], -1)

    def encode_chunks(self, chunks: list[str], variant: int) -> list[bytes]:
        parts = [self.symbols(c) for c in chunks]
        size = np.array([len(p) for p in parts])
        sym = np.array([s for p in parts for s in p], np.int64)
        own = np.repeat(np.arange(len(parts)), size)
        start = np.arange(len(sym)) - np.repeat(np.cumsum(size) - size, size)
        stop = start + 1
        key = mix(np.array([xxhash.xxh3_64_intdigest(c.encode("utf-8", "surrogatepass")) for c in chunks], np.uint64) + mix(np.array([self.seed * 1_000_003 + variant], np.uint64)))
        none = np.iinfo(np.int64).max
        rank, new = self._candidates(sym, start, stop, own, key, np.arange(len(sym)))
        done_sym, done_own, done_start = [], [], []
        while len(sym):
            head = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
            best = np.minimum.reduceat(rank, head)
            n = np.diff(np.r_[head, len(own)])
            live = best != none
            if not live.all():  # chunks without a candidate are done
                gone = np.repeat(~live, n)
                done_sym.append(sym[gone])
                done_own.append(own[gone])
                done_start.append(start[gone])
                keep = ~gone
                sym, own, start, stop, rank, new, n, best = sym[keep], own[keep], start[keep], stop[keep], rank[keep], new[keep], n[live], best[live]
                if not len(sym):
                    break
            hit = np.flatnonzero(rank == np.repeat(best, n))
            hit = hit[np.r_[True, own[hit[1:]] != own[hit[:-1]]]]  # leftmost of each chunk
            sym[hit] = new[hit]
            stop[hit] = stop[hit + 1]
            keep = np.ones(len(sym), bool)
            keep[hit + 1] = False
            place = np.cumsum(keep) - 1
            sym, own, start, stop, rank, new = sym[keep], own[keep], start[keep], stop[keep], rank[keep], new[keep]
            near = place[hit]
            near = np.concatenate([near, near[near > 0] - 1])
            rank[near], new[near] = self._candidates(sym, start, stop, own, key, near)
        sym, own, start = (np.concatenate(x) if x else np.empty(0, np.int64) for x in (done_sym, done_own, done_start))
        order = np.lexsort((start, own))
        ids, n = sym[order].astype(np.uint16 if self.size < 65536 else np.uint32), np.bincount(own, minlength=len(chunks))
        raw, w = ids.tobytes(), ids.itemsize
        ends = np.cumsum(n) * w
        return [raw[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True)]

    def encode(self, texts: list[str], variants: list[int]) -> list[np.ndarray]:
        cut = [_CHUNK.findall(t) for t in texts]
        for v in set(variants):
            kept = self.kept[v]
            if len(kept) > self.most // self.variants:
                kept.clear()
            new = list(set().union(*(x for x, mine in zip(cut, variants, strict=True) if mine == v)).difference(kept))
            for at in range(0, len(new), 20_000):
                some = new[at : at + 20_000]
                kept.update(zip(some, self.encode_chunks(some, v), strict=True))
        kind = np.uint16 if self.size < 65536 else np.uint32
        return [np.frombuffer(b"".join(map(self.kept[v].__getitem__, x)), kind) for x, v in zip(cut, variants, strict=True)]

    def spell(self, ids) -> bytes:
        return b"".join(map(self.raw.__getitem__, ids))

    def decode(self, ids) -> str:
        return self.spell(ids).decode("utf-8", "surrogatepass")


_MODELS: dict = {}


def _model(*args) -> MergeDropout:
    if args not in _MODELS:
        _MODELS[args] = MergeDropout(*args)
    return _MODELS[args]


def _encode(args: tuple, group: int = 512):
    def run(batches):
        m = _model(*args)
        for b in batches:
            for at in range(0, b.num_rows, group):
                some = b.slice(at, group)
                docs, texts = some.column(0).to_pylist(), [t or "" for t in some.column(1).to_pylist()]
                variants = [int(xxhash.xxh3_64_intdigest(str(d).encode(), seed=args[2]) % m.variants) for d in docs]
                ids = m.encode(texts, variants)
                yield pa.RecordBatch.from_arrays([some.column(0), pa.array(variants, pa.int32()), pa.array([x.astype("<u4").tobytes() for x in ids], pa.binary())], names=["doc_id", "variant", "ids"])

    return run


def _decode(args: tuple):
    def run(batches):
        m = _model(*args)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([m.decode(np.frombuffer(x, "<u4").tolist()) for x in b.column(1).to_pylist()], pa.string())], names=["doc_id", "text"])

    return run


def encode(docs: DataFrame, model_path: str, rate: float = 0.1, seed: int = 13, variants: int = 4) -> DataFrame:
    """docs(doc_id, text) -> doc_id, variant, ids (little-endian unsigned 32-bit)."""
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_encode((model_path, rate, seed, variants)), "doc_id long, variant int, ids binary")


def decode(rows: DataFrame, model_path: str, rate: float = 0.1, seed: int = 13, variants: int = 4) -> DataFrame:
    """rows(doc_id, ids) -> doc_id, text."""
    return rows.select("doc_id", "ids").mapInArrow(_decode((model_path, rate, seed, variants)), "doc_id long, text string")


def _digest(args: tuple):
    """Encode, decode, and keep only what can be checked: counts, checksum, whether the text came back."""
    inner = _encode(args)

    def run(batches):
        m = _model(*args)
        for b in batches:
            texts, at = as_bytes(b.column(1)), 0
            for x in inner(iter([b])):
                ids = x.column(2).to_pylist()
                back = [m.spell(np.frombuffer(i, "<u4").tolist()) == (t or b"") for i, t in zip(ids, texts[at : at + x.num_rows], strict=True)]
                at += x.num_rows
                yield pa.RecordBatch.from_arrays([x.column(0), x.column(1), pa.array([len(i) // 4 for i in ids], pa.int64()), pa.array([zlib.crc32(i) for i in ids], pa.int64()), pa.array(back, pa.bool_())], names=["doc_id", "variant", "n_ids", "ids_crc32", "lossless"])

    return run


def encode_digest(docs: DataFrame, model_path: str, rate: float = 0.1, seed: int = 13, variants: int = 4) -> DataFrame:
    """docs(doc_id, text) -> doc_id, variant, n_ids, ids_crc32, lossless, in one pass."""
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(_digest((model_path, rate, seed, variants)), "doc_id long, variant int, n_ids long, ids_crc32 long, lossless boolean")
