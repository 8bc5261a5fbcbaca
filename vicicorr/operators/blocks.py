"""Balls of two hops counted by pairs of blocks of nodes, each pair in one task.

A task holds the arcs of a block of roots and those of a block of targets, marks in a
bitmap of some roots by all targets what paths of two arcs meet, and counts the marks.
Arcs travel sorted, as compressed differences, once for each partner of their block; no row
for a (root, node) is ever shuffled or stored.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.graphs import ship
from .balls import cut

#: Nodes and arcs of a block, about; rows packed at once; bytes of a bitmap; paths marked at once.
NODES, ARCS, ROWS, BITMAP, PATHS = 1 << 16, 1 << 22, 1 << 20, 1 << 22, 1 << 21
COUNTS = ("size", "cnt_a", "cnt_b", "c")
_PLANES = ("p0", "p1", "p2", "p3", "p4")
_PACK = pa.schema([("at", pa.int64()), *((p, pa.binary()) for p in _PLANES)])
_FOUND = pa.schema([("root", pa.int64()), *((c, pa.int64()) for c in COUNTS)])


def coded(x: np.ndarray) -> bytes:
    """Whole numbers as compressed byte planes of their differences."""
    u = np.ascontiguousarray(x, np.int64).view(np.uint64)
    return zlib.compress(np.diff(u, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T.tobytes(), 1)


def decoded(b: bytes) -> np.ndarray:
    planes = np.frombuffer(zlib.decompress(b), np.uint8).reshape(8, -1)
    return np.cumsum(planes.T.copy().view(np.uint64).ravel(), dtype=np.uint64).view(np.int64)


def _pack(batches):
    """Rows (at, numbers) as one row a block, sorted by the first two of the numbers."""
    held, n = [], 0

    def out():
        cols = [np.concatenate(c) for c in zip(*held, strict=True)]
        order = np.lexsort((cols[min(2, len(cols) - 1)], cols[1], cols[0]))
        cols = [c[order] for c in cols]
        start = np.flatnonzero(np.r_[True, cols[0][1:] != cols[0][:-1]])
        stop = np.r_[start[1:], len(order)]
        planes = [[coded(c[a:b]) for a, b in zip(start, stop, strict=True)] for c in cols[1:]]
        planes += [[None] * len(start)] * (len(_PLANES) - len(planes))
        return pa.RecordBatch.from_arrays([pa.array(cols[0][start]), *(pa.array(p, pa.binary()) for p in planes)], schema=_PACK)

    for b in batches:
        if b.num_rows:
            held.append([c.to_numpy(zero_copy_only=False) for c in b.columns])
            n += b.num_rows
        if n >= ROWS:
            yield out()
            held, n = [], 0
    if n:
        yield out()


def packed(df: DataFrame, blocks: int) -> DataFrame:
    """(at, p0, ...): columns of whole numbers, coded, by blocks of the first."""
    first, *rest = df.columns
    at = F.pmod(F.xxhash64(F.col(first).cast("long")), F.lit(blocks)).cast("long").alias("at")
    return df.select(at, *(F.col(c).cast("long").alias(c) for c in (first, *rest))).mapInArrow(_pack, ", ".join(["at long", *(f"{p} binary" for p in _PLANES)]))


def _places(ids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of x in sorted ids, and which of x are there."""
    at = np.minimum(np.searchsorted(ids, x), max(len(ids) - 1, 0))
    return at, (ids[at] == x) if len(ids) else np.zeros(len(x), bool)


def two_hop_sums(roots: np.ndarray, near: tuple[np.ndarray, np.ndarray], targets: np.ndarray, weights: np.ndarray, far: tuple[np.ndarray, np.ndarray]) -> np.ndarray:
    """Sum of the weights of the targets within two hops of each root: near (root, via), far (target, via), roots and targets sorted."""
    kinds, code = np.unique(weights, axis=0, return_inverse=True)
    by_kind = np.argsort(code.ravel(), kind="stable")
    column = np.empty(len(targets), np.int64)
    column[by_kind] = np.arange(len(targets))
    edge = np.r_[0, np.cumsum(np.bincount(code.ravel(), minlength=len(kinds)))].tolist()

    at, there = _places(targets, far[0])
    vias, v = np.unique(far[1][there], return_inverse=True)
    order = np.argsort(v, kind="stable")
    met = column[at[there]][order]
    size = np.bincount(v, minlength=len(vias))
    begin = np.cumsum(size) - size

    at, there = _places(roots, near[0])
    r, v = np.r_[at[there], np.arange(len(roots))], np.r_[near[1][there], roots]  # a root is a via too: its neighbours are met
    at, there = _places(vias, v)
    r, v = r[there], at[there]
    order = np.argsort(r, kind="stable")
    r, v = r[order], v[order]
    own, there = _places(targets, roots)
    own = np.where(there, column[own] if len(targets) else 0, -1)

    out = np.zeros((len(roots), weights.shape[1]), np.int64)
    if not len(targets):
        return out
    rows = max(1, BITMAP // len(targets))
    marks = np.zeros((rows, len(targets)), bool)
    flat = marks.reshape(-1)
    for lo in range(0, len(roots), rows):
        hi = min(lo + rows, len(roots))
        marks[:] = False
        some = np.flatnonzero(own[lo:hi] >= 0)
        marks[some, own[lo:hi][some]] = True
        a, b = np.searchsorted(r, (lo, hi))
        n = size[v[a:b]]
        upto = np.cumsum(n)
        x = 0
        while x < b - a:
            before = int(upto[x] - n[x])
            y = max(x + 1, int(np.searchsorted(upto, before + PATHS, "right")))
            k = n[x:y]
            shift = begin[v[a + x : a + y]] - (upto[x:y] - k - before)
            row = (r[a + x : a + y] - lo) * len(targets)
            path = np.arange(int(upto[y - 1]) - before)
            path += np.repeat(shift, k)
            path = met[path]
            path += np.repeat(row, k)
            flat[path] = True
            x = y
        if len(kinds) <= 64:
            n = np.array([[np.count_nonzero(m[s:e]) for s, e in zip(edge, edge[1:], strict=False)] for m in marks[: hi - lo]], np.int64)
            out[lo:hi] = n @ kinds
        else:
            for s in range(0, hi - lo):
                out[lo + s] = weights[by_kind[marks[s]]].sum(0)
    return out


def _pair(key: tuple[pa.Scalar, ...], tbl: pa.Table) -> pa.Table:
    kind = np.array(tbl.column("kind").to_pylist())

    def of(k: int, n: int) -> list[np.ndarray]:
        part = tbl.filter(pa.array(kind == k))
        return [np.concatenate([np.empty(0, np.int64), *(decoded(b) for b in part.column(p).to_pylist())]) for p in _PLANES[:n]]

    roots = np.unique(of(2, 1)[0])
    targets, *weights = of(3, 5)
    order = np.argsort(targets, kind="stable")
    if not len(roots) or not len(targets):
        return pa.Table.from_batches([], schema=_FOUND)
    sums = two_hop_sums(roots, of(0, 2), targets[order], np.stack(weights, 1)[order], of(1, 2))
    some = np.flatnonzero(sums.any(1))
    return pa.Table.from_arrays([pa.array(roots[some]), *(pa.array(np.ascontiguousarray(c)) for c in sums[some].T)], schema=_FOUND)


def two_hop_counts(arcs: DataFrame, roots: DataFrame, weights: DataFrame, kept: dict) -> DataFrame:
    """(root, <counts>): sums of the counts of weights(node, <counts>) within two hops of each of roots(root), itself included.

    arcs(u, v) go both ways, weights have a row a node.  The packed arcs stay in ``kept``."""
    ship(arcs.sparkSession)
    weights = cut(weights.select("node", *COUNTS))
    if "packed" not in kept:
        blocks = max(4, -(-weights.count() // NODES), -(-arcs.count() // ARCS))
        kept["packed"] = cut(packed(arcs.select("u", "v"), blocks)), blocks
    lists, blocks = kept["packed"]
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long")))
    asks = lambda df, kind: df.select(F.col("at").alias("qb"), every.alias("tb"), F.lit(kind).alias("kind"), *_PLANES)
    gives = lambda df, kind: df.select(every.alias("qb"), F.col("at").alias("tb"), F.lit(kind).alias("kind"), *_PLANES)
    rows = asks(lists, 0).union(gives(lists, 1)).union(asks(packed(roots.select("root"), blocks), 2)).union(gives(packed(weights, blocks), 3).select("qb", "tb", "kind", *_PLANES))
    found = rows.groupBy("qb", "tb").applyInArrow(_pair, "root long, " + ", ".join(f"{c} long" for c in COUNTS))
    return found.groupBy("root").agg(*(F.sum(c).alias(c) for c in COUNTS))
