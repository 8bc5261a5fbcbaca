"""Nearest neighbours along shifted space-filling curves.

Vectors are projected on fixed random directions, another set for each of several
shifted Hilbert orderings; Spark range-partitions and sorts these, which gives
every row a place in each.  A query reads the rows within ``near`` places in every
ordering; the windows merge and are reranked by exact distance.

``near`` is fitted on a bounded sample of queries (``SAMPLE``, by hash), whose
exact neighbours one pass over all rows finds: it is the least width whose windows
hold a share ``recall`` of them.  On clustered vectors a few dozen places do; on
vectors without any structure most rows must be read, as for every index.

With ``exact`` a check follows: the first ordering is cut in windows of
consecutive keys, each with its bounding ball, and a query's windows are widened
to all whose ball reaches into the radius that its windows gave.  So the answer is
exact at any size.

Vectors that are null, empty, zero or hold a null or non-finite component take no
part, nor do those of another dimension than the commonest (the larger among
equals) and rows with a null id.  Rows that repeat an id count once (the
componentwise smallest vector).  Ties go to the smaller id.  Fewer than k
candidates give all of them; an empty table gives none.  Other columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import batch, binaries, checkpointed, plain, shuffle_parts, stored
from .ngram_join import ddl

DIMS, BITS, CURVES = 8, 7, 8
SAMPLE, RECALL = 64, 0.95  # queries that fit the windows' width, and the share of their neighbours that windows must hold
NEAR, BLOCK = 32, 8192  # least width on each side of a query; most rows of a block of an ordering
WINDOW_ROWS, CHUNK = 512, 64  # vectors in a window, queries in a chunk
GROUP = 64  # chunks that meet a window in one task


def hilbert(x: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Keys of points with integer coordinates below 2**bits, by the transpose form of the curve: undo
    excess rotations from the top bit down, Gray-encode, interleave."""
    x = x.astype(np.int64).T.copy()
    n, top = len(x), 1 << (bits - 1)
    q = top
    while q > 1:
        low = q - 1
        for i in range(n):
            on = (x[i] & q) > 0
            t = np.where(on, 0, (x[0] ^ x[i]) & low)
            x[0] ^= np.where(on, low, t)
            x[i] ^= t
        q >>= 1
    for i in range(1, n):
        x[i] ^= x[i - 1]
    t, q = np.zeros_like(x[0]), top
    while q > 1:
        t = np.where(x[n - 1] & q, t ^ (q - 1), t)
        q >>= 1
    x ^= t
    key = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(n):
            key = (key << 1) | ((x[i] >> b) & 1)
    return key


def directions(dim: int, seed: int = 29) -> np.ndarray:
    """At most DIMS orthonormal columns for each ordering, side by side."""
    rng = np.random.default_rng(seed)
    return np.hstack([np.linalg.qr(rng.standard_normal((dim, min(dim, DIMS))))[0] for _ in range(CURVES)])


def distances(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    """All Euclidean distances, summed component by component in double precision."""
    return _across(q, np.ascontiguousarray(x.T))


def _across(q: np.ndarray, by_dim: np.ndarray) -> np.ndarray:
    """The same for rows given by dimension, so that every step reads them in order."""
    d = np.zeros((len(q), by_dim.shape[1]))
    for i in range(q.shape[1]):
        t = q[:, i, None] - by_dim[i]
        t *= t
        d += t
    return np.sqrt(d)


_SPREAD = pa.schema([("d", pa.int64()), ("n", pa.float64()), ("s", pa.float64()), ("ss", pa.float64())])


def _vectors(b: pa.RecordBatch, dim: int) -> np.ndarray:
    return np.frombuffer(b"".join(b.column(1).to_pylist()), np.float64).reshape(-1, dim)


def _spread(dim: int):
    def run(batches):
        for b in batches:
            p = _vectors(b, dim) @ directions(dim)
            yield batch(_SPREAD, np.arange(p.shape[1]), np.full(p.shape[1], float(len(p))), p.sum(0), (p * p).sum(0))

    return run


_KEYED = pa.schema([("curve", pa.int64()), ("key", pa.int64()), ("id", pa.int64()), ("v", pa.binary())])


def _keys(dim: int, mean: np.ndarray, sd: np.ndarray):
    def run(batches):
        at, n = directions(dim), len(mean) // CURVES
        shift = np.random.default_rng(31).random(len(mean))
        for b in batches:
            p = np.clip((_vectors(b, dim) @ at - mean) / (8 * sd) + 0.5, 0, 1)
            grid = ((p + shift) / 2 * ((1 << BITS) - 1)).astype(np.int64)
            for c in range(CURVES):
                yield batch(_KEYED, np.full(b.num_rows, c), hilbert(grid[:, c * n : (c + 1) * n]), b.column(0), b.column(1))

    return run


_NEAR = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.float64())])


def _best(ids: np.ndarray, dist: np.ndarray, k: int) -> np.ndarray:
    """Places of the k nearest, ties to smaller ids."""
    if len(dist) > 4 * k:
        some = np.flatnonzero(dist <= np.partition(dist, k - 1)[k - 1])
    else:
        some = np.arange(len(dist))
    return some[np.lexsort((ids[some], dist[some]))][:k]


def _nearest_to(ids: np.ndarray, q: np.ndarray, k: int):
    """Stated queries against all rows, batch by batch: the k nearest of each in a batch."""

    def run(batches):
        for b in batches:
            x = _vectors(b, q.shape[1])
            mine = b.column(0).to_numpy()
            d = distances(q, x)
            d[ids[:, None] == mine[None, :]] = np.inf
            for i, row in zip(ids, d, strict=True):
                best = _best(mine, row, k)
                best = best[np.isfinite(row[best])]
                yield batch(_NEAR, np.full(len(best), i), mine[best], row[best])

    return run


def places(ordered: DataFrame) -> DataFrame:
    """ordered(curve, key, id, v, m), m a partition and a place in it -> with ``pos``, the place in the whole order."""
    spark = ordered.sparkSession
    part = F.shiftright("m", 33)
    at, rows = 0, []
    for p, n in sorted(tuple(r) for r in ordered.groupBy(part.alias("p")).count().collect()):  # a row a partition
        rows.append((p, at))
        at += n
    base = F.broadcast(spark.createDataFrame(rows, "p long, base long"))
    return ordered.withColumn("p", part).join(base, "p").select("curve", "id", "v", (F.col("base") + F.col("m").bitwiseAND(F.lit((1 << 33) - 1))).alias("pos"))


def fitted_width(packed: DataFrame, placed: DataFrame, dim: int, k: int, every: int, recall: float) -> int:
    """Least number of places that holds ``recall`` of the sample's neighbours in one ordering or another."""
    some = packed.where(F.col("id") % every == 0).orderBy(F.xxhash64(F.lit(3), "id"), "id").limit(SAMPLE).collect()
    if not some:
        return NEAR
    q = np.array([r.id for r in some], np.int64)
    hits = packed.mapInArrow(_nearest_to(q, np.array([np.frombuffer(r.v, np.float64) for r in some]), k), ddl(_NEAR))
    best = hits.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id"))).where(F.col("r") <= k).collect()  # SAMPLE x k rows
    if not best:
        return NEAR
    wanted = sorted({*q.tolist(), *(r.vec_id for r in best)})
    at = {(r.curve, r.id): r.pos for r in placed.where(F.col("id").isin(wanted)).select("curve", "id", "pos").collect()}
    gaps = sorted(min(abs(at[c, r.query_id] - at[c, r.vec_id]) for c in range(CURVES)) for r in best)
    return max(NEAR, gaps[min(len(gaps) - 1, int(np.ceil(recall * len(gaps))))])


def _block_best(dim: int, k: int, near: int):
    """Within a block of an ordering: each query against the rows at most ``near`` places off."""

    def run(key: tuple[pa.Scalar, ...], tbl: pa.Table) -> pa.Table:
        ids, pos, side = (tbl.column(c).to_numpy() for c in ("id", "pos", "side"))
        v = np.frombuffer(b"".join(binaries(tbl, "v")), np.float64).reshape(-1, dim)
        rows, asked, out = np.flatnonzero(side == 0), np.flatnonzero(side == 1), []
        rows = rows[np.argsort(pos[rows], kind="stable")]
        place, mine, by_dim = pos[rows], ids[rows], np.ascontiguousarray(v[rows].T)
        for i in asked:
            lo, hi = np.searchsorted(place, pos[i] - near), np.searchsorted(place, pos[i] + near, side="right")
            others = np.flatnonzero(mine[lo:hi] != ids[i])
            if len(others):
                d, some = _across(v[i][None], by_dim[:, lo:hi])[0][others], mine[lo:hi][others]
                best = _best(some, d, k)
                out.append((np.full(len(best), ids[i]), some[best], d[best]))
        return pa.Table.from_batches([batch(_NEAR, *(np.concatenate(c) for c in zip(*out, strict=True)))] if out else [], schema=_NEAR)

    return run


def in_windows(placed: DataFrame, dim: int, k: int, every: int, near: int) -> DataFrame:
    """(query_id, vec_id, score): the best of each query's windows, a row once.

    Orderings are cut in blocks of equal numbers of rows; a query goes to the blocks
    that its window touches, so a block is met by the queries about it alone."""
    width = min(max(near, 256), BLOCK)
    rows = placed.select("curve", F.floor(F.col("pos") / width).alias("block"), "id", "pos", "v", F.lit(0).alias("side"))
    reach = F.sequence(F.floor((F.col("pos") - near) / width), F.floor((F.col("pos") + near) / width))
    asked = placed.where(F.col("id") % every == 0).select("curve", F.explode(reach).alias("block"), "id", "pos", "v", F.lit(1).alias("side"))
    return rows.union(asked).groupBy("curve", "block").applyInArrow(_block_best(dim, k, near), ddl(_NEAR)).distinct()


_TILE = pa.schema([("tile", pa.int64()), ("n", pa.int64()), ("ids", pa.binary()), ("vs", pa.binary()), ("centre", pa.binary()), ("radius", pa.float64()), ("reach", pa.binary()), ("reach_most", pa.float64())])


def _tiles(dim: int, rows: int, with_reach: bool):
    """Consecutive rows packed, with their bounding ball: ids, vectors and, for queries, their radii."""

    def pack(number, ids, vs, reach):
        centre = vs.mean(0)
        radius = float(np.sqrt(((vs - centre) ** 2).sum(1)).max())
        return batch(_TILE, [number], [len(ids)], [ids.tobytes()], [vs.tobytes()], [centre.tobytes()], [radius], [reach.tobytes()], [float(reach.max(initial=0))])

    def run(batches):
        from pyspark import TaskContext

        number, ids, vs, reach = TaskContext.get().partitionId() << 32, [], [], []
        held = 0
        for b in batches:
            for at in range(0, b.num_rows, rows):
                some = b.slice(at, rows)
                ids.append(some.column(0).to_numpy())
                vs.append(_vectors(some, dim))
                reach.append(some.column(2).to_numpy() if with_reach else np.empty(0))
                held += some.num_rows
                while held >= rows:
                    i, v, r = np.concatenate(ids), np.concatenate(vs), np.concatenate(reach)
                    yield pack(number, i[:rows], v[:rows], r[:rows])
                    number, held = number + 1, held - rows
                    ids, vs, reach = [i[rows:]], [v[rows:]], [r[rows:]]
        if held:
            yield pack(number, np.concatenate(ids), np.concatenate(vs), np.concatenate(reach))

    return run


_MEET = pa.schema([("tile", pa.int64()), ("chunk", pa.int64())])


def _meets(dim: int):
    """(tile, centre, radius, chunk, centre, radius, reach) rows that can hold a neighbour."""

    def run(batches):
        for b in batches:
            t = np.frombuffer(b"".join(b.column(1).to_pylist()), np.float64).reshape(-1, dim)
            q = np.frombuffer(b"".join(b.column(4).to_pylist()), np.float64).reshape(-1, dim)
            gap = np.sqrt(((t - q) ** 2).sum(1)) - b.column(2).to_numpy() - b.column(5).to_numpy()
            ok = np.flatnonzero(gap <= b.column(6).to_numpy() * (1 + 1e-9) + 1e-9)
            yield batch(_MEET, b.column(0).take(pa.array(ok)), b.column(3).take(pa.array(ok)))

    return run


def _scan(dim: int, k: int):
    """A window against up to GROUP chunks: for each query the rows within its radius, k at most."""

    def run(key: tuple[pa.Scalar, ...], tbl: pa.Table) -> pa.Table:
        rows = tbl.select(["side", "ids", "vs", "reach"]).to_pylist()
        tile = next((r for r in rows if r["side"] == 0), None)
        out = []
        if tile is not None:
            ids, vs = np.frombuffer(tile["ids"], np.int64), np.frombuffer(tile["vs"], np.float64).reshape(-1, dim)
            for r in rows:
                if r["side"] == 1:
                    q, reach = np.frombuffer(r["ids"], np.int64), np.frombuffer(r["reach"], np.float64)
                    d = distances(np.frombuffer(r["vs"], np.float64).reshape(-1, dim), vs)
                    near = (d <= reach[:, None]) & (ids[None, :] != q[:, None])
                    for i in np.flatnonzero(near.any(1)):
                        some = np.flatnonzero(near[i])
                        best = some[_best(ids[some], d[i, some], k)]
                        out.append((np.full(len(best), q[i]), ids[best], d[i, best]))
        return pa.Table.from_batches([batch(_NEAR, *(np.concatenate(c) for c in zip(*out, strict=True)))] if out else [], schema=_NEAR)

    return run


def _pack_vectors(batches):
    for b in batches:
        yield pa.RecordBatch.from_arrays([b.column(0), pa.array([np.array(v, np.float64).tobytes() for v in b.column(1).to_pylist()], pa.binary())], names=["id", "v"])


def nearest(vectors: DataFrame, k: int = 10, every: int = 100, id_col: str = "vec_id", vector_col: str = "embedding", recall: float = RECALL, exact: bool = True) -> DataFrame:
    """The k nearest of every vector whose id ``every`` divides: query_id, rank, vec_id, score (distance).

    Without ``exact`` the answer is what the orderings' windows hold."""
    spark = vectors.sparkSession
    parts = shuffle_parts(spark)
    arr = F.col("a")
    rows = plain(vectors, id=id_col, a=vector_col).select(F.col("id").cast("long"), F.col("a").cast("array<double>")).where("id IS NOT NULL AND size(a) > 0")
    fine = F.forall(arr, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf"))) & F.exists(arr, lambda x: x != 0)
    rows = rows.where(fine)
    sizes = rows.groupBy(F.size("a").alias("n")).count().orderBy(F.desc("count"), F.desc("n")).limit(1).collect()
    empty = "query_id long, rank int, vec_id long, score double"
    if not sizes:
        return spark.createDataFrame([], empty)
    dim = sizes[0][0]
    rows = rows.where(F.size("a") == dim).groupBy("id").agg(F.min("a").alias("a"))
    packed = stored(rows.mapInArrow(_pack_vectors, "id long, v binary"))
    stats = {r[0]: r[1:] for r in packed.mapInArrow(_spread(dim), ddl(_SPREAD)).groupBy("d").agg(F.sum("n"), F.sum("s"), F.sum("ss")).collect()}
    n = stats[0][0]
    mean = np.array([stats[d][1] / n for d in sorted(stats)])
    sd = np.sqrt(np.maximum([stats[d][2] / n - m * m for d, m in zip(sorted(stats), mean, strict=True)], 1e-30))
    keyed = packed.mapInArrow(_keys(dim, mean, sd), ddl(_KEYED)).repartitionByRange(parts, "curve", "key", "id").sortWithinPartitions("curve", "key", "id")
    ordered = stored(keyed.withColumn("m", F.monotonically_increasing_id()))
    placed = places(ordered)
    near = fitted_width(packed, placed, dim, k, every, recall)
    seeds = checkpointed(in_windows(placed, dim, k, every, near))
    by_near = Window.partitionBy("query_id").orderBy("score", "vec_id")
    radius = seeds.withColumn("r", F.row_number().over(by_near)).groupBy("query_id").agg(F.count(F.lit(1)).alias("c"), F.max(F.when(F.col("r") <= k, F.col("score"))).alias("reach"))
    if not exact:
        return seeds.withColumn("rank", F.row_number().over(by_near)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
    first = ordered.where("curve = 0")
    along = lambda df: df.repartitionByRange(parts, "key", "id").sortWithinPartitions("key", "id")
    tiles = stored(along(first).select("id", "v").mapInArrow(_tiles(dim, WINDOW_ROWS, False), ddl(_TILE)))
    asked = first.where(F.col("id") % every == 0).join(radius.withColumnRenamed("query_id", "id"), "id", "left")
    asked = asked.withColumn("reach", F.when(F.col("c") >= k, F.col("reach")).otherwise(F.lit(float("inf"))))
    chunks = stored(along(asked.select("key", "id", "v", "reach")).select("id", "v", "reach").mapInArrow(_tiles(dim, CHUNK, True), ddl(_TILE)))
    # every window's ball meets every chunk's, in blocks of the stated queries against all rows
    groups = max(1, -(-chunks.count() // GROUP))
    c = chunks.withColumn("g", F.pmod(F.xxhash64("tile"), F.lit(groups)))
    t = tiles.select("tile", "centre", "radius", F.explode(F.expr(f"sequence(0L, {groups - 1}L)")).alias("g"))
    both = t.join(c.select(F.col("tile").alias("chunk"), F.col("centre").alias("c2"), F.col("radius").alias("r2"), "reach_most", "g"), "g")
    meets = checkpointed(both.select("tile", "centre", "radius", "chunk", "c2", "r2", "reach_most").mapInArrow(_meets(dim), ddl(_MEET)))
    meets = meets.withColumn("g", F.pmod(F.xxhash64("chunk"), F.lit(groups)))
    left = meets.select("tile", "g").distinct().join(tiles.select("tile", "ids", "vs", "reach"), "tile").select("tile", "g", F.lit(0).alias("side"), "ids", "vs", "reach")
    right = meets.join(chunks.select(F.col("tile").alias("chunk"), "ids", "vs", "reach"), "chunk").select("tile", "g", F.lit(1).alias("side"), "ids", "vs", "reach")
    found = left.union(right).groupBy("tile", "g").applyInArrow(_scan(dim, k), ddl(_NEAR))
    all_near = found.union(seeds).distinct().withColumn("rank", F.row_number().over(by_near)).where(F.col("rank") <= k)
    return all_near.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


SQL = """
WITH v AS (
  SELECT vec_id, embedding::DOUBLE[] AS a FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
    AND len(list_filter(embedding, lambda x: x <> 0)) > 0),
d AS (
  SELECT q.vec_id AS query_id, v.vec_id, sqrt(list_reduce(list_transform(list_zip(q.a, v.a), lambda z: (z[1] - z[2]) * (z[1] - z[2])), lambda s, x: s + x)) AS score
  FROM v q JOIN v ON q.vec_id <> v.vec_id WHERE q.vec_id % 100 = 0)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM (
  SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score, vec_id) AS rank FROM d) WHERE rank <= 10
"""
