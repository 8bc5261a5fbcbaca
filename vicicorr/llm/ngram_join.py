"""N-gram Jaccard self-join with rare-first prefix filtering.

How it runs.  One pass turns every text into its set of word shingles and packs
the sets in key ranges, six bytes a shingle, so that one shuffle serves to count
documents per shingle.  A shingle held by one document can link nothing: only
shared shingles go back to their documents, rarest first.  A document whose
unique shingles already fill its prefix is done.  The few others meet on their
prefix shingles: first each with the smallest member of its list, a pair verified
once after length, suffix and positional filters.  Lists with the same smallest
member form a hub; within a hub, documents of different components so found meet
in blocks of bounded size.  There a product of 0/1 matrices over the prefixes
alone finds the pairs that share a prefix key, each in the smallest hub that both
are in, and these go through the same filters and one verification.  So a group of thousands
of near copies costs a pair for each copy, yet no link between components is lost.

Inputs: nulls in the text count as empty; empty texts have no shingle and link
with nothing.  Rows with a null id come back with a null component and link
nothing (-2^63 is reserved for them).  Repeated ids are separate rows that share
an id.  Shingles are 64-bit hashes, compared on at least 54 bits within a pair.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import NULL_ID, as_bytes, batch, binaries, checkpointed, lean, lean_group, narrow, plain, range_bits, ranges_of, runs, stored, widen, window_hashes, word_hashes
from .components import connected_components

BLOCK_KEYS, BLOCK_DOCS = 1_000_000, 60_000
_PACKED = pa.schema([("grp", pa.int64()), ("block", pa.int64()), *((c, pa.binary()) for c in ("hi", "lo", "idx", "ids", "sizes", "digests"))])
_SHARED = pa.schema([("block", pa.int64()), *((c, pa.binary()) for c in ("keys", "idx", "df", "ids", "sizes", "digests"))])
_SETS = pa.schema([("doc_id", pa.int64()), ("n", pa.int64()), ("digest", pa.binary()), ("n_own", pa.int64()), ("n_prefix", pa.int64()), ("shared", pa.binary())])


def ddl(schema: pa.Schema) -> str:
    names = {"int64": "long", "int32": "int", "double": "double", "string": "string", "bool": "boolean", "binary": "binary"}
    return ", ".join(f"{f.name} {names[str(f.type)]}" for f in schema)


def needed(n, percent: int):
    """Least overlap that any partner of a set of size n must have."""
    return -(-percent * n // 100)


def _pack(bits: int, k: int):
    def run(batches):
        from pyspark import TaskContext

        part, number = TaskContext.get().partitionId(), 0
        ids, sizes, digests, sets, held, seen = [], [], [], [], 0, set()

        def flush():
            block = (part << 24) | number
            yield batch(_PACKED, [-1 - block], [block], [None], [None], [None], [np.array(ids, np.int64).tobytes()], [np.array(sizes, np.int64).tobytes()], [b"".join(digests)])
            keys = np.concatenate(sets) if sets else np.empty(0, np.uint64)
            own = np.repeat(np.arange(len(sets), dtype=np.uint16), [len(s) for s in sets])
            order = np.argsort(keys, kind="stable")
            keys, own = keys[order], own[order]
            cut = ranges_of(keys, bits)
            for at in range(0, len(cut), 256):
                rows = cut[at : at + 256]
                hi, lo = zip(*(narrow(keys[a:b], bits) for _, a, b in rows), strict=True)
                none = [None] * len(rows)
                yield batch(_PACKED, [r for r, _, _ in rows], [block] * len(rows), hi, lo, [own[a:b].tobytes() for _, a, b in rows], none, none, none)

        for b in batches:
            for doc, text in zip(b.column(0).to_pylist(), as_bytes(b.column(1)), strict=True):
                keys = np.unique(window_hashes(word_hashes(text), k))
                digest = xxhash.xxh3_128_digest(keys.tobytes())
                ids.append(NULL_ID if doc is None else doc)
                sizes.append(len(keys))
                digests.append(digest)
                # a copy within the block, or a row without an id, needs no keys of its own
                fresh = doc is not None and digest not in seen
                seen.add(digest) if fresh else None
                sets.append(keys if fresh else keys[:0])
                held += len(keys) if fresh else 0
                if held >= BLOCK_KEYS or len(ids) >= BLOCK_DOCS:
                    yield from flush()
                    number += 1
                    ids, sizes, digests, sets, held, seen = [], [], [], [], 0, set()
        if ids:
            yield from flush()

    return lean(run)


def _share(bits: int):
    """Within a range: document counts, and the shared keys back to their blocks."""

    def run(key: tuple[pa.Scalar, ...], tbl: pa.Table) -> pa.Table:
        grp = key[0].as_py()
        if grp < 0:
            none = [None] * tbl.num_rows
            return pa.Table.from_batches([batch(_SHARED, binaries(tbl, "block"), none, none, none, *(binaries(tbl, c) for c in ("ids", "sizes", "digests")))])
        blocks = binaries(tbl, "block")
        keys = [widen(hi, lo) for hi, lo in zip(binaries(tbl, "hi"), binaries(tbl, "lo"), strict=True)]
        own = np.concatenate([np.frombuffer(x, np.uint16) for x in binaries(tbl, "idx")])
        of = np.repeat(np.arange(len(blocks)), [len(x) for x in keys])
        keys = np.concatenate(keys)
        order = np.argsort(keys, kind="stable")
        _, size = runs(keys[order])
        df = np.empty(len(keys), np.uint32)
        df[order] = np.repeat(size, size)
        keep = np.flatnonzero(df > 1)
        start, size = runs(of[keep])
        full = (keys | (np.uint64(grp) << np.uint64(48)))[keep]
        rows = [(blocks[of[keep[a]]], full[a : a + n].tobytes(), own[keep[a : a + n]].tobytes(), df[keep[a : a + n]].tobytes()) for a, n in zip(start, size, strict=True)]
        none = [None] * len(rows)
        return pa.Table.from_batches([batch(_SHARED, *(list(c) for c in zip(*rows, strict=True)), none, none, none)] if rows else [], schema=_SHARED)

    return lean_group(run)


def _order(percent: int):
    """Within a block: each document's shared keys, rarest first, and its prefix."""

    def run(key: tuple[pa.Scalar, ...], tbl: pa.Table) -> pa.Table:
        get = lambda c, kind: np.concatenate([np.frombuffer(x, kind) for x in binaries(tbl, c) if x is not None] or [np.empty(0, kind)])
        ids, n = get("ids", np.int64), get("sizes", np.int64)
        dig = get("digests", "S16") if len(ids) else []
        keys, own, df = get("keys", np.uint64), get("idx", np.uint16), get("df", np.uint32)
        order = np.lexsort((keys, df, own))
        keys, own = keys[order], own[order]
        shared = np.bincount(own, minlength=len(ids))
        end = np.cumsum(shared)
        alone = n - shared
        prefix = n - needed(n, percent) + 1
        open_ = (alone < prefix) & (shared > 0)
        raw = b"".join(x for x in binaries(tbl, "digests") if x is not None)
        payload = [keys[end[i] - shared[i] : end[i]].tobytes() if open_[i] else None for i in range(len(ids))]
        del dig
        return pa.Table.from_batches([batch(_SETS, [None if x == NULL_ID else int(x) for x in ids], n, [raw[16 * i : 16 * i + 16] for i in range(len(ids))], alone, prefix, payload)])

    return lean_group(run)


_POST = pa.schema([("key", pa.int64()), ("cid", pa.int64()), ("n", pa.int64()), ("pos", pa.int64())])


def _postings(batches):
    for b in batches:
        cid, n, own, prefix = (b.column(i).to_numpy() for i in range(4))
        keys, size = [], []
        for x, o, p in zip(b.column(4).to_pylist(), own, prefix, strict=True):
            keys.append(np.frombuffer(x, np.int64)[: p - o])
            size.append(len(keys[-1]))
        if keys:
            at = np.concatenate([np.arange(s) for s in size])
            yield batch(_POST, np.concatenate(keys), np.repeat(cid, size), np.repeat(n, size), np.repeat(own, size) + at)


_LINK = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("linked", pa.bool_())])


def suffix_bound(x: np.ndarray, y: np.ndarray) -> int:
    """Most keys that two key arrays can share, judged by halves about a middle key."""
    if not len(x) or not len(y):
        return 0
    mid = x[len(x) // 2]
    xl, yl = int((x < mid).sum()), int((y < mid).sum())
    return min(xl, yl) + min(len(x) - xl, len(y) - yl)


def linked(n: int, m: int, x: np.ndarray, y: np.ndarray, percent: int) -> bool:
    """Whether two sets link, of sizes ``n`` and ``m`` with the shared keys ``x`` and ``y``: length, suffix and positional filters, then the overlap."""
    least = -(-percent * (n + m) // (100 + percent))
    if needed(max(n, m), percent) > min(n, m) or suffix_bound(x, y) < least:
        return False
    px, py = n - needed(n, percent) + 1 - (n - len(x)), m - needed(m, percent) + 1 - (m - len(y))
    _, i, j = np.intersect1d(x[:px], y[:py], assume_unique=True, return_indices=True)
    # positional filter: own keys come first, so place i of the shared ones leaves len(x) - i
    if not len(i) or min(len(x) - i.min(), len(y) - j.min()) < least:
        return False
    both = len(np.intersect1d(x, y, assume_unique=True))
    return 100 * both >= percent * (n + m - both)


def _verify(percent: int):
    def run(batches):
        for b in batches:
            rows = zip(*(b.column(i).to_pylist() for i in range(2, 6)), strict=True)
            yield batch(_LINK, b.column(0), b.column(1), [linked(n, m, np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64), percent) for n, m, x, y in rows])

    return lean(run)


_TILE = 512  # documents on a side of a block of pairs
_FEW = 20_000  # candidate pairs of a block that are verified one by one; more, by one product over all their keys


def _overlaps(a: list[np.ndarray], b: list[np.ndarray], step: int = 4096) -> np.ndarray:
    """Sizes of all intersections, by products of 0/1 matrices over the keys that both sides have."""
    ka, kb = np.concatenate(a), np.concatenate(b)
    keys = np.intersect1d(ka, kb)
    ra, rb = np.repeat(np.arange(len(a)), [len(x) for x in a]), np.repeat(np.arange(len(b)), [len(x) for x in b])
    out = np.zeros((len(a), len(b)), np.float32)
    for at in range(0, len(keys), step):
        some = keys[at : at + step]
        sides = []
        for k, r, n in ((ka, ra, len(a)), (kb, rb, len(b))):
            i = np.minimum(np.searchsorted(some, k), len(some) - 1)
            hit = some[i] == k
            m = np.zeros((n, len(some)), np.float32)
            m[r[hit], i[hit]] = 1
            sides.append(m)
        out += sides[0] @ sides[1].T
    return out.astype(np.int64)


def _block_links(percent: int):
    """Links between documents of different labels in each block of a hub: one for each (document, label)."""

    def run(key: tuple[pa.Scalar, ...], tbl: pa.Table) -> pa.Table:
        d = tbl.select(["hub", "ta", "tb", "cid", "n", "n_first", "label", "in_a", "in_b"]).to_pandas()
        sets = [np.frombuffer(x, np.uint64) for x in binaries(tbl, "shared")]
        first = [x[:k] for x, k in zip(sets, d.n_first, strict=True)]
        hubs = [frozenset(x) for x in binaries(tbl, "hubs")]
        out = []
        for (hub, _, _), g in d.groupby(["hub", "ta", "tb"], sort=False):
            a, b = g.index[g.in_a], g.index[g.in_b]
            if not len(a) or not len(b):
                continue
            n, m = d.n.values[a][:, None], d.n.values[b][None, :]
            la, lb = d.label.values[a], d.label.values[b]
            want = (la[:, None] != lb[None, :]) & (np.minimum(n, m) * 100 >= np.maximum(n, m) * percent)
            rows, cols = np.flatnonzero(want.any(1)), np.flatnonzero(want.any(0))
            if not len(rows):
                continue
            w = np.ix_(rows, cols)
            maybe = want[w] & (_overlaps([first[a[i]] for i in rows], [first[b[j]] for j in cols]) > 0)
            many = maybe.sum() > _FEW
            if many:
                rows, cols = rows[maybe.any(1)], cols[maybe.any(0)]
                both = _overlaps([sets[a[i]] for i in rows], [sets[b[j]] for j in cols])
                maybe = want[np.ix_(rows, cols)] & (100 * both >= percent * (n[rows] + m[:, cols] - both))
            links = {}
            for i, j in zip(*(c[k] for c, k in zip((rows, cols), np.nonzero(maybe), strict=True)), strict=True):
                x, y = a[i], b[j]
                if (x, lb[j]) not in links and min(hubs[x] & hubs[y]) == hub and (many or linked(int(d.n.values[x]), int(d.n.values[y]), sets[x], sets[y], percent)):
                    links[x, lb[j]] = (int(d.cid.values[x]), int(d.cid.values[y]))
            out += links.values()
        return pa.Table.from_batches([batch(_LINK, [x for x, _ in out], [y for _, y in out], [True] * len(out))] if out else [], schema=_LINK)

    return lean_group(run)


def _hub_links(members: DataFrame, slim: DataFrame, percent: int) -> DataFrame:
    """members(hub, cid, label) -> links between different labels of a hub.

    The members of a hub's commonest label need no pairs among themselves; the
    others meet them and each other in blocks of bounded size.  Small hubs share
    tasks, about 64 a task.
    """
    by = members.groupBy("hub", "label").agg(F.count(F.lit(1)).alias("c"))
    main = by.groupBy("hub").agg(F.max(F.struct("c", "label")).alias("main"), F.sum("c").alias("total")).where("main.c < total")
    tiles = lambda c: F.ceil(c / F.lit(_TILE))
    main = main.select("hub", F.col("main.label").alias("main"), tiles(F.col("main.c")).alias("tm"), tiles(F.col("total") - F.col("main.c")).alias("to"), F.col("total") <= _TILE)
    main = checkpointed(main.toDF("hub", "main", "tm", "to", "small"))
    parts = max(1, main.where("small").count() // 64)
    m = members.join(main, "hub").withColumn("other", F.col("label") != F.col("main"))
    m = m.withColumn("tile", F.pmod(F.xxhash64("cid"), F.when(F.col("other"), F.col("to")).otherwise(F.col("tm"))))
    first = lambda x, y: F.struct(x.cast("long").alias("ta"), y.cast("long").alias("tb"), F.lit(True).alias("in_a"), F.lit(False).alias("in_b"))
    second = lambda x, y: F.struct(x.cast("long").alias("ta"), y.cast("long").alias("tb"), F.lit(False).alias("in_a"), F.lit(True).alias("in_b"))
    # tiles of others are 0..to-1, those of the main label to..to+tm-1; a block joins an other tile with a tile from it on
    t = F.col("tile")
    as_a = F.transform(F.sequence(t, F.col("to") + F.col("tm") - 1), lambda k: first(t, k))
    as_b = F.transform(F.sequence(F.lit(0).cast("long"), t), lambda k: second(k, t))
    as_main = F.transform(F.sequence(F.lit(0).cast("long"), F.col("to") - 1), lambda k: second(k, t + F.col("to")))
    m = m.withColumn("at", F.explode(F.when(F.col("other"), F.concat(as_a, as_b)).otherwise(as_main)))
    bucket = F.when(F.col("small"), F.pmod(F.xxhash64("hub"), F.lit(parts))).otherwise(F.xxhash64("hub", "at.ta", "at.tb"))
    own = members.join(main.select("hub"), "hub", "left_semi").groupBy("cid").agg(F.collect_set("hub").alias("hubs"))  # no more than keys in a prefix
    m = m.select("hub", "cid", "label", bucket.alias("bucket"), "at.*").join(slim.join(own, "cid"), "cid")
    return m.groupBy("bucket").applyInArrow(_block_links(percent), ddl(_LINK))


def shingle_sets(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, set size, digest of the set, and for rows that may link the shared shingles, rarest first."""
    bits = range_bits(docs.sparkSession)
    packed = plain(docs, id=id_col, text=text_col).select(F.col("id").cast("long"), F.col("text").cast("string")).mapInArrow(_pack(bits, k), ddl(_PACKED))
    shared = packed.groupBy("grp").applyInArrow(_share(bits), ddl(_SHARED))
    return shared.groupBy("block").applyInArrow(_order(percent), ddl(_SETS))


def ngram_components(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of ``docs``: doc_id, n_shingles, component_id (smallest id reachable by links)."""
    sets = stored(shingle_sets(docs, k, percent, id_col, text_col))
    classes = sets.where("n > 0 AND doc_id IS NOT NULL").groupBy("digest").agg(F.min("doc_id").alias("cid"))
    reps = stored(sets.where("shared IS NOT NULL").dropDuplicates(["digest"]).join(classes, "digest").select("cid", "n", "n_own", "n_prefix", "shared"))
    posts = stored(reps.mapInArrow(_postings, ddl(_POST)))
    slim = reps.select("cid", "n", (F.col("n_prefix") - F.col("n_own")).alias("n_first"), "shared")

    def verified(pairs: DataFrame) -> DataFrame:
        left, right = (slim.select(F.col("cid").alias(c), F.col("n").alias(f"n_{c}"), F.col("shared").alias(f"s_{c}")) for c in "ab")
        both = pairs.join(left, "a").join(right, "b").select("a", "b", "n_a", "n_b", "s_a", "s_b")
        return both.mapInArrow(_verify(percent), ddl(_LINK))

    fits = lambda x, y: F.least(x, y) * 100 >= F.greatest(x, y) * percent
    pivot = posts.groupBy("key").agg(F.min(F.struct("cid", "n")).alias("p"), F.count(F.lit(1)).alias("c")).where("c > 1")
    star = posts.join(pivot, "key").where((F.col("cid") != F.col("p.cid")) & fits(F.col("n"), F.col("p.n"))).select(F.col("p.cid").alias("a"), F.col("cid").alias("b")).distinct()
    tried = checkpointed(verified(star))
    label = connected_components(tried.where("linked").select("a", "b"))

    # what is left: pairs of different components that share a prefix key.  Lists with the same
    # smallest member form a hub, so a pair is met once a hub and not once a list
    hubs = posts.join(pivot, "key").where(F.col("cid") != F.col("p.cid")).select(F.col("p.cid").alias("hub"), "cid").distinct()
    hubs = hubs.join(label.withColumnRenamed("node", "cid"), "cid", "left").withColumn("label", F.coalesce("label", "cid"))
    rest = checkpointed(_hub_links(checkpointed(hubs), slim, percent))
    label = connected_components(tried.where("linked").select("a", "b").union(rest.select("a", "b")))

    found = classes.join(label.withColumnRenamed("node", "cid"), "cid", "left").select("digest", F.coalesce("label", "cid").alias("component"))
    return sets.select("doc_id", "n", "digest").join(found, "digest", "left").select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).alias("component_id"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", **kw) -> DataFrame:
    """Drop all documents of a component but the one with the smallest id; rows of ``docs`` as they were.

    Rows with a null id stay.  Of repeated rows with the kept id all stay."""
    gone = ngram_components(docs, id_col=id_col, **kw).where("doc_id <> component_id").select(F.col("doc_id").alias("gone")).distinct()
    return docs.join(gone, docs[f"`{id_col}`"] == F.col("gone"), "left_anti").select(*(docs[f"`{c}`"] for c in docs.columns))
