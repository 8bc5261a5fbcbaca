"""Pairs of documents by rare runs of words, against brute force."""

import numpy as np
import pyarrow as pa
import pyarrow.compute

from vicicorr.sources import graphs
from vicicorr.sources.shingles import _packs, _pairs, _Words, run_hashes


def test_shingle_graph_counts_documents_not_rows(spark, tmp_path):
    """A run held by 20 documents in 21 rows links them; one held by 21 documents doesn't; null ids count but link nothing."""
    rows = [(i, "One two, three FOUR") for i in range(20)] + [(3, "x one two three four")]
    rows += [(100 + i, "five six seven eight nine") for i in range(21)]
    rows += [(None, "red green blue black"), (200, "Red green 7 blue black"), (-(2**62), "red green blue black white"), (300, None), (301, ""), (302, "red green blue")]
    spark.createDataFrame([(i, t, "en") for i, t in rows], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(0, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = {(r.src, r.dst) for r in graphs.doc_shingle(spark, str(tmp_path)).edges.collect()}
    assert got == {(i, j) for i in range(20) for j in range(i + 1, 20)} | {(-(2**62), 200)}


def test_packed_runs_take_few_bytes():
    """A run travels in under 13 bytes even in a small pack, and ranges give the pairs of brute force."""
    rng, words = np.random.default_rng(0), _Words()
    docs = [(int(i), " ".join(chr(97 + w % 26) * (1 + w // 26) for w in rng.integers(0, 60, 400))) for i in rng.permutation(300)]
    docs += [(1000 + i, docs[i][1]) for i in range(30)]
    batch = pa.RecordBatch.from_arrays([pa.array([i for i, _ in docs]), pa.array([t for _, t in docs])], names=["doc", "text"])
    packs = list(_packs(4, 8)([batch]))
    runs = {i: {tuple(t.split()[j : j + 4]) for j in range(397)} for i, t in docs}
    n = sum(len(run_hashes(t.encode(), 4, words)) for _, t in docs)
    assert n == sum(map(len, runs.values())) and sum(b.nbytes for b in packs) < 13 * n
    tbl = pa.Table.from_batches(packs)
    got = set()
    for g in set(tbl.column("grp").to_pylist()):
        found = _pairs(3, 8)((pa.scalar(g),), tbl.filter(pa.compute.equal(tbl.column("grp"), g)))
        got |= set(zip(found.column("x").to_pylist(), found.column("y").to_pylist(), strict=True))
    holders = {}
    for i, s in runs.items():
        for r in s:
            holders.setdefault(r, []).append(i)
    assert got == {(min(x, y), max(x, y)) for h in holders.values() if len(h) <= 3 for x in h for y in h if x != y}


def test_shared_runs_count_however_many_hold_them(spark, tmp_path):
    """Runs held by 21 and by 1,500 documents link them all, also where ids repeat or are null, as real_positive's graph takes them; its SQL has no cut."""
    from vicicorr import experiments  # noqa: F401
    from vicicorr.queries import SQL

    rows = [(i, "One two, three FOUR five") for i in range(21)] + [(3, "x one two three four"), (None, "one two three four")]
    rows += [(100 + i, "five six seven eight nine") for i in range(1500)]
    rows += [(-(2**62), "red green blue black white"), (90, "Red green 7 blue black"), (None, "nine ten eleven twelve"), (91, "nine ten eleven twelve"), (92, None), (93, "one two three")]
    spark.createDataFrame([(i, t, "en") for i, t in rows], "doc_id long, text string, lang string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(0, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = {(r.src, r.dst) for r in graphs.BUILDERS["doc_shingle_all"](spark, str(tmp_path)).edges.collect()}
    assert got == {(i, j) for i in range(21) for j in range(i + 1, 21)} | {(i, j) for i in range(100, 1600) for j in range(i + 1, 1600)} | {(-(2**62), 90)}
    assert "BETWEEN 2 AND 20" not in SQL["real_positive"] and "BETWEEN 2 AND 20" in SQL["real_negative"]
