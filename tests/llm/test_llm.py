"""Operators against brute force on small tables, with the odd cases: nulls, empty, repeats, ties, extra columns."""

import random
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from vicicorr.llm import common, curve_ann, langid, lattice_lm, line_dedup, merge_dropout, ngram_join, packing, quality, substring_dedup, toxicity


def docs(spark, rows, extra=False):
    kind = "doc_id long, text string" + (", n long, cid long, h string" if extra else "")
    return spark.createDataFrame([(*r, 1, 2, "x") if extra else r for r in rows], kind)


def words(rng, n, vocab=3000):
    return [f"w{rng.randrange(vocab)}" for _ in range(n)]


@pytest.fixture(scope="module")
def texts():
    rng = random.Random(3)
    out, base = [(0, None), (1, ""), (2, "one two"), (3, "One TWO"), (4, " \n\t "), (None, "one two")], words(rng, 120)
    for i in range(5, 60):
        w = list(base) if i % 2 else words(rng, 80)
        for _ in range(rng.randrange(9)):
            w[rng.randrange(len(w))] = "edit"
        out.append((i, " ".join(w)))
    return [*out, out[10]]


def brute_components(rows):
    sets = {}
    for d, t in rows:
        w = (t or "").encode().lower().split()
        sets[d] = {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()
    ids = [d for d in sets if d is not None]
    up = {d: d for d in ids}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in ids:
        for b in ids:
            if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
                x, y = root(a), root(b)
                up[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), root(d)) for d in ids}


@pytest.mark.parametrize(("tile", "few"), [(2, 10), (1024, 20_000), (1024, 0)])
def test_ngram_join(spark, texts, tile, few, monkeypatch):
    monkeypatch.setattr(ngram_join, "_TILE", tile)
    monkeypatch.setattr(ngram_join, "_FEW", few)
    got = ngram_join.ngram_components(docs(spark, texts, True)).collect()
    assert len(got) == len(texts)
    want = brute_components(texts)
    assert all((r.n_shingles, r.component_id) == want[r.doc_id] for r in got if r.doc_id is not None)
    assert ngram_join.ngram_components(docs(spark, [])).count() == 0
    kept = ngram_join.keep_one(docs(spark, texts, True).withColumnRenamed("doc_id", "key").withColumn("doc_id", F.lit("z")), id_col="key")
    assert {r.key for r in kept.collect()} == {want[d][1] for d in want if d is not None} | {None}


def test_line_dedup(spark):
    rows = [(1, "a long line here\nshort\nonly once in one"), (2, " A LONG line here \nshort\r\n"), (3, None), (4, "a long line here\na long line here"), (None, "a long line here"), (2, "x")]
    out = line_dedup.line_dedup(docs(spark, rows)).collect()
    by = {(r.doc_id, r.n_lines): (r.n_dropped, r.text) for r in out}
    assert len(out) == len(rows)
    assert by[1, 3] == (0, rows[0][1]) and by[None, 1] == (0, "a long line here")
    assert by[4, 2] == (2, "") and by[3, 1] == (0, "")
    # rows that repeat an id count as one document, and each loses the lines of its own text only
    assert by[2, 3] == (1, "short\r\n") and by[2, 1] == (0, "x")


def test_line_dedup_keeps_what_a_repeated_id_holds_alone(spark):
    rows = [(1, "a line in both\nfirst"), (2, "a line in both\nsecond"), (2, "a line of its own\na line in both"), (2, "a line in both\nsecond")]
    clash = docs(spark, rows).selectExpr("*", "1 AS __id", "2 AS `__drops`", "3 AS n_lines", "'x' AS h1")
    out = line_dedup.line_dedup(clash)
    assert sorted(out.columns) == sorted([*clash.columns, "n_dropped"])
    assert sorted(r.text for r in out.collect()) == ["a line in both\nfirst", "a line of its own", "second", "second"]
    assert line_dedup.line_dedup(docs(spark, [])).count() == 0


def test_substring(spark):
    rng = random.Random(5)
    p = words(rng, 80)
    fuzzy = [w if i % 17 else "zz" for i, w in enumerate(p)]
    rows = [(1, " ".join(words(rng, 60) + p)), (2, " ".join(p + words(rng, 60))), (3, " ".join(words(rng, 40) + fuzzy)), (4, None), (5, " ".join(words(rng, 90)))]
    out = {r.doc_id: r for r in substring_dedup.substring_dedup(docs(spark, rows)).collect()}
    assert out[1].n_dup_words == 0 and out[5].n_dup_words == 0 and out[4].text == ""
    clash = docs(spark, [*rows, (None, rows[0][1]), (2, rows[1][1])], True).selectExpr("*", "1 AS n_words", "2 AS __doc", "3 AS __chains")
    again = substring_dedup.substring_dedup(clash)
    assert sorted(again.columns) == sorted([*clash.columns, "n_dup_words", "spans"]) and again.where("doc_id = 2 AND n_dup_words = 80").count() == 2
    assert substring_dedup.substring_dedup(docs(spark, [])).count() == 0
    assert out[2].n_dup_words == 80 and out[3].n_dup_words >= 75


def test_chain_is_best_on_small_cases():
    rng = random.Random(2)
    for _ in range(50):
        seg = [(rng.randrange(30), rng.randrange(30), rng.randrange(1, 5)) for _ in range(6)]
        for c in substring_dedup.chain(seg):
            assert all(a[0] + a[2] <= b[0] and a[1] + a[2] <= b[1] for a, b in zip(c, c[1:], strict=False))


def test_chain_looks_past_a_predecessor_too_far_off():
    far, one, two = (0, 0, 200), (240, 240, 49), (290, 289, 49)
    assert [one, two] in substring_dedup.chain([far, one, two])
    rng = random.Random(7)
    for _ in range(200):
        seg = sorted({(rng.randrange(120), rng.randrange(120), rng.randrange(1, 20)) for _ in range(12)})
        best, cost = [], substring_dedup.GAP_COST
        for d, p, n in seg:
            gaps = [(d - a - m, p - b - m, s) for (a, b, m), s in zip(seg, best, strict=False)]
            best.append(n + max([s - cost * (x + y) for x, y, s in gaps if 0 <= x <= substring_dedup.MAX_GAP and 0 <= y <= substring_dedup.MAX_GAP] + [0]))
        got = substring_dedup.chain(seg)[0]
        value = sum(x[2] for x in got) - cost * sum(y[0] - x[0] - x[2] + y[1] - x[1] - x[2] for x, y in zip(got, got[1:], strict=False))
        assert value == pytest.approx(max(best))


def test_substring_finds_the_holder_behind_changing_partners(spark):
    rng = random.Random(8)
    p = words(rng, 120)
    # documents 1-6 and 20-25 each hold a different 32 of the 120 words that 10 and 30 hold whole
    rows = [(base + i, " ".join(words(rng, 30) + p[20 * i : 20 * i + 32] + words(rng, 30))) for base in (1, 20) for i in range(6)]
    rows += [(d, " ".join(words(rng, 40) + p + words(rng, 40))) for d in (10, 30)]
    out = {r.doc_id: r for r in substring_dedup.substring_dedup(docs(spark, rows)).collect()}
    assert out[30].n_dup_words == 120 and all(r.n_dup_words == 0 for r in out.values() if r.doc_id < 30)


def test_packing(spark):
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    rng = random.Random(1)
    rows = [(i, " ".join(words(rng, rng.randrange(1, 400)))) for i in range(8, 60)] + [(60, None), (61, ""), (7, "again"), (7, "again")]
    rows += [(100 + i, f"ab{chr(i)}cd {chr(i)} {chr(i)}x") for i in range(256)]
    out = packing.pack(docs(spark, rows), path, window=256).collect()
    tok = Tokenizer.from_file(path)
    total = sum(len(tok.encode(t or "", add_special_tokens=False).ids) + 1 for _, t in rows)
    assert sum(r.length for r in out) == total
    ids = {d: np.array(tok.encode(t or "", add_special_tokens=False).ids + [2], "<u4") for d, t in rows}
    for r in out:
        assert zlib.crc32(ids[r.doc_id][r.start : r.start + r.length].tobytes()) == r.ids_crc32 and r.doc_tokens == len(ids[r.doc_id])
    assert packing.pack(docs(spark, []), path).count() == 0
    seqs = {}
    for r in out:
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for s in seqs.values():
        at = 0
        for off, n in sorted(s):
            assert off == at
            at += n
        assert at == 256 or at & (at - 1) == 0


def test_bin_slack_fill_is_best():
    rng = random.Random(4)
    for _ in range(40):
        counts = {rng.randrange(2, 40): rng.randrange(1, 4) for _ in range(5)}
        room, sums = 60, {0}
        for n, c in counts.items():
            sums = {s + n * k for s in sums for k in range(c + 1)}
        used = packing.best_fill(counts, room)
        assert sum(n * c for n, c in used.items()) == max(s for s in sums if s <= room)
        assert all(c <= counts[n] for n, c in used.items())


def test_lattice_sums_all_segmentations():
    pieces = ["▁", "a", "b", "ab", "▁a", "ba"] + [f"<0x{i:02X}>" for i in range(256)]
    m = lattice_lm.Lattice(pieces, np.log(np.full(len(pieces), 1 / len(pieces))), np.arange(6, 262), 0.0)
    (_, x) = next(lattice_lm.by_length([b"aba"]))

    def ways(t):
        return 1.0 if not t else sum(ways(t[len(p) :]) / len(pieces) for p in pieces[:6] if t.startswith(p))

    assert m.forward(x)[2][0, -1] == pytest.approx(np.log(ways("▁aba")))


def test_lm_base(spark):
    rows = [(i, f"the cat {'sat' * (i % 3)} on") for i in range(40)] + [(40, None)]
    out = lattice_lm.lm_scores(docs(spark, rows), public_tokenizers.path("piece_bpe_32k.model")).collect()
    held = lambda d: zlib.crc32(str(d).encode()) % 10 == 0
    train = [w for d, t in rows if not held(d) for w in (t or "").split() + ["\n"]]
    r = next(x for x in out if x.doc_id == 3)
    want = sum(np.log10((train.count(w) + 0.1) / (len(train) + 0.1 * (len(set(train)) + 1))) for w in rows[3][1].split() + ["\n"])
    assert r.base_score == pytest.approx(want) and r.train_tokens == len(train) and np.isfinite([x.score for x in out]).all()


def test_dropout_is_lossless_and_seeded():
    path = public_tokenizers.path("piece_bpe_32k.model")
    m = merge_dropout.MergeDropout(path, 0.2)
    odd = ["", " a  b\n\nc ", "▁x ▁▁", "naïve 日本 😀\x00", "the cat sat on the mat " * 20]
    for v in range(2):
        assert [m.decode(x.tolist()) for x in m.encode(odd, [v] * len(odd))] == odd
    assert m.encode(odd[4:], [0])[0].tolist() != m.encode(odd[4:], [1])[0].tolist()
    plain = merge_dropout.MergeDropout(path, 0.0)
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    assert plain.encode([" hello world"], [0])[0].tolist() == sp.encode("hello world")


def test_nearest(spark):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((300, 16))
    x[100:180] = x[100]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(400, None), (500, [0.0] * 16), (600, [float("nan")] * 16), (700, [1.0])]
    out = curve_ann.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect()
    got = {(r.query_id, r.rank): r.vec_id for r in out}
    for q in (0, 100, 200):
        d = np.sqrt(((x - x[q]) ** 2).sum(1))
        want = [i for i in np.lexsort((np.arange(300), d.round(12))) if i != q][:10]
        assert [got[q, k] for k in range(1, 11)] == want


@pytest.mark.parametrize("groups", [0, 40])
def test_curve_windows_alone_reach_the_recall(spark, groups):
    rng = np.random.default_rng(6)
    x = rng.standard_normal((3000, 24))
    if groups:
        x = rng.standard_normal((groups, 24))[rng.integers(0, groups, 3000)] + x / 8
    rows = spark.createDataFrame([(i, v.tolist(), 1, 2) for i, v in enumerate(x)] + [(5, x[5].tolist(), 3, 4)], "vec_id long, embedding array<double>, id long, a long")
    out = curve_ann.nearest(rows, exact=False).collect()
    got, want = {(r.query_id, r.vec_id) for r in out}, set()
    for q in range(0, 3000, 100):
        d = ((x - x[q]) ** 2).sum(1)
        d[q] = np.inf
        want |= {(q, int(i)) for i in np.argsort(d)[:10]}
    assert len(got & want) >= 0.9 * len(want)
    assert curve_ann.nearest(rows.limit(0)).count() == 0


def test_langid(spark):
    rows = [(i, ("der hund und die katze " if i % 2 else "the dog and the cat ") * 3, "de" if i % 2 else "en") for i in range(80)] + [(81, None, "en"), (82, "123 !", None)]
    out = langid.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()
    assert all(r.lang_pred == ("und" if r.doc_id > 80 else "de" if r.doc_id % 2 else "en") for r in out)


def test_langid_scores_match_a_plain_count():
    rng, texts = random.Random(4), ["", "a", "der hund", "x" * 700, "the dog and the cat " * 40]
    model = np.log(np.random.default_rng(2).dirichlet(np.ones(langid.BUCKETS), 3).T).astype(np.float32)
    prior = np.log(np.array([0.5, 0.3, 0.2]))
    texts += [" ".join(words(rng, 30)) for _ in range(40)]
    for t, got in zip(texts, langid.sparse_scores(texts, model, prior), strict=True):
        want = prior.copy()
        for h in langid.ngram_buckets(t):
            for b in h.tolist():
                want += model[b]
        assert got == pytest.approx(want, rel=1e-6)


def test_langid_learns_the_commonest_languages(spark):
    rows = [(i, f"{'abc' if i % 5 else 'xyz'} text", "aa" if i % 5 else "bb") for i in range(50)] + [(None, "abc", "aa"), (3, "abc", "aa")]
    d = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, lang string, score int")
    assert {r.lang_pred for r in langid.identify(d, most_langs=1).collect()} == {"aa"}
    assert langid.identify(d.limit(0)).count() == 0


def test_viterbi_is_best_of_all_labellings():
    rng = np.random.default_rng(3)
    for _ in range(20):
        f = quality.LineField(rng.standard_normal(9), rng.standard_normal((2, 2)))
        x = rng.integers(0, 2, (6, 9)).astype(float)
        value = lambda y: float((x @ f.w) @ y + sum(f.t[a, b] for a, b in zip(y, y[1:], strict=False)))  # noqa: B023, E731
        every = [[k >> i & 1 for i in range(6)] for k in range(64)]
        assert value(f.decode(x).tolist()) == pytest.approx(max(map(value, every)))


def test_quality_tells_boilerplate(spark):
    rng, rows, labels = random.Random(12), [], []
    for i in range(120):
        lines = [" ".join(words(rng, 12)) + "." for _ in range(8)]
        if i % 2:
            lines = [lines[0]] + [rng.choice(["## $$ || && %%", "BUY NOW HERE FAST", "<< >> ## **"]) for _ in range(12)]
        rows.append((i, "\n".join(lines)))
        labels.append((i, 1 - i % 2))
    d = docs(spark, [*rows, (500, None), (None, ""), (3, rows[3][1])], True)
    lab = spark.createDataFrame([*labels, (None, 1), (7, None)], "doc_id long, quality int")
    out = {r.doc_id: r for r in quality.quality(d, lab).collect()}
    assert len(out) == 122 and not out[500].kept and out[500].base_failed
    assert sum(out[i].kept == (i % 2 == 0) for i in range(120)) >= 118
    assert quality.quality(d.limit(0), lab).count() == 0 and quality.quality(d, lab.limit(0)).count() == 123


def test_dropout_digest(spark):
    path = public_tokenizers.path("piece_bpe_32k.model")
    rows = [(1, "the cat"), (1, "the cat"), (2, None), (None, ""), (3, "naïve\x00 日本 " * 3000)]
    out = merge_dropout.encode_digest(docs(spark, rows, True), path).collect()
    assert len(out) == 5 and all(r.lossless for r in out) and len({r.ids_crc32 for r in out if r.doc_id == 1}) == 1
    back = merge_dropout.decode(merge_dropout.encode(docs(spark, rows), path), path).collect()
    assert sorted(r.text for r in back) == sorted(t or "" for _, t in rows)
    assert merge_dropout.encode_digest(docs(spark, []), path).count() == 0


def test_quality_measures():
    assert quality.base_measures(None) == (0, 0, 0, 0, 0)
    assert quality.base_measures("a b c d e f\na b c d e f\n\n#") == (13, 13, 1, 1, 12)
    x = np.array([[1, 0, 0, 0, 0, 0, 0, 0, 0], [1, 1, 1, 0, 0, 0, 0, 0, 0.0]])
    assert quality.LineField().decode(x).tolist() == [0, 1]


def test_toxicity(spark):
    rng = random.Random(9)
    rows, labels = [], []
    for i in range(300):
        w, bad = words(rng, 60, 300), i % 3 == 0
        for _ in range(6 * bad):
            w.insert(rng.randrange(60), rng.choice(["vile", "scum!", "Rot"]))
        rows.append((i, " ".join(w)))
        labels.append((i, int(bad)))
    d, t = docs(spark, [*rows, (999, None), (None, "")]), spark.createDataFrame(labels, "doc_id long, toxic int")
    out = toxicity.toxicity(d, t).collect()
    held = [r for r in out if r.held_out and r.doc_id is not None and r.doc_id < 300]
    assert np.mean([r.predicted == (r.doc_id % 3 == 0) for r in held]) > 0.95
    assert toxicity.toxicity(docs(spark, [(1, "a")]), t.limit(0)).first().predicted == 0


def test_helpers():
    k = np.sort(np.random.default_rng(0).integers(0, 2**63, 500).astype(np.uint64))
    assert sum(b - a for _, a, b in common.ranges_of(k, 6)) == 500


def test_window_hashes_tell_runs_apart():
    """Equal runs of words have equal hashes wherever they stand, others differ; in a score of joins, not one step a word."""
    from vicicorr.llm import common

    words = np.random.default_rng(2).integers(0, 3, 4000).astype(np.uint64)
    words[3000:3200] = words[100:300]
    for k in (1, 5, 8, 9, 16, 33, 50):
        h = common.window_hashes(words, k)
        runs = [words[i : i + k].tobytes() for i in range(len(words) - k + 1)]
        assert len(h) == len(runs) and len(set(zip(h.tolist(), runs, strict=True))) == len(set(h.tolist())) == len(set(runs))
    assert len(common.window_hashes(words[:20], 50)) == 1
    joins, join = [], common._joined
    common._joined = lambda *a: joins.append(1) or join(*a)
    try:
        common.window_hashes(words, 50)
    finally:
        common._joined = join
    assert len(joins) <= 20


def test_windows_travel_in_large_batches(monkeypatch):
    from vicicorr.llm import substring_dedup as sd

    rows = [(d, np.arange(3), np.arange(3) + 10 * d) for d in range(50)]
    assert [b.num_rows for b in sd._in_batches(iter(rows))] == [150]
    monkeypatch.setattr(sd, "BATCH_ROWS", 40)
    got = list(sd._in_batches(iter(rows)))
    assert len(got) == 4 and [x for b in got for x in b.column(2).to_pylist()] == [x for _, _, key in rows for x in key.tolist()]
    assert list(sd._in_batches(iter([]))) == []


def test_substring_finds_fuzzy_passages_behind_changing_partners(spark):
    rng = random.Random(41)
    p = words(rng, 120, 10**6)
    mine = [w if i % 15 != 14 else f"x{i}" for i, w in enumerate(p)]
    # 1-6 and 20-25 each hold 34 of the 120 words, so each seed's first and last earlier holder is one of them; only 10 holds all
    rows = [(base + i, " ".join(words(rng, 60, 10**6) + p[17 * i : 17 * i + 34] + words(rng, 60, 10**6))) for base in (1, 20) for i in range(6)]
    rows += [(d, " ".join(words(rng, 50, 10**6) + part + words(rng, 50, 10**6))) for d, part in ((10, p), (30, mine))]
    out = {r.doc_id: r for r in substring_dedup.substring_dedup(docs(spark, rows)).collect()}
    assert out[30].n_dup_words >= 110 and all(r.n_dup_words == 0 for r in out.values() if r.doc_id < 30)
