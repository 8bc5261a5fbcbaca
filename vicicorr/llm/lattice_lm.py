"""Language-model scoring: marginal likelihood over a subword lattice.

A text is the stream of its words, each begun by the word mark, then an end.  A
word's probability is the sum over all its segmentations in pieces of an existing
vocabulary, by forward recursion in log space, and over one more arc that spans
the word with its discounted share of the training words; the discount is the
weight of the pieces.  The vocabulary's own order of scores is the starting point,
and rounds of expectation maximisation over all distinct training words (no
sample) set the piece probabilities.  Words are scored once each, not once an
occurrence: counts and scores sit in one table of distinct words, the most
frequent of which (a bounded number) go to every task, while the others are
looked up by a join.

Null text is empty: it has the end token alone.  Rows with null or repeated ids
are scored row by row.  Words are told apart by 64-bit hashes.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import as_bytes, batch, fold, stored
from .ngram_join import ddl

MARK, LONGEST = "▁", 16
TOP_WORDS = 100_000
DISCOUNT = 0.75
_MUL = np.uint64(0x9E3779B97F4A7C15)
_COUNTS = pa.schema([("h", pa.int64()), ("word", pa.binary()), ("c", pa.int64())])


def _hash(word: bytes) -> int:
    return xxhash.xxh3_64_intdigest(word) - (1 << 63)


def _count(batches, most: int = 200_000):
    """Words of all rows with their training counts (0 for words met in held-out rows only)."""
    sums: dict[bytes, int] = {}

    def flush():
        words = list(sums)
        for at in range(0, len(words), 50_000):
            some = words[at : at + 50_000]
            yield batch(_COUNTS, [_hash(w) for w in some], some, [sums[w] for w in some])
        sums.clear()

    for b in batches:
        for held, text in zip(b.column(0).to_pylist(), as_bytes(b.column(1)), strict=True):
            words = text.lower().split() if text else ()
            if held:
                for w in words:
                    sums.setdefault(w, 0)
            else:
                for w in words:
                    sums[w] = sums.get(w, 0) + 1
            if len(sums) >= most:
                yield from flush()
    yield from flush()


class Lattice:
    """Pieces, their natural log probabilities, and recursions over many words at a time."""

    def __init__(self, pieces: list[str], logp: np.ndarray, byte_ids: np.ndarray, end: float):
        self.pieces, self.logp, self.byte_ids, self.end = pieces, logp, byte_ids, end
        keys = np.array([self.key(np.array([list(map(ord, p))], np.uint64))[0] if 0 < len(p) <= LONGEST else 0 for p in pieces], np.uint64)
        keys[byte_ids] = 0
        self.order = np.argsort(keys, kind="stable")
        self.keys = keys[self.order]

    @staticmethod
    def key(codes: np.ndarray) -> np.ndarray:
        h = np.zeros(len(codes), np.uint64)
        for i in range(codes.shape[1]):
            h = (h + codes[:, i] + np.uint64(1)) * _MUL
            h ^= h >> np.uint64(29)
        return h

    def edges(self, x: np.ndarray) -> list[np.ndarray]:
        """For each length from 1: piece number at each place, -1 for none."""
        h, out = np.zeros(x.shape, np.uint64), []
        for n in range(1, min(LONGEST, x.shape[1]) + 1):
            w = x.shape[1] - n + 1
            h = (h[:, :w] + x[:, n - 1 :] + np.uint64(1)) * _MUL
            h ^= h >> np.uint64(29)
            i = np.minimum(np.searchsorted(self.keys, h), len(self.keys) - 1)
            out.append(np.where(self.keys[i] == h, self.order[i], -1).astype(np.int32))
        return out

    def single(self, x: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Log probability of each character alone; one that is no piece is spelt in bytes."""
        lp = self.logp[ids].copy()
        gone = ids < 0
        if gone.any():
            codes, back = np.unique(x[gone], return_inverse=True)
            spelt = np.array([self.logp[self.byte_ids[list(chr(int(c)).encode("utf-8", "surrogatepass"))]].sum() for c in codes])
            lp[gone] = spelt[back]
        return lp

    def forward(self, x: np.ndarray):
        """(edges, their log probabilities, forward sums) of words of one length, a row each."""
        edges = self.edges(x)
        lp = [self.single(x, edges[0])] + [np.where(e >= 0, self.logp[e], -np.inf) for e in edges[1:]]
        f = np.full((len(x), x.shape[1] + 1), -np.inf)
        f[:, 0] = 0
        with np.errstate(invalid="ignore"):
            for j in range(1, x.shape[1] + 1):
                f[:, j] = np.logaddexp.reduce([f[:, j - n] + lp[n - 1][:, j - n] for n in range(1, min(LONGEST, j) + 1)], axis=0)
        return edges, lp, f

    def expect(self, x: np.ndarray, c: np.ndarray, into: np.ndarray) -> None:
        """Add expected uses of each piece in words ``x`` met ``c`` times."""
        edges, lp, f = self.forward(x)
        n_chars = x.shape[1]
        b = np.full(f.shape, -np.inf)
        b[:, n_chars] = 0
        for j in range(n_chars - 1, -1, -1):
            b[:, j] = np.logaddexp.reduce([lp[n - 1][:, j] + b[:, j + n] for n in range(1, min(LONGEST, n_chars - j) + 1)], axis=0)
        for n, e in enumerate(edges, 1):
            w = n_chars - n + 1
            use = np.exp(f[:, :w] + lp[n - 1] + b[:, n:] - f[:, n_chars :]) * c[:, None]
            got = e >= 0
            np.add.at(into, e[got], use[got]) if got.sum() < 64 else into.__iadd__(np.bincount(e[got], use[got], len(into)))
            if n == 1 and (~got).any():
                for code, u in zip(x[~got], use[~got], strict=True):
                    into[self.byte_ids[list(chr(int(code)).encode("utf-8", "surrogatepass"))]] += u


def by_length(words: list[bytes], most_chars: int = 400_000):
    """Rows of characters, words of one length at a time, the word mark first: (indexes, matrix)."""
    text = [MARK + w.decode("utf-8", "surrogatepass") for w in words]
    size = np.array([len(t) for t in text])
    for n in np.unique(size):
        at = np.flatnonzero(size == n)
        step = max(1, most_chars // int(n))
        for i in range(0, len(at), step):
            some = at[i : i + step]
            yield some, np.frombuffer("".join(text[j] for j in some).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(some), n).astype(np.uint64)


_USES = pa.schema([("piece", pa.int64()), ("uses", pa.float64())])


def _expected(sent):
    def run(batches):
        model = sent.value
        into = np.zeros(len(model.pieces))
        for b in batches:
            for at, x in by_length(b.column(0).to_pylist()):
                model.expect(x, np.ones(len(at)), into)
        at = np.flatnonzero(into)
        yield batch(_USES, at, into[at])

    return run


_SCORED = pa.schema([("h", pa.int64()), ("c", pa.int64()), ("lp", pa.float64())])


def _score_words(sent, total: int, kinds: int):
    """log10 of a word's probability: its own arc, with the discounted training share, beside all its segmentations."""
    spare = DISCOUNT * kinds / total if total else 1.0

    def run(batches):
        model = sent.value
        for b in batches:
            lp = np.empty(b.num_rows)
            for at, x in by_length(b.column(1).to_pylist()):
                lp[at] = model.forward(x)[2][:, -1]
            own = np.maximum(b.column(2).to_numpy() - DISCOUNT, 0) / max(total, 1)
            with np.errstate(divide="ignore"):
                lp = np.logaddexp(np.log(own), np.log(spare) + model.end + lp) / np.log(10)
            yield batch(_SCORED, b.column(0), b.column(2), lp)

    return run


def load_vocabulary(model_path: str) -> tuple[list[str], np.ndarray, np.ndarray]:
    """(pieces, scores, numbers of the 256 byte pieces) of an existing vocabulary; control pieces are blanked."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=model_path)
    n = sp.get_piece_size()
    pieces = ["" if sp.is_control(i) or sp.is_unknown(i) else sp.id_to_piece(i) for i in range(n)]
    byte_ids = np.array([sp.piece_to_id(f"<0x{i:02X}>") for i in range(256)])
    return pieces, np.array([sp.get_score(i) for i in range(n)]), byte_ids


def fit(words: DataFrame, model_path: str, kinds: int, rounds: int = 2, prior: float = 0.1) -> Lattice:
    """Piece and word-end probabilities from all distinct training words, each counted once, as the lattice
    answers for words not met; ``prior`` uses a piece are added in the vocabulary's own proportions."""
    pieces, scores, byte_ids = load_vocabulary(model_path)
    live = np.array([bool(p) for p in pieces])
    rank = np.argsort(np.argsort(-scores, kind="stable"), kind="stable")
    first = np.where(live, 1.0 / (rank + 10.0), 0.0)
    first /= first.sum()
    p, end = first * 0.8, 0.2
    with np.errstate(divide="ignore"):
        for _ in range(rounds):
            sent = words.sparkSession.sparkContext.broadcast(Lattice(pieces, np.log(p), byte_ids, np.log(end)))
            rows = words.where("c > 0").select("word").mapInArrow(_expected(sent), ddl(_USES)).groupBy("piece").agg(F.sum("uses")).collect()  # at most one row a piece
            uses = np.zeros(len(pieces))
            for i, u in rows:
                uses[i] = u
            uses += prior * live.sum() * first
            total = uses.sum() + kinds + 1
            p, end = uses / total, (kinds + 1) / total
        return Lattice(pieces, np.log(p), byte_ids, float(np.log(end)))


_ROWS = pa.schema([("rid", pa.int64()), ("h", pa.int64()), ("tf", pa.int64()), ("info", pa.binary())])
_INFO = np.dtype([("doc", "<i8"), ("null", "<i8"), ("held", "<i8"), ("n", "<i8"), ("known", "<i8"), ("base", "<f8"), ("score", "<f8")])


def _rows(sent):
    """A row for each document with what the frequent words give, and one for each other word of it."""

    def run(batches):
        from pyspark import TaskContext

        part, row = TaskContext.get().partitionId(), 0
        top, c, lp = sent.value
        log_c = np.log10(c + 0.1)
        out: list[tuple] = []

        def flush():
            rids, hs, tfs, infos = zip(*out, strict=True)
            n = [len(h) for h in hs]
            info = [x for i, k in zip(infos, n, strict=True) for x in (i, *([None] * (k - 1)))]
            out.clear()
            return batch(_ROWS, np.repeat(np.array(rids, np.int64), n), np.concatenate(hs), np.concatenate(tfs), info)

        for b in batches:
            for doc, held, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), as_bytes(b.column(2)), strict=True):
                rid = (part << 36) | row
                row += 1
                counts: dict[bytes, int] = {}
                words = text.lower().split() if text else ()
                for w in words:
                    counts[w] = counts.get(w, 0) + 1
                h = np.fromiter(map(_KNOWN.__getitem__, counts), np.int64, len(counts))
                tf = np.fromiter(counts.values(), np.int64, len(counts))
                i = np.minimum(np.searchsorted(top, h), max(len(top) - 1, 0))
                hit = top[i] == h if len(top) else np.zeros(len(h), bool)
                i, t = i[hit], tf[hit]
                info = np.array([(doc or 0, doc is None, held, len(words), t[c[i] > 0].sum(), (t * log_c[i]).sum(), (t * lp[i]).sum())], _INFO).tobytes()
                rest = h[~hit]
                out.append((rid, np.r_[np.int64(rid * 2654435761 % (1 << 62)), rest], np.r_[0, tf[~hit]], info))
                if len(out) >= 256:
                    yield flush()
        if out:
            yield flush()

    return run


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 250_000:
            self.clear()
        self[word] = h = _hash(word)
        return h


_KNOWN = _Hashes()
_OUT = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])


def _finish(n_end: int, total: int, kinds: int):
    end = np.log10(max(n_end, 0.1) / max(total, 1))

    def run(batches):
        for b in batches:
            x = np.frombuffer(b"".join(b.column(0).to_pylist()), _INFO)
            n = x["n"] + 1
            known = x["known"] + b.column(1).to_numpy() + (n_end > 0)
            base = x["base"] + b.column(2).to_numpy() + np.log10(n_end + 0.1) - n * np.log10(total + 0.1 * (kinds + 1))
            yield batch(_OUT, pa.array(x["doc"], mask=x["null"] > 0), x["held"] > 0, n, known, np.full(len(x), total), base, x["score"] + b.column(3).to_numpy() + end)

    return run


def lm_scores(docs: DataFrame, model_path: str, mod: int = 10, rest: int = 0, rounds: int = 2, top_words: int = TOP_WORDS) -> DataFrame:
    """docs(doc_id, text) -> doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score; learns where crc32 of the id modulo ``mod`` is not ``rest``."""
    spark = docs.sparkSession
    held = fold("doc_id", mod) == rest
    n_end = docs.where(~held).count()
    words = stored(docs.select(held, "text").mapInArrow(_count, ddl(_COUNTS)).groupBy("h").agg(F.min("word").alias("word"), F.sum("c").alias("c")))
    total, kinds = words.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count_if(F.col("c") > 0)).first()
    model = fit(words, model_path, kinds, rounds)
    scored = stored(words.select("h", "word", "c").mapInArrow(_score_words(spark.sparkContext.broadcast(model), total + n_end, kinds), ddl(_SCORED)))
    # the least count that at most ``top_words`` words reach
    steps = scored.where("c > 0").groupBy(F.floor(F.log2("c") * 8).alias("k")).count().orderBy(F.desc("k")).collect()
    run, least = 0, None
    for k, n in steps:
        run += n
        if run > top_words:
            break
        least = k
    top = scored.where(F.floor(F.log2("c") * 8) >= least).orderBy("h").collect() if least is not None else []
    arrays = tuple(np.array([r[i] for r in top], kind) for i, kind in ((0, np.int64), (1, np.int64), (2, np.float64)))
    rows = docs.select(F.col("doc_id").cast("long"), held, "text").mapInArrow(_rows(spark.sparkContext.broadcast(arrays)), ddl(_ROWS))
    both = rows.join(scored, "h", "left")
    tf = F.when(F.col("info").isNull(), F.col("tf")).otherwise(0)
    sums = both.groupBy("rid").agg(
        F.max("info").alias("info"),
        F.sum(F.when(F.col("c") > 0, tf).otherwise(0)).alias("known"),
        F.sum(F.coalesce(tf * F.log10(F.col("c") + 0.1), F.lit(0.0))).alias("base"),
        F.sum(F.coalesce(tf * F.col("lp"), F.lit(0.0))).alias("score"),
    )
    return sums.select("info", "known", "base", "score").mapInArrow(_finish(n_end, total + n_end, kinds + (n_end > 0)), ddl(_OUT))
