"""Sequence packing by minimum bin slack over a histogram of lengths.

Documents become token ids, end mark included, and are cut at the window size.
The rests form a multiset of at most ``window`` distinct lengths, whatever the
size of the corpus; only that histogram reaches the driver.  Window after window
takes the longest rest left and, by subset-sum over bitsets with counts split in
powers of two, the multiset of others that fills the window closest to capacity;
a found multiset is used as often as the counts allow.  If room stays, the
longest rest that is left is cut to fill it.  The last window's rests are cut in
powers of two, which need no padding.  Rests of a length are numbered within
blocks and blocks by prefix sums, so no length, however common, meets in one task.

Null text is empty (its end mark is packed all the same).  Null and repeated ids
are packed row by row.
"""

from __future__ import annotations

import os
import re
import unicodedata
import zlib
from array import array
from functools import cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import KEPT, batch, checkpointed, lean, plain
from .ngram_join import ddl

_CACHES: dict = {}


#: The tokenizer's own cut of text in words: for lower-cased ASCII, for lower-cased Latin-1, and for any text before lower-casing.
_ASCII = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\sa-z0-9]+", re.ASCII)
_LATIN = re.compile("'s|'t|'re|'ve|'m|'ll|'d|[a-z\xaa\xb5\xba\xdf-\xf6\xf8-\xff]+|[0-9\xb2\xb3\xb9\xbc-\xbe]|[^\t\n\x0b\x0c\r \x85\xa0a-z0-9\xaa\xb2\xb3\xb5\xb9\xba\xbc-\xbe\xdf-\xf6\xf8-\xff]+")
_ANY = regex.compile(r"'[sS]|'[tT]|'[rR][eE]|'[vV][eE]|'[mM]|'[lL][lL]|'[dD]|\p{L}+|\p{N}|[^\s\p{L}\p{N}]+")


@cache
def _newer() -> re.Pattern:
    """Letters and numbers that came after Unicode 3.2, and all beyond its first plane: libraries may differ on them, so texts with one go whole."""
    plane = "".join(chr(c) for c in range(0x10000) if not 0xD800 <= c < 0xE000)
    late = (c for c in regex.findall(r"[\p{L}\p{N}]", plane) if unicodedata.ucd_3_2_0.category(c) == "Cn")
    return re.compile("[" + "".join(map(re.escape, late)) + "]|[\U00010000-\U0001efff\U0001f100-\U0001f10c\U0001fbf0-\U0001fbf9\U00020000-\U0010ffff]")


def _latin(text: str) -> bool:
    try:
        text.encode("latin-1")
    except UnicodeEncodeError:
        return False
    return True


def _byte_letters() -> dict[int, str]:
    """The letter that byte-level vocabularies write for each byte: itself if visible, else the next from 256 on."""
    seen = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(seen)]
    return {b: chr(b) for b in seen} | {b: chr(256 + i) for i, b in enumerate(rest)}


_LETTERS = _byte_letters()


class WordIds:
    """Word, as the tokenizer cuts them -> its ids as bytes; words seen of late are kept in two generations."""

    def __init__(self, path: str, most: int = 200_000):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok, self.most, self.now, self.old = Tokenizer.from_file(path), most, {}, {}
        self.model = self.tok.model

    def _learn(self, words) -> None:
        new, now = [], self.now
        for w in words:
            if (known := self.old.get(w)) is not None:
                now[w] = known
            elif w == w.lower() and (w.isascii() or _latin(w)):  # nothing left for the tokenizer but its merges
                seen = w.isascii() and w.isprintable()  # such bytes are their own letters
                now[w] = array("I", [t.id for t in self.model.tokenize(w if seen else w.encode().decode("latin-1").translate(_LETTERS))]).tobytes()
            else:
                new.append(w)
        for at in range(0, len(new), 20_000):
            some = new[at : at + 20_000]
            for w, e in zip(some, self.tok.encode_batch_fast(some, add_special_tokens=False), strict=True):
                now[w] = array("I", e.ids).tobytes()

    def ids(self, texts: list[str]) -> list[np.ndarray]:
        """Ids of whole texts.  Texts with a special token's mark, a capital that lower-cases to two characters or a letter of a later Unicode go whole."""
        if len(self.now) > self.most:
            self.now, self.old = {}, self.now
        cut = []
        for t in texts:
            if "<|" in t or "\u0130" in t:
                cut.append(None)
            elif t.isascii():
                cut.append(_ASCII.findall(t.lower()))
            elif _latin(t):
                cut.append(_LATIN.findall(t.lower()))
            elif _newer().search(t):
                cut.append(None)
            else:
                cut.append(_ANY.findall(t if unicodedata.is_normalized("NFC", t) else unicodedata.normalize("NFC", t)))
        self._learn(set().union(*(x for x in cut if x)).difference(self.now))
        return [np.array(self.tok.encode(t, add_special_tokens=False).ids, np.uint32) if x is None else np.frombuffer(b"".join(map(self.now.__getitem__, x)), np.uint32) for t, x in zip(texts, cut, strict=True)]


    def clear(self) -> None:
        self.now, self.old = {}, {}


def tokenizer(path: str) -> WordIds:
    if path not in _CACHES:
        _CACHES[path] = WordIds(path)
        KEPT.append(_CACHES[path])
    return _CACHES[path]


_PIECE = pa.schema([(c, pa.int64()) for c in ("doc_id", "h", "block", "start", "length", "rank", "crc", "doc_tokens")])


def _token_rows(path: str, window: int, end: int, group: int = 256):
    """(doc_id, h, text) -> a row for each piece of at most ``window`` ids."""

    def run(batches):
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        seen = np.zeros(window + 1, np.int64)
        tok = tokenizer(path)
        for b in batches:
            for at in range(0, b.num_rows, group):
                some = b.slice(at, group)
                out = [[] for _ in range(8)]
                for doc, h, ids in zip(some.column(0).to_pylist(), some.column(1).to_pylist(), tok.ids([t or "" for t in some.column(2).to_pylist()]), strict=True):
                    ids = np.append(ids, end).astype("<u4")
                    for start in range(0, len(ids), window):
                        x = ids[start : start + window]
                        for c, v in zip(out, (doc, h, part, start, len(x), int(seen[len(x)]), zlib.crc32(x.tobytes()), len(ids)), strict=True):
                            c.append(v)
                        seen[len(x)] += 1
                if out[0]:
                    yield batch(_PIECE, *out)

    return lean(run)


def best_fill(counts: dict[int, int], room: int) -> dict[int, int]:
    """Multiset of lengths, within ``counts``, whose sum comes closest to ``room`` from below.

    Bit s of ``reach`` says that sum s can be made.  Each length is taken in
    lots of 1, 2, 4, ... so that a common length costs log(room) steps; the
    lots are undone from last to first to read the counts off.
    """
    mask = (1 << (room + 1)) - 1
    reach, lots = 1, []
    for length in sorted((x for x in counts if x <= room), reverse=True):
        left, lot = min(counts[length], room // length), 1
        while left > 0:
            take = min(lot, left)
            lots.append((length, take, reach))
            reach |= (reach << (length * take)) & mask
            left -= take
            lot *= 2
        if reach >> room:
            break
    at, used = reach.bit_length() - 1, {}
    for length, take, before in reversed(lots):
        if not before >> at & 1:
            at -= length * take
            used[length] = used.get(length, 0) + take
    return used


def plan_windows(histogram: dict[int, int], window: int) -> list[dict]:
    """Patterns: {"times", "parts": [(kind, length, from, size)]}.

    A part takes ``size`` ids at ``from`` of a rest of ``length``; a rest that is
    cut goes on as (length, from) in later parts.  At most a few patterns a
    distinct length, so the plan is bounded by the window size alone.
    """
    pool: dict[tuple[int, int, int], int] = {(n, n, 0): c for n, c in histogram.items() if c > 0}  # (left, whole, from)
    out: list[dict] = []

    def lengths() -> dict[int, int]:
        have: dict[int, int] = {}
        for (left, _, _), c in pool.items():
            have[left] = have.get(left, 0) + c
        return have

    have = lengths()
    by_left: dict[int, list] = {}
    for key in pool:
        by_left.setdefault(key[0], []).append(key)

    def put(key, c):
        if c > 0:
            if not pool.get(key):
                pool[key] = 0
                by_left.setdefault(key[0], []).append(key)
            pool[key] += c
            have[key[0]] = have.get(key[0], 0) + c

    def take(left: int, times: int, count: int) -> list:
        """Lots of one kind each: [(key, count)] for one window, if ``times`` windows can all have it."""
        got = []
        for key in list(by_left.get(left, ())):
            n = min(count, pool[key] // times)
            if n:
                got.append((key, n))
                count -= n
            if not count:
                break
        return got if not count else []

    def remove(key, c):
        pool[key] -= c
        have[key[0]] -= c
        if not pool[key]:
            del pool[key]
            by_left[key[0]].remove(key)
        if not have[key[0]]:
            del have[key[0]]

    while have:
        if sum(n * c for n, c in have.items()) < window:
            break
        top = max(have)
        need = {top: 1}
        less = dict(have)
        less[top] -= 1
        if top < window:
            for n, c in best_fill({n: c for n, c in less.items() if c}, window - top).items():
                need[n] = need.get(n, 0) + c
        fill = sum(n * c for n, c in need.items())
        times = min(have[n] // c for n, c in need.items())
        cut = None
        if fill < window:
            rest = [n for n in have if have[n] > need.get(n, 0)]
            if not rest:
                break
            cut = max(rest)
            need_cut = dict(need)
            need_cut[cut] = need_cut.get(cut, 0) + 1
            times = min(have[n] // c for n, c in need_cut.items())
            need = need_cut
        # a length may consist of several kinds (cut and whole): fewer repeats until each lot is of one kind
        while True:
            lots = [x for n, c in need.items() for x in take(n, times, c)]
            if sum(c for _, c in lots) == sum(need.values()) or times == 1:
                break
            times = max(1, times // 2)
        if sum(c for _, c in lots) != sum(need.values()):
            raise AssertionError("lots don't cover the pattern")
        parts, cut_done = [], cut is None
        for key, c in lots:
            left, whole, at = key
            remove(key, c * times)
            if not cut_done and left == cut:
                parts += [(whole, at, left, c - 1)] if c > 1 else []
                size = window - fill
                parts.append((whole, at, size, 1))
                put((left - size, whole, at + size), times)
                cut_done = True
            else:
                parts.append((whole, at, left, c))
        out.append({"times": times, "parts": parts})
    # the end: less than a window, cut in powers of two
    left = [[key, c] for key, c in sorted(pool.items(), reverse=True)]
    total = sum(key[0] * c for key, c in left)
    while total:
        size = min(window, 1 << (total.bit_length() - 1))
        parts, room = [], size
        while room:
            (n, whole, at), c = left[0]
            if n <= room:
                many = min(c, room // n)
                parts.append((whole, at, n, many))
                room -= n * many
                left[0][1] -= many
            else:
                parts.append((whole, at, room, 1))
                left[0][1] -= 1
                left.insert(1, [(n - room, whole, at + room), 1])
                room = 0
            if not left[0][1]:
                left.pop(0)
            elif left[0][0][0] > room and room:
                continue
        total -= size
        out.append({"times": 1, "parts": parts})
    return out


def plan_table(plan: list[dict]) -> dict[tuple[int, int], np.ndarray]:
    """(whole, from) -> its parts in plan order, a row each: first number, copies a
    window, first window, size, offset of the first copy, and the number that the
    first item cut here gets among those that go on at from + size."""
    by: dict[tuple[int, int], list] = {}
    used: dict[tuple[int, int], int] = {}
    grown: dict[tuple[int, int], int] = {}
    base = 0
    for p in plan:
        offset = 0
        for whole, at, size, copies in p["parts"]:
            key, n = (whole, at), copies * p["times"]
            on = (whole, at + size)
            by.setdefault(key, []).append((used.get(key, 0), copies, base, size, offset, grown.get(on, 0)))
            used[key] = used.get(key, 0) + n
            if at + size < whole:
                grown[on] = grown.get(on, 0) + n
            offset += size * copies
        base += p["times"]
    return {k: np.array(v, np.int64) for k, v in by.items()}


_SEAT = pa.schema([(c, pa.int64()) for c in ("doc_id", "h", "start", "length", "crc", "doc_tokens", "sequence_id", "offset")])


def _seats(plan: dict[tuple[int, int], np.ndarray]):
    """(doc_id, h, start, length, rank, crc, doc_tokens) -> a row for each part of the piece."""

    def run(batches):
        for b in batches:
            doc, h, crc = b.column(0), b.column(1), b.column(5)
            start, length, rank, whole_tokens = (b.column(i).to_numpy() for i in (2, 3, 4, 6))
            for n in np.unique(length):
                rows = np.flatnonzero(length == n)
                number, at = rank[rows], np.zeros(len(rows), np.int64)
                while len(rows):
                    go_rows, go_number, go_at = [], [], []
                    for a in np.unique(at):
                        mine = at == a
                        r, q = rows[mine], number[mine]
                        t = plan[(int(n), int(a))]
                        i = np.searchsorted(t[:, 0], q, side="right") - 1
                        k, size = q - t[i, 0], t[i, 3]
                        take = pa.array(r)
                        whole = size == n
                        yield batch(_SEAT, doc.take(take), h.take(take), start[r] + a, size, pa.array(crc.take(take).to_numpy(zero_copy_only=False), mask=~whole), whole_tokens[r], t[i, 2] + k // t[i, 1], t[i, 4] + k % t[i, 1] * size)
                        on = a + size < n
                        go_rows.append(r[on])
                        go_number.append((t[i, 5] + k)[on])
                        go_at.append((a + size)[on])
                    rows, number, at = np.concatenate(go_rows), np.concatenate(go_number), np.concatenate(go_at)

    return run


_CRC = pa.schema([(c, pa.int64()) for c in ("doc_id", "h", "start", "length", "crc")])


def _cut_crcs(path: str, end: int):
    def run(batches):
        tok = tokenizer(path)
        for b in batches:
            for i in range(b.num_rows):
                doc, h, text, cuts = (b.column(c)[i].as_py() for c in range(4))
                ids = np.append(tok.ids([text or ""])[0], end).astype("<u4")
                rows = [(doc, h, c["start"], c["length"], zlib.crc32(ids[c["start"] : c["start"] + c["length"]].tobytes())) for c in cuts]
                yield batch(_CRC, *zip(*rows, strict=True))

    return lean(run)


def pack(docs: DataFrame, tokenizer_path: str, window: int = 4096, end: int = 2, id_col: str = "doc_id", text_col: str = "text", broadcast_rows: int = 20_000) -> DataFrame:
    """Pieces of all rows: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset."""
    text = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("h"), F.col(text_col).cast("string").alias("text"))
    pieces = checkpointed(text.mapInArrow(_token_rows(tokenizer_path, window, end), ddl(_PIECE)))
    tally = checkpointed(pieces.groupBy("length", "block").agg(F.count(F.lit(1)).alias("c")))
    before = F.coalesce(F.sum("c").over(Window.partitionBy("length").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    histogram = {r[0]: r[1] for r in tally.groupBy("length").agg(F.sum("c")).collect()}  # at most ``window`` rows
    plan = plan_table(plan_windows(histogram, window))
    ranked = pieces.join(tally.select("length", "block", before.alias("before")), ["length", "block"])
    ranked = ranked.select("doc_id", "h", "start", "length", (F.col("rank") + F.col("before")).alias("rank"), "crc", "doc_tokens")
    seats = checkpointed(ranked.mapInArrow(_seats(plan), ddl(_SEAT)))
    cuts = checkpointed(seats.where("crc IS NULL").select("doc_id", "h", "start", "length").distinct().groupBy("doc_id", "h").agg(F.collect_list(F.struct("start", "length")).alias("cuts")))
    few = cuts.count() <= broadcast_rows
    c = cuts.select(F.col("doc_id").alias("c_id"), F.col("h").alias("c_h"), "cuts")
    same = F.col("doc_id").eqNullSafe(F.col("c_id")) & (F.col("h") == F.col("c_h"))
    again = text.join(F.broadcast(c) if few else c, same)
    if not few:
        again = again.dropDuplicates(["doc_id", "h"])
    crcs = again.select("doc_id", "h", "text", "cuts").mapInArrow(_cut_crcs(tokenizer_path, end), ddl(_CRC)).distinct()
    crcs = crcs.select(F.col("doc_id").alias("c_id"), F.col("h").alias("c_h"), F.col("start").alias("c_start"), F.col("length").alias("c_length"), F.col("crc").alias("c_crc"))
    same = same & (F.col("start") == F.col("c_start")) & (F.col("length") == F.col("c_length"))
    out = ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
    whole = seats.where("crc IS NOT NULL").withColumnRenamed("crc", "ids_crc32").select(*out)
    return whole.union(seats.where("crc IS NULL").join(crcs, same).withColumnRenamed("c_crc", "ids_crc32").select(*out))
