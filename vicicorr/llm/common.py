"""Helpers shared by the operators: shared storage, word hashing, packed key blocks."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
import zipfile
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space that separates words (fixed by the contract).
SPACE = " \t\n\x0b\x0c\r"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"
NULL_ID = -(2**63)


_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give executors this package, once an application, in case they don't have it."""
    app = spark.sparkContext.applicationId
    if app not in _SHIPPED:
        root = Path(__file__).resolve().parents[1]
        path = Path(tempfile.mkdtemp(prefix="package-")) / "package.zip"
        with zipfile.ZipFile(path, "w") as z:
            for f in root.rglob("*.py"):
                z.write(f, f.relative_to(root.parent))
        spark.sparkContext.addPyFile(str(path))
        _SHIPPED.add(app)


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """The named table, cut to ``cols`` so that the scan reads no other column."""
    ship(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share: spark.checkpoint.dir.  Unset, it is one of our own in local mode and an error on a cluster."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        at = spark.conf.get("spark.checkpoint.dir", None)
        if at is None and sc.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(at or tempfile.mkdtemp(prefix="shared-"))
    return sc.getCheckpointDir()


def release(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of steps whose result has been written."""
    gc.collect()
    spark._jvm.System.gc()


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage of a narrow table with a reliable checkpoint."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """Write ``df`` as Parquet in the shared folder and read it back; gone when the driver ends."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    jvm = spark._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(at)
    schema = df.schema
    del df
    release(spark)
    return spark.read.schema(schema).parquet(path)


def shuffle_parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def range_bits(spark: SparkSession) -> int:
    """Bits of a key that name its range: about eight ranges for each shuffle partition."""
    return min(16, max(6, (8 * shuffle_parts(spark) - 1).bit_length()))


def fold(col: str, mod: int):
    """crc32 of the id as text, modulo ``mod``; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(col).cast("string"), F.lit("")).cast("binary")) % mod


def as_bytes(column: pa.Array) -> list:
    """UTF-8 bytes of a string column, null as None, without building Python strings."""
    return column.cast(pa.binary()).to_pylist()


def lower_ascii(col):
    """A-Z lower-cased, all else untouched; pure-ASCII values take the fast built-in."""
    return F.when(F.octet_length(col) == F.char_length(col), F.lower(col)).otherwise(F.translate(col, UPPER, LOWER))


class WordHash(dict):
    """word bytes -> 64-bit hash, kept for up to ``most`` words."""

    def __init__(self, most: int = 120_000):
        self.most = most

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        self[word] = value = xxhash.xxh3_64_intdigest(word)
        return value

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


_WORDS = WordHash()
#: What a task may keep while it runs; emptied at its end, as workers live on.
KEPT: list = [_WORDS]
try:
    _TRIM = ctypes.CDLL(None).malloc_trim
except (OSError, AttributeError):  # not glibc
    _TRIM = None


def forget() -> None:
    """Empty the caches and give freed memory back."""
    for kept in KEPT:
        kept.clear()
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(0)


def lean(run):
    """A task function over batches that leaves nothing behind in its worker."""

    def task(batches):
        try:
            yield from run(batches)
        finally:
            forget()

    return task


def lean_group(run):
    """The same for a function of one group."""

    def task(key, tbl):
        try:
            return run(key, tbl)
        finally:
            forget()

    return task


def lean_pieces(run):
    """The same for a function that takes a group and gives its result in pieces."""

    def task(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(key, batches)
        finally:
            forget()

    return task


def slices(batches, rows: int = 512):
    """Batches of few rows, so that few are Python objects at once."""
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)


def fresh(df: DataFrame, name: str) -> str:
    """``name``, or with underscores before it, so that no column of ``df`` has it."""
    have = {c.lower() for c in df.columns}
    while name.lower() in have:
        name = "_" + name
    return name


def plain(df: DataFrame, **cols: str) -> DataFrame:
    """Columns by their new names and no others, whatever else a table holds; the package goes to the executors with it."""
    ship(df.sparkSession)
    return df.select(*(F.col(f"`{old}`").alias(new) for new, old in cols.items()))
_ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)]


def word_hashes(text: bytes | None) -> np.ndarray:
    """Hashes of the lower-cased words of a text, in order."""
    return _WORDS.of(text.lower().split()) if text else np.empty(0, np.uint64)


PIECE = 1 << 16
_IS_SPACE = np.isin(np.arange(256), list(SPACE.encode()))
_LETTER = np.array([xxhash.xxh3_64_intdigest(bytes([c])) for c in range(256)], np.uint64)
_POWER = np.cumprod(np.full(PIECE, _ODD[0]))
_INVERSE = np.cumprod(np.full(PIECE, np.uint64(pow(int(_ODD[0]), -1, 2**64))))


def text_hashes(text: bytes | None) -> np.ndarray:
    """Hashes of the lower-cased words of a text, in order, from sums over its bytes; other ones than those of ``word_hashes``.

    Words of PIECE bytes and more are hashed one by one."""
    text, out, a = (text or b"").lower(), [], 0
    while a < len(text):
        b = len(text)
        if b - a >= PIECE:
            b = max(text.rfind(x, a, a + PIECE) for x in (b" ", b"\n", b"\t", b"\r", b"\x0b", b"\x0c"))
            if b < 0:
                b = min((x for x in (text.find(x, a) for x in (b" ", b"\n", b"\t", b"\r", b"\x0b", b"\x0c")) if x >= 0), default=len(text))
                out.append(np.array([xxhash.xxh3_64_intdigest(text[a:b])], np.uint64))
                a = b
                continue
            b += 1
        c = np.frombuffer(text, np.uint8, b - a, a)
        space = np.ones(b - a + 2, np.int8)
        space[1:-1] = _IS_SPACE[c]
        turn = np.diff(space)
        start, stop = np.flatnonzero(turn == -1), np.flatnonzero(turn == 1)
        total = np.zeros(b - a + 1, np.uint64)
        np.cumsum(_LETTER[c] * _POWER[: b - a], out=total[1:])
        h = (total[stop] - total[start]) * _INVERSE[start]
        h ^= h >> np.uint64(32)
        h *= _ODD[1]
        h ^= h >> np.uint64(29)
        h *= _ODD[2]
        h ^= h >> np.uint64(32)
        out.append(h)
        a = b
    return np.concatenate(out) if out else np.empty(0, np.uint64)


def _joined(a: np.ndarray, b: np.ndarray, at: int) -> np.ndarray:
    """Hashes of the runs of ``at`` words, ``a``, each with the run ``b`` that follows it."""
    h = a[: len(b) - at] * _ODD[0]
    h ^= h >> np.uint64(29)
    h += b[at:]
    h *= _ODD[1]
    h ^= h >> np.uint64(31)
    return h


def window_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """Hash of every run of ``k`` words; one hash of all words if there are fewer, none without words.

    Runs of over eight words are joined from runs of 1, 2, 4, ... words."""
    n = len(words)
    if n == 0:
        return words
    k = min(k, n)
    if k > 8:
        h, done, power, size = None, 0, words, 1
        while size <= k:
            if k & size:
                h, done = (power, size) if h is None else (_joined(h, power, done), done + size)
            if 2 * size <= k:
                power = _joined(power, power, size)
            size *= 2
        h = h * _ODD[2]
        h ^= h >> np.uint64(32)
        return h + np.uint64(k)
    h = words[: n - k + 1] * _ODD[0]
    h ^= h >> np.uint64(29)
    for i in range(1, k):
        h += words[i : n - k + 1 + i]
        h *= _ODD[1]
        h ^= h >> np.uint64(31)
    h *= _ODD[2]
    h ^= h >> np.uint64(32)
    return h + np.uint64(k)


def ranges_of(keys: np.ndarray, bits: int):
    """Cut sorted keys in ranges by their top bits: (range, from, to) for those with keys."""
    at = keys >> np.uint64(64 - bits)
    cut = np.flatnonzero(np.r_[True, at[1:] != at[:-1]]) if len(at) else np.empty(0, np.int64)
    return [(int(at[a]), int(a), int(b)) for a, b in zip(cut, np.r_[cut[1:], len(at)], strict=True)]


def narrow(keys: np.ndarray, bits: int) -> tuple[bytes, bytes]:
    """The 48 bits after the range bits, as two planes: six bytes a key."""
    rest = (keys << np.uint64(bits)) >> np.uint64(16)
    return (rest >> np.uint64(16)).astype(np.uint32).tobytes(), rest.astype(np.uint16).tobytes()


def widen(hi: bytes, lo: bytes) -> np.ndarray:
    return (np.frombuffer(hi, np.uint32).astype(np.uint64) << np.uint64(16)) | np.frombuffer(lo, np.uint16)


def runs(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of runs of equal values."""
    if not len(values):
        return np.empty(0, np.int64), np.empty(0, np.int64)
    start = np.flatnonzero(np.r_[True, values[1:] != values[:-1]])
    return start, np.diff(np.r_[start, len(values)])


def batch(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


def binaries(tbl: pa.Table, name: str) -> list:
    return tbl.column(name).to_pylist()


__all__ = [n for n in dir() if not n.startswith("__")] + ["pc"]
