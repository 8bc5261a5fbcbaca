"""Line dedup with DataFrame functions only.

Lines are exploded with their place, keyed by two independent 64-bit hashes of
the normalised line, and counted by distinct document.  Lines over the threshold
go, except in the smallest id; the text is put together again by position.  Only
hashes and positions are shuffled for counting; a key that a third of all lines
share is pre-aggregated, and its join is one that AQE splits.

Null or empty text is one empty line.  Rows with a null id take no part: they
are neither counted nor cut.  Rows that repeat an id count as one document, and
each loses the lines of its own text.  Very long texts go whole, as an array of
lines; an empty table gives an empty one.  Other columns stay as they are, but for
columns named n_lines or n_dropped, which the new ones replace.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SPACE, fresh, lower_ascii


def _row(text):
    """What tells rows of one id apart: rows with equal texts lose the same lines."""
    return F.xxhash64(F.coalesce(text, F.lit("")))


def _lines(docs: DataFrame, id_col: str, text_col: str, least_chars: int) -> DataFrame:
    text = F.col(f"`{text_col}`")
    rows = docs.where(F.col(f"`{id_col}`").isNotNull()).select(F.col(f"`{id_col}`").alias("id"), _row(text).alias("row"), F.posexplode(F.split(F.coalesce(text, F.lit("")), "\n", -1)).alias("pos", "line"))
    rows = rows.select("id", "row", "pos", F.btrim("line", F.lit(SPACE)).alias("line")).where(F.char_length("line") >= least_chars)
    key = lower_ascii(F.col("line"))
    return rows.select("id", "row", "pos", F.xxhash64(key).alias("h1"), F.xxhash64(F.lit(7), key).alias("h2"))


def dropped_lines(docs: DataFrame, least_chars: int = 10, least_docs: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Lines to drop: (id, row: hash of the text, drops: sorted distinct positions from 0)."""
    lines = _lines(docs, id_col, text_col, least_chars)
    held = lines.groupBy("h1", "h2").agg(F.count_distinct("id").alias("n_docs"), F.min("id").alias("first")).where(F.col("n_docs") >= least_docs)
    gone = lines.join(held.select("h1", "h2", "first"), ["h1", "h2"]).where("id <> first")
    return gone.groupBy("id", "row").agg(F.sort_array(F.collect_set("pos")).alias("drops"))


def line_dedup(docs: DataFrame, least_chars: int = 10, least_docs: int = 2, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` with ``text`` cut, plus n_lines (before) and n_dropped."""
    c_id, c_row, c_drops, c_lines = (fresh(docs, f"__{c}") for c in ("id", "row", "drops", "lines"))
    gone = dropped_lines(docs, least_chars, least_docs, id_col, text_col).toDF(c_id, c_row, c_drops)
    text = F.col(f"`{text_col}`")
    both = docs.join(gone.hint("shuffle_hash"), (F.col(f"`{id_col}`") == F.col(c_id)) & (_row(text) == F.col(c_row)), "left").drop(c_id, c_row)
    both = both.withColumn(c_lines, F.split(F.coalesce(text, F.lit("")), "\n", -1))
    d, lines = F.col(c_drops), F.col(c_lines)

    def part(k):
        """Lines after the drop before the k-th and before the k-th."""
        start = F.when(k == 0, F.lit(1)).otherwise(F.get(d, k - 1) + 2)
        stop = F.when(k == F.size(d), F.size(lines)).otherwise(F.get(d, k))
        return F.slice(lines, start, F.greatest(stop - start + 1, F.lit(0)))

    kept = F.array_join(F.flatten(F.transform(F.sequence(F.lit(0), F.size(d)), part)), "\n")
    out = both.withColumn("n_lines", F.size(lines).cast("long")).withColumn("n_dropped", F.when(d.isNull(), F.lit(0)).otherwise(F.size(d)).cast("long"))
    return out.withColumn(text_col, F.when(d.isNull(), F.coalesce(text, F.lit(""))).otherwise(kept)).drop(c_drops, c_lines)


SQL = """
WITH l AS (
  SELECT doc_id, i - 1 AS pos, lines[i] AS line FROM (
    SELECT doc_id, string_split(coalesce(text, ''), chr(10)) AS lines FROM documents), range(1, len(lines) + 1) r(i)),
k AS (
  SELECT doc_id, pos, line, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
    'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key FROM l),
h AS (
  SELECT key, min(doc_id) AS f FROM k WHERE length(key) >= 10 GROUP BY key HAVING count(DISTINCT doc_id) >= 2),
m AS (
  SELECT k.doc_id, k.pos, k.line, h.f IS NOT NULL AND h.f <> k.doc_id AS gone FROM k LEFT JOIN h ON k.key = h.key)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM m GROUP BY doc_id
"""
