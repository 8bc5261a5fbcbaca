"""Corpus pipeline: toxic documents go, then repeated lines, near copies and repeated passages; the rest is packed.

Each stage takes (spark, docs, sf_dir) and works on all that the one before kept.
All but the last return the columns of documents; n_chars is kept in step with the text.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vicicorr.llm import toxicity as tox
from vicicorr.llm.common import ship, stored, table
from vicicorr.llm.line_dedup import line_dedup
from vicicorr.llm.ngram_join import keep_one
from vicicorr.llm.packing import pack
from vicicorr.llm.substring_dedup import substring_dedup


def _same_columns(out: DataFrame, docs: DataFrame) -> DataFrame:
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.char_length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


#: The stages take null, empty, very long and repeated rows as their operators state; columns other than
#: those of documents stay, and an empty table gives an empty one (tests/llm/test_pipeline.py).


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents scored toxic go; the model learns from all labels."""
    return tox.keep_clean(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier document holds go; rows stay, a text may become empty."""
    return _same_columns(line_dedup(docs), docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays; those whose texts line dedup emptied are in no group."""
    ship(spark)
    return keep_one(docs)


def drop_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that an earlier document holds go from the texts."""
    ship(spark)
    return _same_columns(substring_dedup(docs), docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of token ids in sequences: not the columns of documents."""
    ship(spark)
    return pack(docs, public_tokenizers.path("word_bpe_49k.json"))


STAGES = [
    ("toxicity", drop_toxic),
    ("line dedup", drop_lines),
    ("n-gram join", drop_near_copies),
    ("substring dedup", drop_passages),
    ("packing", pack_sequences),
]

#: Kneser-Ney scores, chained passages and token ids can't be had in SQL; tests/llm holds the operators against brute force and the stages against planted cases.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = stored(docs)
    return docs
