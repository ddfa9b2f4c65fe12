"""From documents to packed sequences: quality, repeated lines, near-duplicates, source mix, packing."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from uncertainseq.llm import bagminhash, line_dedup, mixing, packing, quality
from uncertainseq.llm.common import shared_dir, table
from uncertainseq.runtime import ship


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier does not reject.

    Null and empty texts have a score like any other; every row is judged by itself, so repeated rows share a fate. No rows give no rows.
    """
    return quality.keep_good(docs, table(ship(spark), sf_dir, "labels"))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that occur or almost occur before.

    No document goes: one whose lines all go keeps its row. Null text stays null, rows without doc_id stay as they are; see ``dedup_lines``.
    """
    return line_dedup.dedup_lines(docs).select(docs.columns)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates, that of the least doc_id.

    Empty texts, null ones too, are one group; rows without doc_id stay, rows of one doc_id share a fate. No rows give no rows.
    """
    ship(spark)
    return bagminhash.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for every copy of a document that the mix takes.

    Null source is a source; texts without words add nothing and come in whole passes; equal rows are drawn one by one. No rows give no rows.
    """
    return mixing.mixture(docs)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the mixed documents in training sequences.

    Every row is a document, null text an empty one of the closing id alone; each id lies in one piece. No rows give no rows.
    """
    ship(spark)
    return packing.pack(docs)


STAGES = [("quality", keep_good), ("line_dedup", drop_lines), ("near_dedup", drop_near_duplicates), ("mixing", mix_sources), ("packing", pack_sequences)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, each written to the shared folder and read again by the next."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        path = f"{shared_dir(spark)}/pipeline-{name}-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs


#: Tokens, signatures and learned scores have no SQL; tests/llm/test_pipeline.py holds the stages against plain Python on a small fixture.
ORACLE_SQL = None
