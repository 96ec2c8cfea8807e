"""A training-data pipeline of five stages: each takes (spark, docs, sf_dir), and its rows are written and read again for the next."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from freeseg.llm import decontam, langid, line_dedup, near_dup, pieces
from freeseg.llm.queries import VOCABULARY, table
from freeseg.shipping import shared_dir, ship


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the documents whose language is known; the model learns from all that name one."""
    ship(spark)
    return langid.keep_identified(docs, langid.train(docs))


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops lines whose template recurs across documents, but for the first, and documents of which no word is left."""
    ship(spark)
    return line_dedup.clean(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each group linked by five-word shingles at a similarity of 0.8."""
    ship(spark)
    return near_dup.dedup(docs)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that hold a benchmark item."""
    return decontam.clean(docs, table(spark, sf_dir, "benchmark"))


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The piece ids of each document, and whether they decode to its text."""
    ship(spark)
    coded = pieces.encode(docs, pieces.read_pieces(VOCABULARY))
    return coded.select("doc_id", "lang", "source", F.size("piece_ids").cast("long").alias("n_pieces"), "piece_ids", "decodes")


STAGES = [("language_id", language_id), ("line_dedup", drop_lines), ("near_duplicates", near_duplicates), ("decontamination", decontaminate), ("sentencepiece", encode)]

#: Templates, sketches and pieces can't be expressed in SQL; tests hold the stages against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages over the documents of sf_dir, one after the other."""
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        out.write.parquet(f"{folder}/{k}-{name}")
        docs = spark.read.parquet(f"{folder}/{k}-{name}")
