"""The queries of these operators over the given tables, and their SQL for DuckDB where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..shipping import ship
from . import decontam, langid, line_dedup, lm, merkle, near_dup, pieces, toxicity, warc, wordpiece
from .kernel import remainder

#: Where the public tokenizers' files are.
TOKENIZERS = "/opt/tokenizers"
VOCABULARY = f"{TOKENIZERS}/piece_bpe_32k.model"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = near_dup.groups(docs, width=2, num=80, den=100)
    return found.select(F.col("id").alias("doc_id"), "n_shingles", "component_id", F.col("id").eqNullSafe(F.col("component_id")).alias("kept"))


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = langid.train(docs.where(remainder("doc_id", 5) != 0))
    return langid.predict(docs.select("doc_id", "text"), model).select("doc_id", (remainder("doc_id", 5) == 0).alias("held_out"), "lang_pred", "score")


def op3_lm_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    with open(VOCABULARY, "rb") as f:
        found = lm.score(docs, remainder("doc_id", 7) != 2, f.read())
    return found.withColumnRenamed("id", "doc_id").withColumn("held_out", remainder("doc_id", 7) == 2)


def op4_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return merkle.compare_edits(table(spark, sf_dir, "documents"))


def op5_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return line_dedup.digest_rows(line_dedup.dedup_lines(docs))


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return wordpiece.token_counts(docs, *wordpiece.read_vocabulary(VOCABULARY)).drop("text")


def op7_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    coded = pieces.encode(docs, pieces.read_pieces(VOCABULARY)).drop("text")
    return coded.select("doc_id", F.size("piece_ids").cast("long").alias("n_pieces"), F.xxhash64("piece_ids").alias("ids_hash"), "decodes")


def op8_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages").select("page_id", "url", "html")
    return warc.round_trip(pages, payloads=False).drop("payload", "url")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    learn = remainder("doc_id", 5) != 0
    model = toxicity.train(docs.where(learn), table(spark, sf_dir, "labels").where(learn))
    return toxicity.predict(docs, model).select("doc_id", (remainder("doc_id", 5) == 0).alias("held_out"), "score", "predicted")


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = decontam.scan(docs, table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", (F.size("item_ids") > 0).alias("contaminated"), "item_ids", "coverage", "reparameterised")


QUERIES = {f.__name__: f for f in (op1_near_duplicates, op2_language_id, op3_lm_scores, op4_fingerprints, op5_line_dedup, op6_token_counts, op7_sentencepiece, op8_warc, op9_toxicity, op10_decontamination)}
ORACLES: dict[str, str] = {
    "op8_warc": """
        WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
        q AS (SELECT page_id, CAST(strlen(h) AS BIGINT) AS n, sha256(h) AS d, min(page_id) OVER (PARTITION BY h) AS f FROM p)
        SELECT page_id, n AS payload_bytes, d AS payload_digest,
            CASE WHEN n >= 100 AND f <> page_id THEN 'revisit' ELSE 'response' END AS record_type,
            CASE WHEN n >= 100 AND f <> page_id THEN f END AS refers_to, true AS verified
        FROM q
    """,
}
