"""Five stages over the documents table, each with one operator of the llm subpackage.

Every stage takes ``(spark, docs, sf_dir)`` and works on all rows its
predecessor kept. All but the last return the columns of documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusmill.llm import bpe, mixture_fit, near_dedup, quality_model, queries, secret_scan
from corpusmill.session import ship_package

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def drop_low_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the preference model predicts good; the held-out fold of labels is not learned from."""
    labels = queries._seen_labels(spark.read.parquet(f"{sf_dir}/labels.parquet"))
    rejected = quality_model.quality_scores(docs, labels).where("predicted = 0").select("doc_id").distinct()
    return docs.join(rejected, "doc_id", "left_anti").select(COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: five-word shingles, similarity 0.8."""
    gone = near_dedup.near_duplicates(docs, shingle=5, percent=80).where("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(COLUMNS)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, found secrets replaced by their kind."""
    return secret_scan.redact(docs).select(COLUMNS)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them: a document taken twice is two rows."""
    copies = mixture_fit.mix(docs).where("copies > 0").groupBy("doc_id").agg(F.max("copies").alias("copies"))
    times = F.explode(F.sequence(F.lit(1).cast("long"), "copies"))
    return docs.join(copies, "doc_id").withColumn("copy", times).select(COLUMNS)


def tokenize(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of every row as little-endian 32-bit integers, and the text decoded from them as a digest."""
    got = bpe.encode_documents(docs, queries.tokenizer_path())
    return got.select("doc_id", "n_tokens", "ids", F.sha2("decoded", 256).alias("decoded_sha256"))


STAGES = [
    ("quality_classifier", drop_low_quality),
    ("near_dedup", drop_near_copies),
    ("secret_scan", mask_secrets),
    ("mixture", mix_sources),
    ("bpe", tokenize),
]

#: A learned model and hashed signatures are beyond SQL; the tests compare with plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each written as Parquet in the shared folder and read again."""
    ship_package(spark)
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    shared = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None)
    for name, stage in STAGES:
        out = stage(spark, docs, sf_dir)
        if shared is None:  # set by the stage's own checkpoints where the session has none
            shared = spark.sparkContext.getCheckpointDir()
        path = f"{shared}/pipeline-{uuid.uuid4().hex}/{name}"
        out.write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
