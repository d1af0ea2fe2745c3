"""The corpus pipeline: toxicity, near duplicates, decontamination, secrets, packing.

Each stage takes ``(spark, docs, sf_dir)``; what it returns is written as Parquet and read
again as the next one's ``docs``. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallypath.llm import decontamination, minhash, packing, secrets, toxicity
from tallypath.llm.common import shared_dir, table, written


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose toxicity score is below 0.5; the classifier learns from ``labels`` as op5 does."""
    model = toxicity.train(docs, table(spark, sf_dir, "labels"))
    return toxicity.score(docs, model, "__toxicity").where(F.col("__toxicity") < 0.5).select(*docs.columns)


def _keyed(rows: DataFrame) -> DataFrame:
    return rows.withColumnsRenamed({"doc_id": "__id", "text_key": "__key"})


def _same_row(docs: DataFrame):
    """Rows are told apart by id and text, so that rows of one id and rows without id are judged each on its own."""
    return docs["doc_id"].eqNullSafe(F.col("__id")) & (F.xxhash64(docs["text"]) == F.col("__key"))


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near duplicates (85 % of 5-word shingles): that with the smallest id, once if its row is repeated."""
    first = minhash.near_duplicates(docs).where("first").groupBy("doc_id", "text_key").agg(F.count("*").alias("__rows"), F.max("n_shingles").alias("__n"))
    first = written(_keyed(first), "first")
    again = (F.col("__rows") > 1) & (F.col("__n") > 0) & F.col("__id").isNotNull()  # texts without words link with nothing
    once = docs.join(first.where(~again), _same_row(docs)).select(*docs.columns)
    repeated = docs.join(first.where(again), _same_row(docs)).dropDuplicates(["__id", "__key"]).select(*docs.columns)
    return once.unionByName(repeated)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold an item of ``benchmark``."""
    leaks = _keyed(decontamination.find_leaks(docs, table(spark, sf_dir, "benchmark")).select("doc_id", "text_key").distinct())
    return docs.join(leaks, _same_row(docs), "left_anti").select(*docs.columns)


def mask_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Masks live-looking secrets in the texts; widely copied examples and all documents stay."""
    return secrets.redact(docs, secrets.find_secrets(docs))


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into sequences of 4096 tokens."""
    return packing.pack(docs)


STAGES = [
    ("toxicity", drop_toxic),
    ("minhash_near_dedup", drop_near_duplicates),
    ("decontamination", drop_contaminated),
    ("secrets", mask_secrets),
    ("packing", pack_sequences),
]

#: SQL can express neither the classifier nor the tokenizer.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        path = f"{folder}/{k}-{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
