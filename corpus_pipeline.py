"""Corpus pipeline: toxicity, line dedup, near duplicates, secrets, packing.

Each stage reads what its predecessor wrote. All but the last return the columns of ``documents``.

Defined results: null and empty texts are clean, have no lines to lose, link with nothing and pack as their end token; null
ids are documents of their own; of rows that repeat both doc_id and text one stays, a repeated doc_id with another text
is a document of its own; among equally near copies the least doc_id stays (a null one only where no other is there);
texts of any length are read whole; columns beyond those of ``documents`` are left behind; an empty table gives no rows.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession, functions as F

from bspframe.llm import line_dedup, ngram_join, packing, secrets, toxicity
from bspframe.session import materialise

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]
#: The stages are not expressible in SQL as a whole (a trained model, a tokenizer); tests hold them against brute force.
ORACLE_SQL = None


def _with_text(docs: DataFrame, text) -> DataFrame:
    return docs.withColumn("text", text).withColumn("n_chars", F.char_length("text").cast("long")).select(*COLUMNS)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go; it learns from labels outside the held-out fold."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    model = toxicity.train(docs, labels.where(~toxicity.held_out(F.col("doc_id"))))
    return toxicity.score(docs, model, COLUMNS).where("score < 0.5").select(*COLUMNS)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of 40 or more characters found in 5 or more documents stay in one of them."""
    return _with_text(line_dedup.dedup_lines(docs.select(*COLUMNS)), F.col("kept_text"))


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document, the least doc_id, of each group of near duplicates stays (five words, 0.8).

    Texts of a repeated or null doc_id are documents of their own; of identical rows one stays.
    """
    docs = docs.select(*COLUMNS)
    if docs.groupBy("doc_id").count().where("count > 1 or doc_id is null").isEmpty():
        return docs.join(_near_copies(docs.select("doc_id", "text")), "doc_id", "left_anti").select(*COLUMNS)
    rows = materialise(docs.withColumn("_print", F.xxhash64(F.coalesce("text", F.lit("")))).dropDuplicates(["doc_id", "_print"]), "rows")
    order = [F.col("doc_id").asc_nulls_last(), F.col("_print").asc()]
    keyed = materialise(rows.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("_key", F.monotonically_increasing_id()), "keyed")  # keys rise with doc_id
    gone = _near_copies(keyed.select(F.col("_key").alias("doc_id"), "text")).withColumnRenamed("doc_id", "_key")
    return keyed.join(gone, "_key", "left_anti").select(*COLUMNS)


def _near_copies(docs: DataFrame) -> DataFrame:
    """doc_id of documents that are near duplicates of one of a lesser doc_id, over any number of steps."""
    found = ngram_join.jaccard_components(docs, width=5, num=80, den=100)
    return found.where("component_id <> doc_id").select("doc_id")


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets are cut out of the texts; the documents stay."""
    return _with_text(secrets.redact(secrets.scan(docs.select(*COLUMNS))), F.col("text"))


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token sequences of at most 1024."""
    return packing.pack(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [("toxicity", drop_toxic), ("line_dedup", drop_lines), ("ngram_join", drop_near_copies), ("secret_scan", redact_secrets), ("packing", pack)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read back by the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = materialise(docs, f"pipeline-{name}")
    return docs
