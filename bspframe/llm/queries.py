"""The queries of this subpackage, each over its whole tables, and SQL where it can express them."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import functions as F

from bspframe.llm import audio, bpe, fingerprints, line_dedup, ngram_join, packing, secrets, sharding, toxicity, url_filter


def _table(spark, sf_dir, name):
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _docs(spark, sf_dir):
    return _table(spark, sf_dir, "documents").select("doc_id", "text")


def op1_media_audio(spark, sf_dir):
    """Every text as the payload of an MPEG audio stream, read back and measured."""
    return audio.round_trip(_docs(spark, sf_dir))


def op2_url_filter(spark, sf_dir):
    """Verdict on every page's url by rules, else by host reputation learned from the labels of equal id."""
    labels = _table(spark, sf_dir, "labels").select(F.col("doc_id").alias("page_id"), F.col("quality").alias("good"))
    return url_filter.judge(_table(spark, sf_dir, "pages").select("page_id", "url"), labels)


def op3_line_dedup(spark, sf_dir):
    """Lines of 40 characters and more in 5 and more documents stay in the largest doc_id only."""
    return line_dedup.dedup_lines(_docs(spark, sf_dir)).select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


def op4_ngram_join(spark, sf_dir):
    """Components of documents whose 3-word shingle sets have a Jaccard similarity of 0.9 or more."""
    return ngram_join.jaccard_components(_docs(spark, sf_dir), width=3, num=90, den=100)


def op5_sharding(spark, sf_dir):
    """Jump consistent hashing of all documents to 24 shards."""
    return sharding.shard(_docs(spark, sf_dir), 24)


def op6_bpe(spark, sf_dir):
    """Byte-level BPE ids of every text and their decoding."""
    return bpe.round_trip_digests(_docs(spark, sf_dir), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)


def op7_toxicity(spark, sf_dir):
    """Toxicity score of every document."""
    return toxicity.judge(_docs(spark, sf_dir), _table(spark, sf_dir, "labels").select("doc_id", "toxic"))


def op8_fingerprints(spark, sf_dir):
    """Bottom-k sketches of every text and its edited form, and their likeness."""
    found = fingerprints.compare_with_edits(_docs(spark, sf_dir))
    return found.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), fingerprints.as_text("sketch").alias("fingerprint"), fingerprints.as_text("edited_sketch").alias("edited_fingerprint"), "near_edited", "near_next", "distinct_shingles")


def op9_packing(spark, sf_dir):
    """All documents packed into sequences of 1024 tokens."""
    return packing.pack(_docs(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))


def op10_secrets(spark, sf_dir):
    """Secrets of every text, scanned once for each content."""
    return secrets.digests(secrets.scan(_docs(spark, sf_dir)))


QUERIES = {f.__name__: f for f in (op1_media_audio, op2_url_filter, op3_line_dedup, op4_ngram_join, op5_sharding, op6_bpe, op7_toxicity, op8_fingerprints, op9_packing, op10_secrets)}
ORACLES = {"op2_url_filter": url_filter.oracle(), "op3_line_dedup": line_dedup.ORACLE}
