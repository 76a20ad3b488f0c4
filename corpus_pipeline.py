"""The corpus pipeline: quality rules, near-dedup, repeated passages, benchmark leaks, byte-level BPE."""

from __future__ import annotations

from pyspark.sql import functions as F

from sparsetier.llm import byte_bpe, decontaminate, near_dedup, quality_rules, suffix_dedup
from sparsetier.llm.common import materialize, table


def counted(docs, columns):
    """``docs`` with n_chars, if the table has it, brought up to date with the text."""
    return (docs.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in columns else docs).select(columns)


def quality(spark, docs, sf_dir):
    """Rejected documents go; in kept ones the failing lines go."""
    return counted(quality_rules.clean_documents(docs), docs.columns)


def numbered(docs):
    """Rows with a number of their own, ``_row``, as a doc_id may be null or stand on several rows; written, so that numbers hold."""
    return materialize(docs.withColumn("_row", F.monotonically_increasing_id()), "numbered")


def near_duplicates(spark, docs, sf_dir):
    """One row of each group stays: the one with the smallest doc_id, null last. Every row is judged by its own text, whatever its
    doc_id; rows without words count once per doc_id, and all stay where that is null."""
    rows = numbered(docs)
    found = near_dedup.near_components(rows.select(F.col("_row").alias("doc_id"), "text")).withColumnRenamed("doc_id", "_row")
    wordless = (F.col("n_shingles") == 0) & F.col("doc_id").isNotNull()
    groups = found.join(rows.select("_row", "doc_id"), "_row").groupBy(
        F.when(~wordless, F.col("component_id")).alias("component"), F.when(wordless, F.col("doc_id")).alias("same_id"))
    kept = groups.agg(F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "_row")).alias("first")).select("first._row")
    return rows.join(kept, "_row", "left_semi").select(docs.columns)


def repeated_passages(spark, docs, sf_dir):
    """Passages of over 50 words and strings of 400 bytes that occur twice are cut out; every document stays, maybe shorter."""
    return counted(suffix_dedup.remove_repeats(docs, words=suffix_dedup.PASSAGE), docs.columns)


def benchmark_leaks(spark, docs, sf_dir):
    """Rows that contain a benchmark item go, each judged by its own text."""
    rows = numbered(docs)
    hit = decontaminate.contaminated(rows.select(F.col("_row").alias("doc_id"), "text"), table(spark, sf_dir, "benchmark"))
    return rows.join(hit.select(F.col("doc_id").alias("_row")).distinct(), "_row", "left_anti").select(docs.columns)


def tokens(spark, docs, sf_dir):
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of what is left."""
    return byte_bpe.digests(byte_bpe.encode_blocks(docs))


STAGES = [("quality_rules", quality), ("near_dedup", near_duplicates), ("suffix_dedup", repeated_passages),
          ("decontaminate", benchmark_leaks), ("byte_bpe", tokens)]

#: Only the first stage could be SQL; tests/llm/test_pipeline.py holds every stage, and the whole run on sf0.001, against plain versions.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"stage_{name}")
    return docs
