"""The registered queries of the training-data operators and their SQL."""

from __future__ import annotations

from sparsetier.llm import byte_bpe, decontaminate, license_scan, near_dedup, quality_rules, suffix_dedup, token_counts, token_files, toxicity, warc
from sparsetier.llm.common import table


def op1_suffix_dedup(spark, sf_dir):
    return suffix_dedup.repeat_report(table(spark, sf_dir, "documents"), words=suffix_dedup.PASSAGE)


def op9_near_dedup(spark, sf_dir):
    return near_dedup.near_components(table(spark, sf_dir, "documents"))


def op2_byte_bpe(spark, sf_dir):
    return byte_bpe.digests(byte_bpe.encode_blocks(table(spark, sf_dir, "documents")))


def op3_quality_rules(spark, sf_dir):
    return quality_rules.quality_measures(table(spark, sf_dir, "documents")).select(quality_rules.COLUMNS)


def op4_token_files(spark, sf_dir):
    return token_files.read_shards(*token_files.write_shards(table(spark, sf_dir, "documents")))


def op5_token_counts(spark, sf_dir):
    return token_counts.token_counts(table(spark, sf_dir, "documents"), "byte_bpe_50k.json")


def op6_toxicity(spark, sf_dir):
    return toxicity.toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op7_warc(spark, sf_dir):
    return warc.warc_roundtrip(table(spark, sf_dir, "pages"))


def op8_decontaminate(spark, sf_dir):
    return decontaminate.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op10_license_scan(spark, sf_dir):
    return license_scan.license_scan(table(spark, sf_dir, "documents"))


def queries():
    return {f.__name__: f for f in (op1_suffix_dedup, op2_byte_bpe, op3_quality_rules, op4_token_files, op5_token_counts, op6_toxicity, op7_warc, op8_decontaminate, op9_near_dedup, op10_license_scan)}


def oracle_sql():
    return {"op3_quality_rules": quality_rules.SQL}
