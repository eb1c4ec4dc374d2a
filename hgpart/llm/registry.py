"""The corpus operators' queries and SQL equivalents."""

from __future__ import annotations

import corpus_pipeline
from hgpart.llm import decontamination, html_text, licenses, pieces, pii, quality, sharding, simhash, suffix_dedup, token_counts
from hgpart.llm.quality_sql import report_sql
from hgpart.llm.tables import table


def op1_template_extraction(spark, sf_dir):
    return html_text.extract(table(spark, sf_dir, "pages"))


def op2_cgk_decontamination(spark, sf_dir):
    return decontamination.contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op3_jump_sharding(spark, sf_dir):
    return sharding.shard_documents(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op4_length_histogram(spark, sf_dir):
    return token_counts.suffix_sums(token_counts.length_histogram(table(spark, sf_dir, "documents")))


def op5_suffix_dedup(spark, sf_dir):
    return suffix_dedup.repeat_report(table(spark, sf_dir, "documents"))


def op6_surrogates(spark, sf_dir):
    return pii.replace_entities(table(spark, sf_dir, "documents").select("doc_id", "text"), pii.session_key(spark))


def op7_suffix_array_pieces(spark, sf_dir):
    return pieces.token_digests(table(spark, sf_dir, "documents"))


def op8_license_scan(spark, sf_dir):
    return licenses.scan(table(spark, sf_dir, "documents"))


def op9_anchor_covering(spark, sf_dir):
    return simhash.near_duplicate_groups(table(spark, sf_dir, "documents"))


def op10_distribution_divergence(spark, sf_dir):
    return quality.quality_report(table(spark, sf_dir, "documents"))


def queries() -> dict:
    return {
        "pipeline": corpus_pipeline.run,
        "op1_template_extraction": op1_template_extraction,
        "op2_cgk_decontamination": op2_cgk_decontamination,
        "op3_jump_sharding": op3_jump_sharding,
        "op4_length_histogram": op4_length_histogram,
        "op5_suffix_dedup": op5_suffix_dedup,
        "op6_surrogates": op6_surrogates,
        "op7_suffix_array_pieces": op7_suffix_array_pieces,
        "op8_license_scan": op8_license_scan,
        "op9_anchor_covering": op9_anchor_covering,
        "op10_distribution_divergence": op10_distribution_divergence,
    }


def oracle_sql() -> dict:
    found = {"op8_license_scan": licenses.scan_sql(), "op10_distribution_divergence": report_sql()}
    if corpus_pipeline.ORACLE_SQL:
        found["pipeline"] = corpus_pipeline.ORACLE_SQL
    return found
