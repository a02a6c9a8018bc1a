"""Named queries of the text operators, and the DuckDB text of those that SQL can express."""

from __future__ import annotations

import public_tokenizers

from . import bpe, decontaminate, html_extract, language_id, license_scan, near_dedup, pii, quality_lm, quality_rules, token_count
from .common import documents


def op1_language_id(spark, sf_dir):
    docs = documents(spark, sf_dir, "doc_id", "text", "lang")
    model = language_id.train(docs)
    found = language_id.identify(docs, model)
    return found.select("doc_id", language_id.is_held_out().alias("held_out"), "lang_pred", "score", "bits", "rejected")


def op2_byte_bpe(spark, sf_dir):
    docs = documents(spark, sf_dir, "doc_id", "text")
    return bpe.digests(bpe.encode(docs, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN))


def op3_license_scan(spark, sf_dir):
    return license_scan.scan(documents(spark, sf_dir, "doc_id", "text")).drop("places")


def op4_token_counts(spark, sf_dir):
    return token_count.count_tokens(documents(spark, sf_dir, "doc_id", "text"), public_tokenizers.path("byte_bpe_50k.json"))


def op5_quality_rules(spark, sf_dir):
    docs = documents(spark, sf_dir, "doc_id", "text", "lang")
    return quality_rules.judge(docs)


def op6_pii_surrogates(spark, sf_dir):
    return pii.pseudonymise(documents(spark, sf_dir, "doc_id", "text"), pii.session_key(spark))


def op7_quality_lm(spark, sf_dir):
    return quality_lm.classify(documents(spark, sf_dir, "doc_id", "text", "lang"), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op8_html_extract(spark, sf_dir):
    return html_extract.extract(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op9_near_duplicates(spark, sf_dir):
    return near_dedup.classes(documents(spark, sf_dir, "doc_id", "text"))


def op10_decontamination(spark, sf_dir):
    return decontaminate.find_leaks(documents(spark, sf_dir, "doc_id", "text"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def pipeline(spark, sf_dir):
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def queries():
    return {
        "op1_language_id": op1_language_id,
        "op2_byte_bpe": op2_byte_bpe,
        "op3_license_scan": op3_license_scan,
        "op4_token_counts": op4_token_counts,
        "op5_quality_rules": op5_quality_rules,
        "op6_pii_surrogates": op6_pii_surrogates,
        "op7_quality_lm": op7_quality_lm,
        "op8_html_extract": op8_html_extract,
        "op9_near_duplicates": op9_near_duplicates,
        "op10_decontamination": op10_decontamination,
        "pipeline": pipeline,
    }


def oracle_sql():
    return {}
