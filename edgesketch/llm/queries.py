"""The queries of this subpackage, by name, and the SQL of those that SQL can express."""

from __future__ import annotations

from edgesketch.llm import classifier, decontam, html_text, jaccard, packing, quality_rules, suffix_dedup, token_files, tokens, url_filter


def queries() -> dict:
    return {
        "op1_benchmark_decontamination": decontam.query,
        "op2_best_fit_packing": packing.query,
        "op3_quality_rules": quality_rules.query,
        "op4_url_filters": url_filter.query,
        "op5_suffix_array_dedup": suffix_dedup.query,
        "op6_token_files": token_files.query,
        "op7_html_extraction": html_text.query,
        "op8_token_counts": tokens.query,
        "op9_ngram_jaccard_join": jaccard.query,
        "op10_quality_classifier": classifier.query,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_benchmark_decontamination": decontam.ORACLE,
        "op3_quality_rules": quality_rules.ORACLE,
        "op4_url_filters": url_filter.ORACLE,
        "op9_ngram_jaccard_join": jaccard.ORACLE,
    }
