"""The queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from . import chat_format, exact_dedup, license_scan, line_runs, mixing, ngram_join, quality, tiling, toxicity, warc


def queries() -> dict:
    """Query callables by name."""
    return {
        "op1_chat_format": chat_format.op1_chat_format,
        "op2_ngram_jaccard_join": ngram_join.op2_ngram_jaccard_join,
        "op3_quality_classifier": quality.op3_quality_classifier,
        "op4_license_scan": license_scan.op4_license_scan,
        "op5_line_dedup": line_runs.op5_line_dedup,
        "op6_mixing": mixing.op6_mixing,
        "op7_decontamination": tiling.op7_decontamination,
        "op8_toxicity": toxicity.op8_toxicity,
        "op9_exact_dedup": exact_dedup.op9_exact_dedup,
        "op10_warc": warc.op10_warc,
    }


def oracle_sql() -> dict[str, str]:
    """DuckDB text by query name."""
    return {
        "op1_chat_format": chat_format.SQL,
        "op2_ngram_jaccard_join": ngram_join.SQL,
        "op9_exact_dedup": exact_dedup.SQL,
        "op10_warc": warc.SQL,
    }


def further_queries() -> dict:
    """Queries beside the one of each operator."""
    return {"ngram_jaccard_links": ngram_join.ngram_jaccard_links}


def further_sql() -> dict[str, str]:
    """DuckDB text of the further queries."""
    return {"ngram_jaccard_links": ngram_join.LINKS_SQL}
