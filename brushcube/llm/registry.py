"""The queries of this subpackage, by name, and their SQL."""

from __future__ import annotations

from . import decontaminate, fingerprint, html_extract, jaccard_join, license_scan, mixing, token_count, toxicity, url_filter, warc

_MODULES = {
    "op1_jaccard_join": jaccard_join, "op2_url_filters": url_filter, "op3_warc": warc, "op4_mixing": mixing, "op5_toxicity": toxicity, "op6_fingerprints": fingerprint,
    "op7_decontamination": decontaminate, "op8_license_scans": license_scan, "op9_token_counts": token_count, "op10_html_extraction": html_extract,
}


def queries() -> dict:
    import corpus_pipeline

    return {name: m.query for name, m in _MODULES.items()} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    import corpus_pipeline

    found = {name: m.ORACLE_SQL for name, m in _MODULES.items() if m.ORACLE_SQL}
    return found | ({"pipeline": corpus_pipeline.ORACLE_SQL} if corpus_pipeline.ORACLE_SQL else {})
