"""Queries of this subpackage for ``__spark_entry__``."""

from __future__ import annotations

import corpus_pipeline
from rgsketch.llm import decontaminate, language_id, license_scan, media, mixing, near_dedup, secret_scan, sharding, suffix_dedup, url_filter


def queries() -> dict:
    return {
        "pipeline": corpus_pipeline.run,
        "op1_decontaminate": decontaminate.query,
        "op2_shard": sharding.query,
        "op3_media": media.query,
        "op4_near_dedup": near_dedup.query,
        "op5_secrets": secret_scan.query,
        "op6_language_id": language_id.query,
        "op7_suffix_dedup": suffix_dedup.query,
        "op8_url_filter": url_filter.query,
        "op9_mix": mixing.query,
        "op10_licenses": license_scan.query,
    }


def oracle_sql() -> dict[str, str]:
    return {"op4_near_dedup": near_dedup.ORACLE, "op8_url_filter": url_filter.ORACLE, "op9_mix": mixing.ORACLE}
