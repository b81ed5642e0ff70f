"""Queries of this subpackage and their SQL."""

from __future__ import annotations

from collections.abc import Callable

import corpus_pipeline
from pyspark.sql import DataFrame, SparkSession

from . import archive, decontamination, langid, licenses, near_dedup, packing, quality, repeats, secrets, urls


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_winnowing_decontamination": decontamination.op1_winnowing_decontamination,
        "op2_signature_license_scan": licenses.op2_signature_license_scan,
        "op3_signature_join_dedup": near_dedup.op3_signature_join_dedup,
        "op4_url_markov_filter": urls.op4_url_markov_filter,
        "op5_crf_secret_scan": secrets.op5_crf_secret_scan,
        "op6_hashed_ratio_quality": quality.op6_hashed_ratio_quality,
        "op7_bm25_packing": packing.op7_bm25_packing,
        "op8_line_hash_dedup": repeats.op8_line_hash_dedup,
        "op9_ftrl_language_id": langid.op9_ftrl_language_id,
        "op10_warc_round_trip": archive.op10_warc_round_trip,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_winnowing_decontamination": decontamination.OP1_SQL, "op3_signature_join_dedup": near_dedup.OP3_SQL, "op10_warc_round_trip": archive.OP10_SQL}
