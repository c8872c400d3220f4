"""The queries of this subpackage and their SQL, for ``__spark_entry__.py``."""

from __future__ import annotations

from . import exact_dedup, license_scan, line_dedup, media, near_dedup, packing, pii, piece_lattice, token_store, toxicity


def queries() -> dict:
    return {
        "op1_sentencepiece": piece_lattice.query,
        "op2_exact_dedup": exact_dedup.query,
        "op3_media_columns": media.query,
        "op4_toxicity": toxicity.query,
        "op5_token_store": token_store.query,
        "op6_line_dedup": line_dedup.query,
        "op7_license_scan": license_scan.query,
        "op8_packing": packing.query,
        "op9_pii_spans": pii.query,
        "op10_near_dedup": near_dedup.query,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op2_exact_dedup": exact_dedup.ORACLE,
        "op6_line_dedup": line_dedup.ORACLE,
        "op7_license_scan": license_scan.oracle(),
    }
