"""The operators' queries and their SQL."""

from __future__ import annotations

from . import decontaminate, exact_dedup, license_scan, line_dedup, near_dedup, packing, quality, secret_scan, token_count, warc

QUERIES = {
    "op2_warc_normaliser": warc.op2_warc_normaliser,
    "op8_license_scan": license_scan.op8_license_scan,
    "op6_line_field_quality": quality.op6_line_field_quality,
    "op7_simhash_decontamination": decontaminate.op7_simhash_decontamination,
    "op1_minhash_near_dedup": near_dedup.op1_minhash_near_dedup,
    "op9_best_fit_packing": packing.op9_best_fit_packing,
    "op3_secret_scan": secret_scan.op3_secret_scan,
    "op4_token_count": token_count.op4_token_count,
    "op5_exact_dedup": exact_dedup.op5_exact_dedup,
    "op10_line_dedup": line_dedup.op10_line_dedup,
}
ORACLE_SQL = {
    "op8_license_scan": license_scan.license_sql(),
    "op5_exact_dedup": exact_dedup.OP5_SQL,
    "op10_line_dedup": line_dedup.OP10_SQL,
}
