"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from . import bit_topk, budget_mix, license_scan, near_dup, packing, ppm, quality_lines, toxicity, url_templates, warc


def queries() -> dict:
    return {
        "op1_ppm": ppm.op1_ppm,
        "op2_budget_mix": budget_mix.op2_budget_mix,
        "op3_bit_sliced_topk": bit_topk.op3_bit_sliced_topk,
        "op4_warc": warc.op4_warc,
        "op5_license_digests": license_scan.op5_license_digests,
        "op6_toxicity": toxicity.op6_toxicity,
        "op7_line_quality": quality_lines.op7_line_quality,
        "op8_url_templates": url_templates.op8_url_templates,
        "op9_near_duplicates": near_dup.op9_near_duplicates,
        "op10_best_fit_packing": packing.op10_best_fit_packing,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_bit_sliced_topk": bit_topk.OP3_SQL,
        "op4_warc": warc.OP4_SQL,
        "op5_license_digests": license_scan.OP5_SQL,
        "op7_line_quality": quality_lines.OP7_SQL,
        "op8_url_templates": url_templates.OP8_SQL,
        "op9_near_duplicates": near_dup.OP9_SQL,
    }
