"""Queries of the training-data operators, by name, and their SQL where it can express them."""

from . import decontaminate, html_extract, language_id, license_scan, mixing, near_dedup, token_output, topk, toxicity, url_filter

QUERIES = {
    "op1_license_scan": license_scan.op1_license_scan,
    "op2_html_extraction": html_extract.op2_html_extraction,
    "op3_topk": topk.op3_topk,
    "op4_token_output": token_output.op4_token_output,
    "op5_toxicity": toxicity.op5_toxicity,
    "op6_language_id": language_id.op6_language_id,
    "op7_minhash": near_dedup.op7_minhash,
    "op8_mixing": mixing.op8_mixing,
    "op9_decontamination": decontaminate.op9_decontamination,
    "op10_url_filter": url_filter.op10_url_filter,
}
ORACLES = {"op1_license_scan": license_scan.OP1_SQL, "op3_topk": topk.OP3_SQL, "op8_mixing": mixing.OP8_SQL, "op9_decontamination": decontaminate.OP9_SQL, "op10_url_filter": url_filter.OP10_SQL}
