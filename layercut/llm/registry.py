"""Queries of the corpus operators and their DuckDB oracles."""

from __future__ import annotations

from . import mixing, near_dups, packing, page_text, quality, repeats, secrets, topk, toxicity, url_rules


def queries() -> dict:
    return {"op1_secrets": secrets.op1_secrets, "op2_url_filters": url_rules.op2_url_filters, "op3_toxicity": toxicity.op3_toxicity, "op4_page_text": page_text.op4_page_text, "op5_near_dups": near_dups.op5_near_dups, "op6_topk": topk.op6_topk, "op7_repeats": repeats.op7_repeats, "op8_quality": quality.op8_quality, "op9_mixing": mixing.op9_mixing, "op10_packing": packing.op10_packing}


def oracle_sql() -> dict[str, str]:
    return {"op1_secrets": secrets.ORACLE, "op6_topk": topk.ORACLE}
