"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from . import fingerprints, html, packing, pii, quality, sentencepiece_fst, simhash, token_counts, toxicity, warc


def queries() -> dict:
    return {
        "op1_fingerprints": fingerprints.op1_fingerprints,
        "op2_sentencepiece": sentencepiece_fst.op2_sentencepiece,
        "op3_pii": pii.op3_pii,
        "op4_main_text": html.op4_main_text,
        "op5_simhash": simhash.op5_simhash,
        "op6_quality_rules": quality.op6_quality_rules,
        "op7_packing": packing.op7_packing,
        "op8_toxicity": toxicity.op8_toxicity,
        "op9_fixity": warc.op9_fixity,
        "op10_token_counts": token_counts.op10_token_counts,
    }


def oracle_sql() -> dict[str, str]:
    return {"op6_quality_rules": quality.ORACLE, "op9_fixity": warc.ORACLE}
