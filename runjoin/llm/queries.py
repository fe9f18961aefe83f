"""Queries of the text operators and, where SQL can express them, their oracles."""

from __future__ import annotations

from . import bpe, exact_dedup, factor_machine, license_scan, near_dedup, packing, quality_rules, recurrent_lm, token_store, warc

QUERIES = {
    "op1_quality_fm": factor_machine.op1_quality_fm,
    "op2_exact_dedup": exact_dedup.op2_exact_dedup,
    "op3_byte_bpe": bpe.op3_byte_bpe,
    "op4_lm_score": recurrent_lm.op4_lm_score,
    "op5_token_ids": token_store.op5_token_ids,
    "op6_near_dedup": near_dedup.op6_near_dedup,
    "op7_license_scan": license_scan.op7_license_scan,
    "op8_warc": warc.op8_warc,
    "op9_quality_rules": quality_rules.op9_quality_rules,
    "op10_packing": packing.op10_packing,
}

ORACLES = {
    "op2_exact_dedup": exact_dedup.OP2_SQL,
    "op6_near_dedup": near_dedup.OP6_SQL,
    "op8_warc": warc.OP8_SQL,
}
