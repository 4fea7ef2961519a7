"""The queries of this package and their oracles, by name."""

from __future__ import annotations

from . import bpe, exact_dedup, imi, katz, langid, line_dedup, mixing, pii, simhash, url_rules

QUERIES = {
    "op1_url_rules": url_rules.op1_url_rules,
    "op2_language_id": langid.op2_language_id,
    "op3_exact_dedup": exact_dedup.op3_exact_dedup,
    "op4_line_dedup": line_dedup.op4_line_dedup,
    "op5_katz_lm": katz.op5_katz_lm,
    "op6_pii": pii.op6_pii,
    "op7_simhash": simhash.op7_simhash,
    "op8_multi_index": imi.op8_multi_index,
    "op9_mixing": mixing.op9_mixing,
    "op10_byte_bpe": bpe.op10_byte_bpe,
}

ORACLES = {"op1_url_rules": url_rules.ORACLE, "op3_exact_dedup": exact_dedup.ORACLE, "op4_line_dedup": line_dedup.ORACLE, "op9_mixing": mixing.ORACLE}
