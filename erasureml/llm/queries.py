"""The registered queries of this subpackage and their SQL, by name."""

from __future__ import annotations

from erasureml.llm import bpe, containment, lm, multiset, pii, simhash, substring, suffix, tokens, toxicity

QUERIES = {
    "op1_toxicity": toxicity.op1_toxicity,
    "op2_suffix_dedup": suffix.op2_suffix_dedup,
    "op3_pii": pii.op3_pii,
    "op4_lm_scoring": lm.op4_lm_scoring,
    "op5_fingerprint": multiset.op5_fingerprint,
    "op6_simhash": simhash.op6_simhash,
    "op7_token_store": tokens.op7_token_store,
    "op8_decontamination": containment.op8_decontamination,
    "op9_substring": substring.op9_substring,
    "op10_byte_bpe": bpe.op10_byte_bpe,
}

ORACLES: dict[str, str] = {"op8_decontamination": containment.ORACLE, "op9_substring": substring.ORACLE}
