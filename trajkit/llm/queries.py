"""Queries of this subpackage and their SQL, by name."""

from . import decontamination, language, mixing, order_minhash, ppm, resharding, secrets, suffix_dedup, topk, toxicity

QUERIES = {
    "op1_exact_top_k": topk.op1_exact_top_k,
    "op10_order_minhash": order_minhash.op10_order_minhash,
    "op2_language_id": language.op2_language_id,
    "op3_suffix_dedup": suffix_dedup.op3_suffix_dedup,
    "op4_ppm_score": ppm.op4_ppm_score,
    "op5_reshard": resharding.op5_reshard,
    "op6_toxicity": toxicity.op6_toxicity,
    "op7_secrets": secrets.op7_secrets,
    "op8_decontaminate": decontamination.op8_decontaminate,
    "op9_mix_curriculum": mixing.op9_mix_curriculum,
}
ORACLES = {"op1_exact_top_k": topk.ORACLE, "op8_decontaminate": decontamination.ORACLE, "op9_mix_curriculum": mixing.ORACLE}
