"""The operators' queries and, where SQL can express them, their SQL."""

from __future__ import annotations

from bundlemv.llm import additive, langid, mixing, packing, pii, quality, simhash, suffix_dedup, topk, warc


def queries() -> dict:
    return {
        "op1_exact_top_k": topk.op1,
        "op2_suffix_dedup": suffix_dedup.op2,
        "op3_warc_archive": warc.op3,
        "op4_language_mixture": langid.op4,
        "op5_personal_data": pii.op5,
        "op6_quality_discriminant": quality.op6,
        "op7_mix_sources": mixing.op7,
        "op8_additive_search": additive.op8,
        "op9_pack_sequences": packing.op9,
        "op10_simhash_components": simhash.op10,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_exact_top_k": topk.OP1_SQL, "op3_warc_archive": warc.OP3_SQL, "op7_mix_sources": mixing.OP7_SQL}
