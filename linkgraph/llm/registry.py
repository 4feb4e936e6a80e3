"""Queries of the training-data operators and their SQL twins."""

from __future__ import annotations

from linkgraph.llm import ann, bpe, decontaminate, licenses, near_dup, pii, quality, suffix_dedup, toxicity, warc


def queries() -> dict:
    return {
        "op1_suffix_dedup": suffix_dedup.op1_suffix_dedup,
        "op2_toxicity": toxicity.op2_toxicity,
        "op3_bpe": bpe.op3_bpe,
        "op4_ann": ann.op4_ann,
        "op5_pii": pii.op5_pii,
        "op6_warc": warc.op6_warc,
        "op7_licenses": licenses.op7_licenses,
        "op8_quality": quality.op8_quality,
        "op9_near_dup": near_dup.op9_near_dup,
        "op10_decontaminate": decontaminate.op10_decontaminate,
    }


def oracle_sql() -> dict[str, str]:
    return {"op6_warc": warc.OP6_SQL}
