"""Queries and SQL of the corpus operators, for the driver's entry module."""

from __future__ import annotations

from memojoin.llm import bpe, brown_lm, e8_dedup, jaccard_join, kn_quality, langid, mixing, quality_rules, toxicity, warc


def queries() -> dict:
    return {
        "op1_jaccard_join": jaccard_join.op1_jaccard_join,
        "op2_langid": langid.op2_langid,
        "op3_warc": warc.op3_warc,
        "op4_quality_rules": quality_rules.op4_quality_rules,
        "op7_mixing": mixing.op7_mixing,
        "op5_toxicity": toxicity.op5_toxicity,
        "op6_e8_dedup": e8_dedup.op6_e8_dedup,
        "op8_brown_lm": brown_lm.op8_brown_lm,
        "op9_quality_classifier": kn_quality.op9_quality_classifier,
        "op10_bpe": bpe.op10_bpe,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_jaccard_join": jaccard_join.OP1_SQL, "op6_e8_dedup": e8_dedup.OP6_SQL, "op3_warc": warc.OP3_SQL, "op4_quality_rules": quality_rules.OP4_SQL, "op7_mixing": mixing.OP7_SQL}
