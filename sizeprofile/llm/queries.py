"""Registry of the training-data queries and their SQL."""

from __future__ import annotations

from . import bpe, jaccard_join, line_dedup, mixing, quality_gam, quality_rules, substring_dedup, token_files, topk, warc


def queries() -> dict:
    return {
        "op1_jaccard_join": jaccard_join.op1_jaccard_join,
        "op2_line_dedup": line_dedup.op2_line_dedup,
        "op3_token_files": token_files.op3_token_files,
        "op4_warc": warc.op4_warc,
        "op5_quality_rules": quality_rules.op5_quality_rules,
        "op6_mixing": mixing.op6_mixing,
        "op7_top_k": topk.op7_top_k,
        "op8_bpe": bpe.op8_bpe,
        "op9_substring_dedup": substring_dedup.op9_substring_dedup,
        "op10_quality_gam": quality_gam.op10_quality_gam,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_jaccard_join": jaccard_join.OP1_SQL,
        "op2_line_dedup": line_dedup.OP2_SQL,
        "op4_warc": warc.OP4_SQL,
        "op5_quality_rules": quality_rules.OP5_SQL,
        "op7_top_k": topk.OP7_SQL,
        "op9_substring_dedup": substring_dedup.OP9_SQL,
    }
