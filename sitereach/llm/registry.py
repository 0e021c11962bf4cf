"""Queries of the corpus operators and the SQL of those that SQL can express."""

from __future__ import annotations

from . import bytebpe, decontaminate, linear, neardup, permindex, personal, piececount, suffixdedup, tokenfiles


def queries() -> dict:
    found = (suffixdedup.op1_repeated_strings, tokenfiles.op2_token_files, neardup.op3_near_duplicates, linear.op4_quality, linear.op5_toxicity, piececount.op6_token_counts, personal.op7_personal_data, bytebpe.op8_byte_bpe, decontaminate.op9_decontaminate, permindex.op10_nearest)
    return {f.__name__: f for f in found}


def oracle_sql() -> dict[str, str]:
    return {"op3_near_duplicates": neardup.ORACLE, "op9_decontaminate": decontaminate.ORACLE}
