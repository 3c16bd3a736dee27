"""Queries of this subpackage, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from . import bytebpe, chat, covers, packing, pivots, quality, recompress, secrets, setjoin, toxicity


def queries() -> dict:
    return {
        "op1_secrets": secrets.op1_secrets,
        "op2_chat": chat.op2_chat,
        "op3_bytebpe": bytebpe.op3_bytebpe,
        "op4_jaccard": setjoin.op4_jaccard,
        "op5_substrings": recompress.op5_substrings,
        "op6_suffixes": covers.op6_suffixes,
        "op7_pivots": pivots.op7_pivots,
        "op8_quality": quality.op8_quality,
        "op10_toxicity": toxicity.op10_toxicity,
        "op9_pack": packing.op9_pack,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_secrets": secrets.ORACLE, "op2_chat": chat.ORACLE, "op4_jaccard": setjoin.ORACLE, "op5_substrings": recompress.ORACLE, "op6_suffixes": covers.ORACLE, "op7_pivots": pivots.ORACLE}
