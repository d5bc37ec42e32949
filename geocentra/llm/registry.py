"""The queries of the training-data operators and their DuckDB SQL."""

from __future__ import annotations

from geocentra.llm import chat, decontaminate, katz, kneser_ney, minhash, packing, substring_dedup, suffix_dedup, topk, url_rules


def queries() -> dict:
    return {
        "op1_substring_dedup": substring_dedup.op1_substring_dedup,
        "op2_decontaminate": decontaminate.op2_decontaminate,
        "op3_quality_classifier": kneser_ney.op3_quality_classifier,
        "op4_katz_scores": katz.op4_katz_scores,
        "op5_best_fit_packing": packing.op5_best_fit_packing,
        "op6_suffix_dedup": suffix_dedup.op6_suffix_dedup,
        "op7_near_duplicates": minhash.op7_near_duplicates,
        "op8_chat_format": chat.op8_chat_format,
        "op9_url_rules": url_rules.op9_url_rules,
        "op10_top_k": topk.op10_top_k,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_substring_dedup": substring_dedup.ORACLE,
        "op2_decontaminate": decontaminate.ORACLE,
        "op6_suffix_dedup": suffix_dedup.ORACLE,
        "op7_near_duplicates": minhash.ORACLE,
        "op8_chat_format": chat.ORACLE,
        "op10_top_k": topk.ORACLE,
    }
