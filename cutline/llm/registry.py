"""Names of the corpus queries, and the SQL that checks those that SQL can express."""

from __future__ import annotations

from . import avi, html_text, language, line_dedup, mixing, near_dup, packing, sharding, topk, toxicity


def queries() -> dict:
    return {
        "op1_maxscore": topk.op1_maxscore,
        "op2_rendezvous": sharding.op2_rendezvous,
        "op3_entropy_mix": mixing.op3_entropy_mix,
        "op4_line_dedup": line_dedup.op4_line_dedup,
        "op5_best_fit": packing.op5_best_fit,
        "op6_avi": avi.op6_avi,
        "op7_main_text": html_text.op7_main_text,
        "op8_toxicity": toxicity.op8_toxicity,
        "op9_jaccard": near_dup.op9_jaccard,
        "op10_language": language.op10_language,
    }


def oracle_sql() -> dict[str, str]:
    return {"op1_maxscore": topk.OP1_SQL, "op4_line_dedup": line_dedup.OP4_SQL, "op9_jaccard": near_dup.OP9_SQL}
