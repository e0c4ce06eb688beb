"""The queries of this subpackage and their SQL."""

from facetsel.llm import chat, decontam, licences, lines, mixing, near, quality, rules, substrings, tokens


def queries():
    return {
        "op1_mix": mixing.op1_mix,
        "op2_substrings": substrings.op2_substrings,
        "op3_quality": quality.op3_quality,
        "op4_chat": chat.op4_chat,
        "op5_decontaminate": decontam.op5_decontaminate,
        "op6_tokens": tokens.op6_tokens,
        "op7_near": near.op7_near,
        "op8_licences": licences.op8_licences,
        "op9_rules": rules.op9_rules,
        "op10_lines": lines.op10_lines,
    }


def oracle_sql():
    return {"op1_mix": mixing.OP1_SQL, "op2_substrings": substrings.OP2_SQL, "op4_chat": chat.OP4_SQL, "op7_near": near.OP7_SQL, "op8_licences": licences.OP8_SQL}
