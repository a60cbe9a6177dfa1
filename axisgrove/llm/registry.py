"""Queries of this subpackage and their DuckDB twins."""

from __future__ import annotations

from axisgrove.llm import decontaminate, html_text, jaccard_join, kd_sharding, line_rules, mixing, personal_data, quotations, suffix_dedup, url_filter

QUERIES = {
    "op1_pareto_mix": mixing.op1_pareto_mix,
    "op2_suffix_dedup": suffix_dedup.op2_suffix_dedup,
    "op3_quotations": quotations.op3_quotations,
    "op4_html_text": html_text.op4_html_text,
    "op5_personal_data": personal_data.op5_personal_data,
    "op6_kd_shards": kd_sharding.op6_kd_shards,
    "op7_line_rules": line_rules.op7_line_rules,
    "op8_decontaminate": decontaminate.op8_decontaminate,
    "op9_jaccard_join": jaccard_join.op9_jaccard_join,
    "op10_url_filter": url_filter.op10_url_filter,
}

ORACLE_SQL = {
    "op1_pareto_mix": mixing.OP1_SQL,
    "op3_quotations": quotations.OP3_SQL,
    "op7_line_rules": line_rules.OP7_SQL,
    "op8_decontaminate": decontaminate.OP8_SQL,
    "op9_jaccard_join": jaccard_join.OP9_SQL,
}
