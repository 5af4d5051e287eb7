"""The opN_ queries and, where SQL can express one, its oracle."""

from __future__ import annotations

from graphdist.llm import (
    ann_search, chat_format, decontaminate, html_extract, language_id, line_dedup, packing, simhash_dedup, substring_dedup, url_filter,
)


def queries():
    return {
        "op1_line_dedup": line_dedup.op1_line_dedup,
        "op2_url_filter": url_filter.op2_url_filter,
        "op3_packing": packing.op3_packing,
        "op4_chat_format": chat_format.op4_chat_format,
        "op5_simhash_dedup": simhash_dedup.op5_simhash_dedup,
        "op6_html_extract": html_extract.op6_html_extract,
        "op7_decontaminate": decontaminate.op7_decontaminate,
        "op8_ann_search": ann_search.op8_ann_search,
        "op9_substring_dedup": substring_dedup.op9_substring_dedup,
        "op10_language_id": language_id.op10_language_id,
    }


def oracle_sql():
    return {"op2_url_filter": url_filter.OP2_SQL, "op4_chat_format": chat_format.OP4_SQL}
