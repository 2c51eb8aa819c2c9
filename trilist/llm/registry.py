"""Queries of the text operators, and SQL for those that it can express."""

from __future__ import annotations

import corpus_pipeline
from trilist.llm import chat, decontaminate, language, lines, media, mixing, repeats, simhash, tokencount, warc


def queries():
    return {
        "op1_line_spread": lines.op1_line_spread,
        "op2_repeated_windows": repeats.op2_repeated_windows,
        "op3_tool_links": chat.op3_tool_links,
        "chat_messages": chat.chat_messages,
        "op4_simhash_grid": simhash.op4_simhash_grid,
        "simhash_paths": simhash.simhash_paths,
        "op5_family_svm": language.op5_family_svm,
        "op9_suffix_decontamination": decontaminate.op9_suffix_decontamination,
        "op6_digest_cache": tokencount.op6_digest_cache,
        "token_cache_again": tokencount.token_cache_again,
        "op7_media_columns": media.op7_media_columns,
        "op8_source_mix": mixing.op8_source_mix,
        "op10_segment_reassembly": warc.op10_segment_reassembly,
        "pipeline": corpus_pipeline.run,
    }


def oracle_sql():
    return {"op1_line_spread": lines.OP1_SQL, "op3_tool_links": chat.OP3_SQL, "chat_messages": chat.MESSAGES_SQL, "op8_source_mix": mixing.OP8_SQL, "op10_segment_reassembly": warc.OP10_SQL, "op9_suffix_decontamination": decontaminate.OP9_SQL}
