"""Queries of this subpackage and their SQL."""

from __future__ import annotations

from exkit.llm import chat, language, mixing, packing, quality, shingle_join, toxicity, url_filter, warc, webp

QUERIES = {
    "op1_chat_windows": chat.query,
    "op2_language_id": language.query,
    "op2_language_id_pages": language.query_pages,
    "op3_source_mixing": mixing.query,
    "op4_toxicity_crf": toxicity.query,
    "op5_url_filter": url_filter.query,
    "op6_warc_archives": warc.query,
    "op7_line_quality": quality.query,
    "op8_shingle_join": shingle_join.query,
    "op9_best_fit_packing": packing.query,
    "op10_webp_media": webp.query,
}
SQL = {
    "op3_source_mixing": mixing.SQL,
    "op5_url_filter": url_filter.SQL,
    "op6_warc_archives": warc.SQL,
}
