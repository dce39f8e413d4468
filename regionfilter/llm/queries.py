"""The queries of this subpackage by name, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from . import bpe_roundtrip, chat, exact_dedup, html_text, licenses, packing, quality, simhash, token_counts, topk

QUERIES = {
    "op1_exact_dedup": exact_dedup.op1_exact_dedup,
    "op2_topk": topk.op2_topk,
    "op3_html_text": html_text.op3_html_text,
    "op4_token_counts": token_counts.op4_token_counts,
    "op5_chat_format": chat.op5_chat_format,
    "op6_packing": packing.op6_packing,
    "op7_bpe_roundtrip": bpe_roundtrip.op7_bpe_roundtrip,
    "op8_licenses": licenses.op8_licenses,
    "op9_quality": quality.op9_quality,
    "op10_simhash": simhash.op10_simhash,
}
ORACLES = {"op1_exact_dedup": exact_dedup.ORACLE, "op2_topk": topk.ORACLE, "op5_chat_format": chat.ORACLE}
