"""The queries of this subpackage, and their SQL where SQL can express them."""

from . import chat_format, chunk_dedup, exact_dedup, language_id, line_dedup, mixing, packing, simhash, suffix_dedup, topk_search

QUERIES = {
    "op1_best_fit_packing": packing.op1_best_fit_packing,
    "op2_source_mixing": mixing.op2_source_mixing,
    "op3_language_id": language_id.op3_language_id,
    "op4_exact_dedup": exact_dedup.op4_exact_dedup,
    "op5_exact_topk": topk_search.op5_exact_topk,
    "op6_simhash_near_dedup": simhash.op6_simhash_near_dedup,
    "op7_line_dedup": line_dedup.op7_line_dedup,
    "op8_chat_format": chat_format.op8_chat_format,
    "op9_chunk_dedup": chunk_dedup.op9_chunk_dedup,
    "op10_suffix_dedup": suffix_dedup.op10_suffix_dedup,
}
ORACLE_SQL = exact_dedup.SQL | topk_search.SQL | line_dedup.SQL | chat_format.SQL
