"""Queries of the text operators and their SQL."""

from . import chat_format, decontaminate, embedding_join, language_id, line_dedup, ngram_join, personal_data, pieces, token_counts, url_filter

QUERIES = {
    "op1_decontamination": decontaminate.op1_decontamination,
    "op2_token_counts": token_counts.op2_token_counts,
    "op3_language_id": language_id.op3_language_id,
    "op4_embedding_join": embedding_join.op4_embedding_join,
    "op5_chat_formatting": chat_format.op5_chat_formatting,
    "op6_line_dedup": line_dedup.op6_line_dedup,
    "op7_ngram_join": ngram_join.op7_ngram_join,
    "op8_personal_data": personal_data.op8_personal_data,
    "op9_url_filter": url_filter.op9_url_filter,
    "op10_pieces": pieces.op10_pieces,
}

#: the others have no SQL form and are tested against brute force
ORACLE_SQL = {
    "op4_embedding_join": embedding_join.OP4_SQL,
    "op5_chat_formatting": chat_format.OP5_SQL,
    "op6_line_dedup": line_dedup.OP6_SQL,
    "op7_ngram_join": ngram_join.OP7_SQL,
    "op9_url_filter": url_filter.OP9_SQL,
}
