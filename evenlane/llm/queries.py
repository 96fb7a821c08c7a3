"""Queries of the training-data operators and their SQL."""

from __future__ import annotations

from evenlane.llm.chat import CHAT_SQL, chat_query
from evenlane.llm.near_dup import NEAR_DUP_SQL, near_dup_query
from evenlane.llm.packing import packing_query
from evenlane.llm.quality import QUALITY_SQL, quality_query
from evenlane.llm.secrets import SECRETS_SQL, secrets_query
from evenlane.llm.sentence_pieces import sentence_pieces_query
from evenlane.llm.token_counts import token_counts_query
from evenlane.llm.token_files import token_files_query
from evenlane.llm.topk import TOP_K_SQL, top_k_query
from evenlane.llm.url_filter import url_filter_query, url_filter_sql

QUERIES = {
    "op1_minhash_near_dup": near_dup_query,
    "op2_secret_scan": secrets_query,
    "op3_token_counts": token_counts_query,
    "op4_sentence_pieces": sentence_pieces_query,
    "op5_quality_rules": quality_query,
    "op6_token_files": token_files_query,
    "op7_url_filter": url_filter_query,
    "op8_exact_top_k": top_k_query,
    "op9_tool_calls": chat_query,
    "op10_packing": packing_query,
}


def oracle_sql() -> dict[str, str]:
    """SQL of the queries that SQL can express; the URL model is fitted here."""
    return {
        "op1_minhash_near_dup": NEAR_DUP_SQL,
        "op2_secret_scan": SECRETS_SQL,
        "op5_quality_rules": QUALITY_SQL,
        "op7_url_filter": url_filter_sql(),
        "op8_exact_top_k": TOP_K_SQL,
        "op9_tool_calls": CHAT_SQL,
    }
