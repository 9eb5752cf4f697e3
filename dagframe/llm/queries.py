"""Queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from dagframe.llm import chat, embeddings, html, lines, order_minhash, packing, piece_lattice, quality, simhash, wordbpe


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_simhash_dedup": simhash.op1_simhash_dedup,
        "op2_sentencepiece": piece_lattice.op2_sentencepiece,
        "op3_chat_format": chat.op3_chat_format,
        "op4_quality_classifier": quality.op4_quality_classifier,
        "op5_token_counts": wordbpe.op5_token_counts,
        "op6_embedding_dedup": embeddings.op6_embedding_dedup,
        "op7_html_main_text": html.op7_html_main_text,
        "op8_best_fit_packing": packing.op8_best_fit_packing,
        "op9_order_minhash": order_minhash.op9_order_minhash,
        "op10_line_dedup": lines.op10_line_dedup,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op3_chat_format": chat.OP3_SQL,
        "op10_line_dedup": lines.OP10_SQL,
    }
