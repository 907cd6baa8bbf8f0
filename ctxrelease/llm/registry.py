"""Queries of the corpus operators for the entry module."""

from __future__ import annotations

from . import bpe, chat, langid, media, ngram_join, packing, pii, sharding, topk, toxicity


def queries() -> dict:
    return {
        "op1_chat_formatting": chat.op1_chat_formatting,
        "op2_best_fit_packing": packing.op2_best_fit_packing,
        "op3_exact_topk": topk.op3_exact_topk,
        "op4_sharding": sharding.op4_sharding,
        "op5_language_id": langid.op5_language_id,
        "op6_pii": pii.op6_pii,
        "op7_toxicity": toxicity.op7_toxicity,
        "op8_media": media.op8_media,
        "media_clips": media.media_clips,
        "op9_ngram_jaccard": ngram_join.op9_ngram_jaccard,
        "op10_bpe": bpe.op10_bpe,
    }


def oracle_sql() -> dict[str, str]:
    return {
        "op1_chat_formatting": chat.OP1_SQL,
        "op3_exact_topk": topk.OP3_SQL,
    }
