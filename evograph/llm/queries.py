"""The queries of this subpackage and, where SQL can express them, their oracles."""

from __future__ import annotations

from evograph.llm import chat_format, embedding_dedup, html_extract, language_id, minhash_dedup, packing, piece_codec, quality_model, quality_rules, substring_dedup

QUERIES = {
    "op1_recompression": substring_dedup.op1_recompression,
    "op2_co_training": quality_model.op2_co_training,
    "op3_sentencepiece": piece_codec.op3_sentencepiece,
    "op4_language_id": language_id.op4_language_id,
    "op5_pca_tiles": embedding_dedup.op5_pca_tiles,
    "op6_prob_minhash": minhash_dedup.op6_prob_minhash,
    "op7_best_fit": packing.op7_best_fit,
    "op8_quality_rules": quality_rules.op8_quality_rules,
    "op9_chat_format": chat_format.op9_chat_format,
    "op10_html_crf": html_extract.op10_html_crf,
}

ORACLES: dict[str, str] = {
    "op5_pca_tiles": embedding_dedup.OP5_SQL,
    "op1_recompression": substring_dedup.OP1_SQL,
    "op8_quality_rules": quality_rules.OP8_SQL,
    "op9_chat_format": chat_format.OP9_SQL,
}
