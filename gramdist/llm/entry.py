"""The queries of this subpackage and their SQL."""

from __future__ import annotations

from . import bloom_dedup, chat, compression_rules, kneser_ney, lang_fusion, mil_toxicity, mixing, packing, pu_quality, simhash

QUERIES = {
    "op1_simhash_gray": simhash.op1_simhash_gray,
    "op2_kneser_ney": kneser_ney.op2_kneser_ney,
    "op3_pack_binary": packing.op3_pack_binary,
    "op4_compression_bands": compression_rules.op4_compression_bands,
    "op5_mil_toxicity": mil_toxicity.op5_mil_toxicity,
    "op6_chat_format": chat.op6_chat_format,
    "op7_pu_quality": pu_quality.op7_pu_quality,
    "op8_mix_sources": mixing.op8_mix_sources,
    "op9_bloom_dedup": bloom_dedup.op9_bloom_dedup,
    "op10_lang_fusion": lang_fusion.op10_lang_fusion,
}
ORACLES = {"op6_chat_format": chat.ORACLE, "op8_mix_sources": mixing.ORACLE, "op9_bloom_dedup": bloom_dedup.ORACLE}
