"""The registered queries of this folder and the SQL they are held against."""

from __future__ import annotations

from . import bpe, chat, decontaminate, licences, neardup, quality, sharding, substring, topk, toxicity

QUERIES = {f.__name__: f for f in (sharding.op1_virtual_slot_sharding, licences.op2_licence_scan, neardup.op3_ngram_jaccard_join, chat.op4_chat_formatting, topk.op5_voronoi_top_k, quality.op6_quality_classifier, toxicity.op7_toxicity_grammar, bpe.op8_byte_bpe, decontaminate.op9_decontamination, substring.op10_substring_dedup)}
ORACLE = {"op4_chat_formatting": chat.SQL, "op5_voronoi_top_k": topk.SQL, "op9_decontamination": decontaminate.SQL, "op10_substring_dedup": substring.SQL}
