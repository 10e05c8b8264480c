"""Registered queries of the text operators, and their SQL where SQL can express them."""

from __future__ import annotations

from . import chat, decontaminate, lm, packing, pii, quality, records, repeats, sharding, simhash
from .oracles import ORACLES

QUERIES = {
    "op1_suffix_array_intervals": repeats.query,
    "op2_simhash_ball": simhash.query,
    "op3_chat_event_fold": chat.query,
    "op4_stratified_interleave": sharding.query,
    "op5_adaptive_quality": quality.query,
    "op6_binary_records": records.query,
    "op7_template_decontamination": decontaminate.query,
    "op8_weak_supervision_pii": pii.query,
    "op9_bloom_language_model": lm.query,
    "op10_sum_of_squares_packing": packing.query,
}

__all__ = ["ORACLES", "QUERIES"]
