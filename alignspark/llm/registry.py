"""Queries and SQL oracles of the corpus operators."""

from __future__ import annotations

from alignspark.llm import bpe, chat, decontaminate, jaccard, langid, quality, secrets, sharding, substrings, tokenids

MODULES = {"op1_jaccard": jaccard, "op2_sharding": sharding, "op3_language": langid, "op4_chat": chat, "op5_secrets": secrets, "op6_token_ids": tokenids, "op7_bpe": bpe, "op8_quality": quality, "op9_decontamination": decontaminate, "op10_substrings": substrings}


def queries():
    return {name: getattr(module, name) for name, module in MODULES.items()}


def oracle_sql():
    out = {}
    for module in MODULES.values():
        out |= getattr(module, "SQL", {})
    return out
