"""Queries and oracle SQL of the subpackage."""

from __future__ import annotations

from importlib import import_module

#: query name -> module; the module holds a function of that name and may hold ORACLE.
QUERIES = {
    "op1_latent_votes": "latent_votes",
    "op2_exact_dedup": "exact_dedup",
    "op3_trie_lm": "trie_lm",
    "op4_simhash_trie": "simhash_trie",
    "op5_ring_sharding": "ring_sharding",
    "op6_suffix_decontam": "suffix_decontam",
    "op7_rank_array_bpe": "rank_array_bpe",
    "op8_longest_match": "longest_match",
    "op9_block_lstm": "block_lstm",
    "op10_snapshot_chat": "snapshot_chat",
}


def queries() -> dict:
    return {name: getattr(import_module(f".{module}", __package__), name) for name, module in QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    modules = {name: import_module(f".{module}", __package__) for name, module in QUERIES.items()}
    return {name: m.ORACLE for name, m in modules.items() if hasattr(m, "ORACLE")}
