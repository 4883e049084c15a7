"""Queries of this subpackage for the driver's registry, and their SQL twins."""

from __future__ import annotations

from . import bpe, decontaminate, embeddings, html, lines, simhash, sst, substrings, toxicity, warc

QUERIES = {
    "op1_nearest_examples": toxicity.op1_nearest_examples,
    "op2_bpe_automaton": bpe.op2_bpe_automaton,
    "op3_simhash_bktree": simhash.op3_simhash_bktree,
    "op4_token_shards": sst.op4_token_shards,
    "op5_suffix_automata": substrings.op5_suffix_automata,
    "op6_merkle_fixity": warc.op6_merkle_fixity,
    "op7_simhash_windows": decontaminate.op7_simhash_windows,
    "op8_host_suffix_array": html.op8_host_suffix_array,
    "op9_edit_join": lines.op9_edit_join,
    "op10_cap_filters": embeddings.op10_cap_filters,
}

ORACLE_SQL: dict[str, str] = {
    "op6_merkle_fixity": warc.OP6_SQL,
    "op7_simhash_windows": decontaminate.OP7_SQL,
}
